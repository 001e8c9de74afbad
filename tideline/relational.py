"""Queries for the relational operators that the methods are made of: filters, joins, aggregates, windows, set operations."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tideline import oracles as O
from tideline.functions import heuristics as H
from tideline.functions import scalars as X
from tideline.queries import ROAD, SOCIAL, register
from tideline.operators import paths as P
from tideline.plans.schedule import Schedule
from tideline.sources import graphs as G
from tideline.sources.tables import table
from tideline.streaming import windows as S


@register("adjacency_pack", O.plain(O.WEB, "SELECT src, count(*) AS degree, min(dst) AS first_dst, max(dst) AS last_dst FROM edges GROUP BY src"))
def adjacency_pack(s, d):
    return G.pack_adjacency(G.g_web(s, d).edges).select("src", F.size("adj").cast("long").alias("degree"), F.col("adj")[0]["dst"].alias("first_dst"), F.element_at("adj", -1)["dst"].alias("last_dst"))


@register("induced_subgraph", O.plain(ROAD, "SELECT src, dst, weight FROM edges WHERE src < 500 AND dst < 500"))
def induced_subgraph(s, d):
    g = G.g_road(s, d)
    return G.induced(g.edges, g.vertices.where("id < 500").select("id"))


@register("edge_filter_weight", O.plain(ROAD, "SELECT src, dst, weight FROM edges WHERE weight BETWEEN 600 AND 650 AND src < dst"))
def edge_filter_weight(s, d):
    return G.g_road(s, d).edges.where(F.col("weight").between(600, 650) & (F.col("src") < F.col("dst")))


@register("degree_filter", O.plain(ROAD, "SELECT src AS id, count(*) AS degree FROM edges GROUP BY src HAVING count(*) < 4"))
def degree_filter(s, d):
    return G.g_road(s, d).edges.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("degree")).where("degree < 4")


@register("neighbors_join", O.plain(SOCIAL, "SELECT src, dst, weight FROM edges WHERE src IN (1, 5, 9)"))
def neighbors_join(s, d):
    ids = s.createDataFrame([(1,), (5,), (9,)], "src long")
    return G.g_social(s, d).edges.join(ids.hint("shuffle_hash"), "src").select("src", "dst", "weight")


@register("neighbors_broadcast", O.plain(SOCIAL, "SELECT src, dst, weight FROM edges WHERE src IN (1, 5, 9)"))
def neighbors_broadcast(s, d):
    ids = s.createDataFrame([(1,), (5,), (9,)], "src long")
    return G.g_social(s, d).edges.join(F.broadcast(ids), "src").select("src", "dst", "weight")


@register("merge_state", O.plain(ROAD, "SELECT coalesce(a.id, b.id) AS id, coalesce(a.o, 0) AS o, coalesce(b.i, 0) AS i FROM (SELECT src AS id, count(*) AS o FROM edges WHERE src < dst GROUP BY src) a FULL JOIN (SELECT dst AS id, count(*) AS i FROM edges WHERE src < dst GROUP BY dst) b ON a.id = b.id"))
def merge_state(s, d):
    e = G.g_road(s, d).edges.where("src < dst")
    a = e.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("o"))
    return a.join(e.groupBy(F.col("dst").alias("id")).agg(F.count(F.lit(1)).alias("i")), "id", "full_outer").select("id", F.coalesce("o", F.lit(0)).alias("o"), F.coalesce("i", F.lit(0)).alias("i"))


@register("reachable_semi", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")
def reachable_semi(s, d):
    return table(s, d, "customer").select("c_custkey").join(table(s, d, "orders").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_semi")


@register("unreached_anti", O.distances(O.WEB, 0, "SELECT DISTINCT v.id FROM (SELECT src AS id FROM edges UNION SELECT dst FROM edges) v WHERE v.id NOT IN (SELECT id FROM d)"))
def unreached_anti(s, d):
    g = G.g_web(s, d)
    return g.all_vertices().join(P.sssp(g, 0, Schedule(delta=1 << 20)).values().select("id"), "id", "left_anti")


@register("lattice_edges", O.plain(ROAD, "SELECT src, dst, weight FROM edges"))
def lattice_edges(s, d):
    return G.g_road(s, d).edges


@register("knn_exact", O.plain(O.VEC, "SELECT src, dst, weight FROM edges"))
def knn_exact(s, d):
    return G.g_vec(s, d).edges


@register("event_next_asof", "SELECT event_id, coalesce((SELECT epoch_us(min(b.ts)) FROM events b WHERE b.user_id = a.user_id AND b.ts > a.ts), -1) AS next_us FROM events a")
def event_next_asof(s, d):
    e = table(s, d, "events").select("event_id", "user_id", "ts")
    e = e.withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    w = W.partitionBy("user_id").orderBy("us").rangeBetween(1, W.unboundedFollowing)
    return e.select("event_id", F.coalesce(F.min("us").over(w), F.lit(-1)).alias("next_us"))


@register("degree_in_out", O.plain(O.WEB, "SELECT id, CAST(sum(o) AS BIGINT) AS outs, CAST(sum(i) AS BIGINT) AS ins FROM (SELECT src AS id, 1 AS o, 0 AS i FROM edges UNION ALL SELECT dst, 0, 1 FROM edges) GROUP BY id"))
def degree_in_out(s, d):
    e = G.g_web(s, d).edges
    both = e.select(F.col("src").alias("id"), F.lit(1).alias("o"), F.lit(0).alias("i")).unionByName(e.select(F.col("dst").alias("id"), F.lit(0).alias("o"), F.lit(1).alias("i")))
    return both.groupBy("id").agg(F.sum("o").alias("outs"), F.sum("i").alias("ins"))


@register("degree_histogram", O.plain(SOCIAL, "SELECT degree, count(*) AS n FROM (SELECT src, count(*) AS degree FROM edges GROUP BY src) GROUP BY degree"))
def degree_histogram(s, d):
    return G.g_social(s, d).edges.groupBy("src").agg(F.count(F.lit(1)).alias("degree")).groupBy("degree").agg(F.count(F.lit(1)).alias("n"))


@register("weight_summary", O.plain(SOCIAL, "SELECT min(weight) AS low, max(weight) AS high, CAST(sum(weight) AS BIGINT) AS total, count(DISTINCT weight) AS kinds, bool_or(weight = 1) AS has_one FROM edges"))
def weight_summary(s, d):
    return G.g_social(s, d).edges.agg(F.min("weight").alias("low"), F.max("weight").alias("high"), F.sum("weight").alias("total"), F.countDistinct("weight").alias("kinds"), F.bool_or(F.col("weight") == 1).alias("has_one"))


@register("edge_weight_cube", "SELECT r_name, c_mktsegment, count(*) AS n, CAST(sum(CAST(floor(o_totalprice) AS BIGINT)) AS BIGINT) AS w, grouping_id(r_name, c_mktsegment) AS level FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY CUBE (r_name, c_mktsegment)")
def edge_weight_cube(s, d):
    o = table(s, d, "orders").select("o_custkey", F.floor("o_totalprice").cast("long").alias("p"))
    x = o.join(table(s, d, "customer").select("c_custkey", "c_nationkey", "c_mktsegment"), F.col("o_custkey") == F.col("c_custkey")).join(table(s, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(table(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return x.cube("r_name", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"), F.sum("p").alias("w"), F.grouping_id().alias("level"))


@register("edge_weight_rollup", "SELECT coalesce(n_regionkey, -1) AS region, coalesce(c_nationkey, -1) AS nation, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY ROLLUP (n_regionkey, c_nationkey)")
def edge_weight_rollup(s, d):
    return table(s, d, "customer").join(table(s, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).rollup("n_regionkey", "c_nationkey").agg(F.count(F.lit(1)).alias("n")).select(F.coalesce("n_regionkey", F.lit(-1)).alias("region"), F.coalesce("c_nationkey", F.lit(-1)).alias("nation"), "n")


@register("bucket_prefix_sum", O.plain(SOCIAL, "SELECT bucket, n, CAST(sum(n) OVER (ORDER BY bucket) AS BIGINT) AS upto FROM (SELECT weight // 64 AS bucket, count(*) AS n FROM edges GROUP BY 1)"))
def bucket_prefix_sum(s, d):
    n = G.g_social(s, d).edges.groupBy(X.bucket_of(F.col("weight"), 64).alias("bucket")).agg(F.count(F.lit(1)).alias("n"))
    return n.withColumn("upto", F.sum("n").over(W.orderBy("bucket").rowsBetween(W.unboundedPreceding, 0)))


@register("core_rank", O.core(O.WEB_SYM, "SELECT id, coreness, rank() OVER (ORDER BY coreness DESC) AS r, dense_rank() OVER (ORDER BY coreness DESC) AS dr FROM core"))
def core_rank(s, d):
    from tideline.operators import kcore as K

    core = K.coreness(K.kcore(G.g_web(s, d, True))).select("id", "coreness")
    # Windows run over the distinct values only; rows take their value's rank by a join.
    w = W.orderBy(F.desc("coreness"))
    n = core.groupBy("coreness").agg(F.count(F.lit(1)).alias("n"))
    rank = n.select("coreness", (F.coalesce(F.sum("n").over(w.rowsBetween(W.unboundedPreceding, -1)), F.lit(0)) + 1).cast("long").alias("r"), F.row_number().over(w).cast("long").alias("dr"))
    return core.join(rank, "coreness").select("id", "coreness", "r", "dr")


@register("top_neighbors", O.plain(SOCIAL, "SELECT src, dst, weight FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY weight, dst) AS r FROM edges) WHERE r <= 3"))
def top_neighbors(s, d):
    w = W.partitionBy("src").orderBy("weight", "dst")
    return G.g_social(s, d).edges.withColumn("r", F.row_number().over(w)).where("r <= 3").select("src", "dst", "weight")


@register("event_chain", O.plain(O.TIME, "SELECT src, dst, weight FROM edges"))
def event_chain(s, d):
    return G.g_time(s, d).edges


@register("conversation_chain", O.plain(O.TURN, "SELECT src, dst, weight FROM edges"))
def conversation_chain(s, d):
    return G.g_turn(s, d).edges


@register("distance_deciles", O.distances(SOCIAL, 0, "SELECT part, count(*) AS n, min(dist) AS low, max(dist) AS high FROM (SELECT dist, ntile(10) OVER (ORDER BY dist, id) AS part FROM d) GROUP BY part"))
def distance_deciles(s, d):
    x = P.sssp(G.g_social(s, d), 0, Schedule(delta=64)).values("dist")
    return G.tiles(x, 10, ["dist", "id"]).groupBy("part").agg(F.count(F.lit(1)).alias("n"), F.min("dist").alias("low"), F.max("dist").alias("high"))


@register("farthest_k", O.distances(SOCIAL, 0, "SELECT id, dist FROM d ORDER BY dist DESC, id LIMIT 10"))
def farthest_k(s, d):
    return P.sssp(G.g_social(s, d), 0, Schedule(delta=64)).values("dist").orderBy(F.desc("dist"), "id").limit(10)


@register("core_topk", O.core(O.WEB_SYM, "SELECT id, coreness FROM core ORDER BY coreness DESC, id LIMIT 10"))
def core_topk(s, d):
    from tideline.operators import kcore as K

    return K.coreness(K.kcore(G.g_web(s, d, True))).orderBy(F.desc("coreness"), "id").limit(10)


def _near(s, d, v):
    return P.k_hop(G.g_road(s, d), v, 3).select("id")


_HOPS = "h(id, n, v) AS (SELECT id, 0, id FROM (VALUES (0::BIGINT), (27::BIGINT)) t(id) UNION SELECT e.dst, h.n + 1, h.v FROM h JOIN edges e ON e.src = h.id WHERE h.n < 3)"


@register("k_hop", f"WITH RECURSIVE {ROAD}, {_HOPS} SELECT id, min(n) AS hops FROM h WHERE v = 0 GROUP BY id")
def k_hop(s, d):
    return P.k_hop(G.g_road(s, d), 0, 3)


@register("reach_intersect", f"WITH RECURSIVE {ROAD}, {_HOPS} SELECT id FROM h WHERE v = 0 INTERSECT SELECT id FROM h WHERE v = 27")
def reach_intersect(s, d):
    return _near(s, d, 0).intersect(_near(s, d, 27))


@register("reach_except", f"WITH RECURSIVE {ROAD}, {_HOPS} SELECT id FROM h WHERE v = 0 EXCEPT SELECT id FROM h WHERE v = 27")
def reach_except(s, d):
    return _near(s, d, 0).exceptAll(_near(s, d, 27))


@register("reach_union", f"WITH RECURSIVE {ROAD}, {_HOPS} SELECT DISTINCT id FROM h")
def reach_union(s, d):
    return _near(s, d, 0).union(_near(s, d, 27)).distinct()


@register("components_web", O.labels(O.WEB_SYM, "SELECT src, dst FROM edges", "SELECT DISTINCT src AS id FROM edges", "SELECT id, low AS component FROM l"))
def components_web(s, d):
    from tideline.operators.components import connected_components

    return connected_components(G.g_web(s, d).edges, "src", "dst")


@register("bucket_of", O.plain(ROAD, "SELECT src, dst, weight // 64 AS bucket FROM edges"))
def bucket_of(s, d):
    return G.g_road(s, d).edges.select("src", "dst", X.bucket_of(F.col("weight"), 64).alias("bucket"))


@register("great_circle", f"WITH {ROAD} SELECT id, CAST(floor(round(2 * 6371.0088 * asin(sqrt(least(1.0, pow(sin((radians(12.0) - radians(y)) / 2), 2) + cos(radians(y)) * cos(radians(12.0)) * pow(sin((radians(40.0) - radians(x)) / 2), 2)))), 3)) AS BIGINT) AS km FROM cells")
def great_circle(s, d):
    c = G.road_cells(s, d, 28)
    return c.select("id", F.floor(F.round(H.great_circle_km(F.col("x"), F.col("y"), F.lit(40.0), F.lit(12.0)), 3)).cast("long").alias("km"))


@register("event_props_k", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def event_props_k(s, d):
    return table(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


@register("url_host", "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) AS host FROM pages")
def url_host(s, d):
    return table(s, d, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/?#]*)", 1).alias("host"))


@register("doc_words", "SELECT doc_id, len(list_distinct(regexp_extract_all(lower(text), '[a-z]{4,}'))) AS n FROM documents")
def doc_words(s, d):
    return table(s, d, "documents").select("doc_id", F.size(F.array_distinct(X.long_words(F.col("text")))).cast("long").alias("n"))


@register("attribute_map", "SELECT n_nationkey, r_name AS region FROM nation JOIN region ON n_regionkey = r_regionkey")
def attribute_map(s, d):
    """A small dimension as one map, looked up by key."""
    m = table(s, d, "region").agg(F.map_from_entries(F.collect_list(F.struct("r_regionkey", "r_name"))).alias("m"))
    return table(s, d, "nation").join(F.broadcast(m)).select("n_nationkey", F.element_at("m", F.col("n_regionkey")).alias("region"))


@register("suggest_delta", O.plain(SOCIAL, "SELECT true AS power_of_two, true AS within FROM (SELECT 1)"))
def suggest_delta(s, d):
    x = X.suggest_delta(G.g_social(s, d).edges)
    return s.createDataFrame([(x & (x - 1) == 0, 1 <= x <= 1 << 17)], "power_of_two boolean, within boolean")


@register("frontier_estimate", O.plain(SOCIAL, "SELECT weight // 256 AS bucket, count(DISTINCT dst) AS targets, true AS estimate_within_a_fifth FROM edges GROUP BY 1"))
def frontier_estimate(s, d):
    """The sketch's estimate of a frontier's size, held against the exact number."""
    n = G.g_social(s, d).edges.groupBy(X.bucket_of(F.col("weight"), 256).alias("bucket")).agg(F.approx_count_distinct("dst").alias("e"), F.countDistinct("dst").alias("targets"))
    return n.select("bucket", "targets", (F.abs(F.col("e") - F.col("targets")) <= 0.2 * F.col("targets")).alias("estimate_within_a_fifth"))


register("events_tumbling", "SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")(lambda s, d: S.tumbling(table(s, d, "events"), "1 hour"))
register("events_sliding", "SELECT start, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 30 MINUTE, ts), time_bucket(INTERVAL 30 MINUTE, ts) - INTERVAL 30 MINUTE]) AS start FROM events) GROUP BY start")(lambda s, d: S.sliding(table(s, d, "events"), "1 hour", "30 minutes"))
register("events_session", """SELECT user_id, min(ts) AS start, count(*) AS n FROM (
  SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS g FROM (
    SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 2 HOUR THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, g""")(lambda s, d: S.sessions(table(s, d, "events"), "2 hours"))
