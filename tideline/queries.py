"""The registered queries: methods, variants, baselines, measures, workloads and the operators around them.

Each entry is (function of session and table folder, SQL for DuckDB or None). Where an answer can't be written as SQL, the
query returns a verdict (mismatches, bounds that hold) whose expected row is the SQL.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tideline import oracles as O
from tideline.functions import heuristics as H
from tideline.operators import kcore as K
from tideline.operators import paths as P
from tideline.operators import setcover as C
from tideline.operators import verify as V
from tideline.plans.schedule import PRESETS, UNBOUNDED, Schedule
from tideline.sources import graphs as G
from tideline.sources.tables import table

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}

ROAD, SOCIAL, SOCIAL_LOG = O.road(28), O.social(), O.social(True)


def register(name: str, sql: str | None = None):
    def keep(f: Callable[[SparkSession, str], DataFrame]):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return keep


def _sssp(name: str, graph: Callable, sql_graph: str, source: int, schedule: Schedule, method: Callable = P.sssp) -> None:
    register(name, O.distances(sql_graph, source))(lambda s, d: method(graph(s, d), source, schedule).values("dist"))


# Shortest paths -----------------------------------------------------------------------------------------------
_sssp("sssp_fused", G.g_road, ROAD, 0, Schedule(update="eager_fused", delta=16_384))
_sssp("sssp_eager", G.g_social, SOCIAL, 0, PRESETS["eager_plain"].with_(delta=64))
_sssp("sssp_lazy", G.g_social, SOCIAL, 0, Schedule(delta=32))
_sssp("sssp_pull", G.g_social, SOCIAL, 0, Schedule(delta=64, direction="pull"))
_sssp("sssp_auto", G.g_social, SOCIAL, 0, Schedule(delta=64, direction="auto"))
_sssp("sssp_salted", G.g_social, SOCIAL, 0, Schedule(delta=64, balance="salted"))
_sssp("sssp_edge_balanced", G.g_social, SOCIAL, 0, Schedule(delta=64, balance="edge"))
_sssp("sssp_delta_16", G.g_social, SOCIAL, 0, Schedule(delta=16))
_sssp("sssp_delta_1024", G.g_social, SOCIAL, 0, Schedule(delta=1024))
_sssp("sssp_delta_1", lambda s, d: G.g_social(s, d, True), SOCIAL_LOG, 0, Schedule(delta=1))
_sssp("sssp_hops", G.g_social, SOCIAL, 0, Schedule(delta=64, plan_hops=3))
_sssp("sssp_overflow", G.g_social, SOCIAL, 0, Schedule(delta=64, open_buckets=2))
_sssp("sssp_lazy_callback", G.g_social, SOCIAL, 0, PRESETS["lazy_callback"].with_(delta=64))
_sssp("sssp_hash_blocks", G.g_social, SOCIAL, 0, Schedule(update="eager_fused", delta=32, layout="hash"))
_sssp("sssp_web", lambda s, d: G.g_web(s, d, True), O.WEB_SYM, 0, Schedule(delta=1024))
_sssp("sssp_vec", G.g_vec, O.VEC, 0, Schedule(delta=2048))
_sssp("sssp_time", G.g_time, O.TIME, 0, Schedule(update="eager_fused", delta=1 << 22))
_sssp("sssp_road_wide", lambda s, d: G.g_road(s, d, 28, True), O.road(28, True), 0, Schedule(update="eager_fused", delta=4096))
_sssp("wbfs_lazy", lambda s, d: G.g_social(s, d, True), SOCIAL_LOG, 0, Schedule(), P.wbfs)
_sssp("wbfs_eager_fused", lambda s, d: G.g_social(s, d, True), SOCIAL_LOG, 0, Schedule(update="eager_fused"), P.wbfs)
_sssp("wbfs_web", lambda s, d: G.log_weights(G.g_web(s, d, True)), O.log_weights(O.WEB_SYM), 0, Schedule(), P.wbfs)
_sssp("bf_push", G.g_social, SOCIAL, 0, PRESETS["unordered_push"])
_sssp("bf_pull", G.g_social, SOCIAL, 0, Schedule(delta=UNBOUNDED, direction="pull"))
_sssp("bf_switching", G.g_social, SOCIAL, 0, PRESETS["unordered_switching"])
_sssp("sssp_relaxed", G.g_social, SOCIAL, 0, Schedule(width=4, delta=16))


@register("sssp_many", O.many_distances(SOCIAL, list(range(10))))
def sssp_many(s, d):
    return P.many(G.g_social(s, d), list(range(10)), 64)


@register("widest_path", O.widest(SOCIAL, 0, 1000))
def widest_path(s, d):
    return P.widest(G.g_social(s, d), 0, 1000, Schedule(delta=64)).values("width")


@register("sssp_parent_check", O.distances(SOCIAL, 0, "SELECT count(*) AS reached, 0::BIGINT AS loose FROM d"))
def sssp_parent_check(s, d):
    g = G.g_social(s, d)
    t = P.parents(g, P.sssp(g, 0, Schedule(delta=64)), 0)
    up = t.join(g.edges, (F.col("parent") == F.col("src")) & (F.col("id") == F.col("dst")), "left").join(t.select(F.col("id").alias("pid"), F.col("dist").alias("pd")), F.col("parent") == F.col("pid"), "left")
    return up.agg(F.count(F.lit(1)).alias("reached"), F.count(F.when((F.col("id") != 0) & ~F.coalesce(F.col("pd") + F.col("weight") == F.col("dist"), F.lit(False)), 1)).alias("loose"))


def _last(s, d):
    """The lattice vertex with the largest id, as a far target."""
    return G.g_road(s, d).all_vertices().agg(F.max("id")).first()[0]


_FAR = O.distances(ROAD, 0, "SELECT 0::BIGINT AS source, (SELECT max(src) FROM edges) AS target, (SELECT dist FROM d WHERE id = (SELECT max(src) FROM edges)) AS dist")


def _mid(sql_graph: str) -> str:
    return O.distances(sql_graph, 0, "SELECT 0::BIGINT AS source, 500::BIGINT AS target, (SELECT dist FROM d WHERE id = 500) AS dist")


@register("ppsp", _mid(ROAD))
def ppsp(s, d):
    return P.distance_to(P.ppsp(G.g_road(s, d), 0, 500, Schedule(update="eager_fused", delta=4096), prune=False), 0, 500)


@register("ppsp_lazy", _mid(SOCIAL))
def ppsp_lazy(s, d):
    return P.distance_to(P.ppsp(G.g_social(s, d), 0, 500, Schedule(delta=32)), 0, 500)


@register("ppsp_unordered", _mid(SOCIAL))
def ppsp_unordered(s, d):
    return P.distance_to(P.bellman_ford(G.g_social(s, d), 0), 0, 500)


@register("ppsp_edge_cases", "SELECT * FROM (VALUES (0::BIGINT, 0::BIGINT, 0::BIGINT), (0::BIGINT, -1::BIGINT, -1::BIGINT)) t(source, target, dist)")
def ppsp_edge_cases(s, d):
    g = G.g_social(s, d)
    both = P.distance_to(P.ppsp(g, 0, 0, Schedule(delta=64)), 0, 0).unionByName(P.distance_to(P.ppsp(g, 0, -1, Schedule(delta=1024)), 0, -1))
    return both.withColumn("dist", F.coalesce("dist", F.lit(-1)))  # null: no path


@register("ppsp_batch10", O.many_distances(SOCIAL, list(range(10)), "SELECT source, id AS target, dist FROM d WHERE id = source + 100"))
def ppsp_batch10(s, d):
    pairs = {i: i + 100 for i in range(10)}
    goal = s.createDataFrame(list(pairs.items()), "source long, target long")
    return P.many(G.g_social(s, d), list(pairs), 64, pairs).join(F.broadcast(goal), "source").where("id = target").select("source", "target", "dist")


@register("astar_lattice", _FAR)
def astar_lattice(s, d):
    g, t = G.g_road(s, d), _last(s, d)
    return P.distance_to(P.astar(g, 0, t, H.manhattan(g.vertices, t, 500), Schedule(update="eager_fused", delta=4096)), 0, t)


@register("astar_lazy", _mid(ROAD))
def astar_lazy(s, d):
    g = G.g_road(s, d, 28)
    return P.distance_to(P.astar(g, 0, 500, H.manhattan(g.vertices, 500, 500), Schedule(delta=16_384)), 0, 500)


@register("astar_vector", O.distances(O.VEC, 0, "SELECT 0::BIGINT AS source, 7::BIGINT AS target, (SELECT dist FROM d WHERE id = 7) AS dist"))
def astar_vector(s, d):
    g = G.g_vec(s, d)
    v = table(s, d, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("v"))
    return P.distance_to(P.astar(g, 0, 7, H.vector(v, 7, 1000.0), Schedule(delta=1024)), 0, 7)


@register("astar_unordered", _mid(ROAD))
def astar_unordered(s, d):
    return P.distance_to(P.sssp(G.g_road(s, d), 0, Schedule(update="eager_fused", delta=UNBOUNDED)), 0, 500)


def _between(graph: Callable, sql_graph: str, name: str, target: int, schedule: Schedule) -> None:
    @register(name, O.distances(sql_graph, 0, f"SELECT 0::BIGINT AS source, {target}::BIGINT AS target, (SELECT dist FROM d WHERE id = {target}) AS dist"))
    def run(s, d):
        return P.distance_to(P.ppsp(graph(s, d), 0, target, schedule), 0, target)


_between(lambda s, d: G.g_web(s, d, True), O.WEB_SYM, "ppsp_web", 1_000_000_251, Schedule(delta=512))
_between(G.g_vec, O.VEC, "ppsp_vector", 7, Schedule(delta=1024))


@register("astar_great_circle", _mid(ROAD))
def astar_great_circle(s, d):
    """Cells as degrees of longitude and latitude. A step is a degree, at most 111.2 km, and costs at least 500: 4 a km is never too much."""
    g = G.g_road(s, d)
    return P.distance_to(P.astar(g, 0, 500, H.great_circle(g.vertices, 500, 4.0), Schedule(update="eager_fused", delta=4096)), 0, 500)


@register("ppsp_balanced10", O.distances(SOCIAL, 0, "SELECT 0::BIGINT AS source, id AS target, dist FROM (SELECT id, dist, row_number() OVER (PARTITION BY part ORDER BY dist, id) AS r FROM (SELECT id, dist, ntile(10) OVER (ORDER BY dist, id) AS part FROM d)) WHERE r = 1"))
def ppsp_balanced10(s, d):
    """One target for each tenth of the distances from the source."""
    g = G.g_social(s, d)
    out = None
    for t in P.pairs_by_distance(g, 0):
        one = P.distance_to(P.ppsp(g, 0, t, Schedule(delta=256)), 0, t)
        out = one if out is None else out.unionByName(one)
    return out


@register("astar_vs_ppsp_visited", O.distances(ROAD, 0, "SELECT (SELECT dist FROM d WHERE id = 500) AS dist, true AS same, true AS fewer"))
def astar_vs_ppsp_visited(s, d):
    g, how = G.g_road(s, d), Schedule(delta=8192, update="eager_fused")
    a = P.astar(g, 0, 500, H.manhattan(g.vertices, 500, 500), how)
    b = P.ppsp(g, 0, 500, how, prune=False)
    x, y = (r.state.where("id = 500").first()["value"] for r in (a, b))
    return s.createDataFrame([(x, x == y, a.metrics.visited <= b.metrics.visited)], "dist long, same boolean, fewer boolean")


@register("heuristic_consistency", "SELECT * FROM (VALUES ('euclidean', 0::BIGINT), ('manhattan', 0::BIGINT), ('zero', 0::BIGINT)) t(estimate, violations)")
def heuristic_consistency(s, d):
    g = G.g_road(s, d)
    all_ = {"zero": H.zero(g.vertices), "manhattan": H.manhattan(g.vertices, 500, 500), "euclidean": H.euclidean(g.vertices, 500, 500.0)}
    rows = [P.check_estimate(g, h).select(F.lit(n).alias("estimate"), "violations") for n, h in all_.items()]
    return rows[0].unionByName(rows[1]).unionByName(rows[2])


# Coreness -------------------------------------------------------------------------------------------------------
register("kcore_count", O.core(SOCIAL))(lambda s, d: K.coreness(K.kcore(G.g_social(s, d))))
register("kcore_lazy", O.core(O.TRADE))(lambda s, d: K.coreness(K.kcore(G.g_trade(s, d), Schedule())))
register("kcore_eager", O.core(ROAD))(lambda s, d: K.coreness(K.kcore(G.g_road(s, d), Schedule(update="eager", fuse_limit=0))))
register("kcore_web", O.core(O.WEB_SYM))(lambda s, d: K.coreness(K.kcore(G.g_web(s, d, True))))
register("kcore_road", O.core(ROAD))(lambda s, d: K.coreness(K.kcore(G.g_road(s, d))))
register("kcore_lazy_callback", O.core(O.WEB_SYM))(lambda s, d: K.coreness(K.kcore(G.g_web(s, d, True), Schedule(callback=True))))
register("kcore_hindex", O.core(SOCIAL))(lambda s, d: K.h_index_rounds(G.Graph(G.social_pairs(s, d)), dealt=True)[0])
register("kcore_rescan", O.core(O.WEB_SYM))(lambda s, d: K.rescan(G.g_web(s, d, True)))
register("kcore_histogram", O.core(O.WEB_SYM, "SELECT coreness, count(*) AS n, CAST(sum(count(*)) OVER (ORDER BY coreness DESC) AS BIGINT) AS at_least FROM core GROUP BY coreness"))(lambda s, d: K.histogram(K.coreness(K.kcore(G.g_web(s, d, True)))))


@register("kcore_components_k", O.core(O.WEB_SYM, """SELECT id, min(b) AS component FROM (
  WITH RECURSIVE ce AS (SELECT e.src, e.dst FROM edges e JOIN core a ON a.id = e.src AND a.coreness >= 2 JOIN core b ON b.id = e.dst AND b.coreness >= 2),
  l(id, low) USING KEY (id) AS (SELECT id, id FROM core WHERE coreness >= 2 UNION SELECT e.dst, min(l.low) FROM l JOIN ce e ON e.src = l.id JOIN recurring.l o ON o.id = e.dst AND l.low < o.low GROUP BY e.dst)
  SELECT id, low AS b FROM l) GROUP BY id"""))
def kcore_components_k(s, d):
    g = G.g_web(s, d, True)
    return K.subgraph(g, K.coreness(K.kcore(g)), 2)


# Set cover ------------------------------------------------------------------------------------------------------
_SYSTEMS = {
    "supplier": (G.s_supplier, "SELECT count(DISTINCT l_partkey) AS n_elements, 0::BIGINT AS uncovered, 0::BIGINT AS empty_picks FROM lineitem"),
    "customer": (G.s_customer, "SELECT count(DISTINCT l_partkey) AS n_elements, 0::BIGINT AS uncovered, 0::BIGINT AS empty_picks FROM orders JOIN lineitem ON o_orderkey = l_orderkey"),
    "vertex": (lambda s, d: G.s_neighbours(G.g_road(s, d)), O.plain(ROAD, "SELECT count(DISTINCT src) AS n_elements, 0::BIGINT AS uncovered, 0::BIGINT AS empty_picks FROM edges")),
    "social": (lambda s, d: G.s_neighbours(G.g_social(s, d)), O.plain(SOCIAL, "SELECT count(DISTINCT src) AS n_elements, 0::BIGINT AS uncovered, 0::BIGINT AS empty_picks FROM edges")),
    "document": (G.s_document, "SELECT count(DISTINCT w) AS n_elements, 0::BIGINT AS uncovered, 0::BIGINT AS empty_picks FROM (SELECT unnest(regexp_extract_all(lower(text), '[a-z]{4,}')) AS w FROM documents)"),
}


def _cover(name: str) -> None:
    make, sql = _SYSTEMS[name]

    @register(f"set_cover_{name}", sql)
    def run(s, d):
        system = make(s, d)
        # The systems other than the suppliers' take wider buckets and looser elections: fewer rounds, larger covers.
        eps, accept = (0.1, 0.1) if name == "supplier" else (0.5, 0.25)
        return C.verdict(system, C.set_cover(system, eps, accept).chosen)


for _name in _SYSTEMS:
    _cover(_name)


@register("set_cover_weighted", _SYSTEMS["supplier"][1])
def set_cover_weighted(s, d):
    system = G.s_supplier(s, d)
    return C.verdict(system, C.set_cover(system, costs=G.supplier_costs(s, d)).chosen)


_GREEDY = """WITH RECURSIVE sys AS (SELECT DISTINCT l_suppkey AS s, l_partkey AS e FROM lineitem),
g(step, set_id, gain, held) AS (
  SELECT 0, CAST(NULL AS BIGINT), CAST(0 AS BIGINT), CAST([] AS BIGINT[])
  UNION ALL
  SELECT step + 1, s, n, list_concat(held, es) FROM (
    SELECT g.step, g.held, p.s, count(*) AS n, list(p.e) AS es, row_number() OVER (ORDER BY count(*) DESC, p.s) AS r
    FROM g JOIN sys p ON NOT list_contains(g.held, p.e) GROUP BY g.step, g.held, p.s) WHERE r = 1)
"""


@register("set_cover_quality", _GREEDY + "SELECT (SELECT count(DISTINCT e) FROM sys) AS n_elements, 0::BIGINT AS uncovered, max(step)::BIGINT AS greedy_sets, true AS within_bound FROM g")
def set_cover_quality(s, d):
    return V.cover_quality(G.s_supplier(s, d), 0.1, 0.1)


@register("greedy_cover_supplier", _GREEDY + "SELECT CAST(step AS INTEGER) AS step, set_id, gain FROM g WHERE step > 0")
def greedy_cover_supplier(s, d):
    return C.greedy(G.s_supplier(s, d))


# Measures -------------------------------------------------------------------------------------------------------
_FAREST = "SELECT count(*) AS reached, max(dist) AS farthest"


@register("fusion_rounds", O.distances(ROAD, 0, f"{_FAREST}, 0::BIGINT AS mismatches, true AS fewer_rounds FROM d"))
def fusion_rounds(s, d):
    return V.fusion(G.g_road(s, d, 28), 0, 16_384)


@register("fusion_rounds_social", O.distances(SOCIAL, 0, f"{_FAREST}, 0::BIGINT AS mismatches, true AS fewer_rounds FROM d"))
def fusion_rounds_social(s, d):
    return V.fusion(G.g_social(s, d), 0, 64)


@register("fusion_rounds_vector", O.distances(O.VEC, 0, f"{_FAREST}, 0::BIGINT AS mismatches, true AS fewer_rounds FROM d"))
def fusion_rounds_vector(s, d):
    return V.fusion(G.g_vec(s, d), 0, 2048)


@register("fusion_rounds_web", O.distances(O.WEB_SYM, 0, f"{_FAREST}, 0::BIGINT AS mismatches, true AS fewer_rounds FROM d"))
def fusion_rounds_web(s, d):
    return V.fusion(G.g_web(s, d, True), 0, 512)


_CORES = "SELECT count(*) AS vertices, max(coreness) AS degeneracy, 0::BIGINT AS mismatches, true AS counts_fewer_inserts FROM core"


@register("update_modes", O.core(ROAD, _CORES))
def update_modes(s, d):
    return V.update_modes(G.g_road(s, d))


@register("update_modes_trade", O.core(O.TRADE, _CORES))
def update_modes_trade(s, d):
    return V.update_modes(G.g_trade(s, d))


@register("update_modes_paths", O.distances(SOCIAL, 0, f"{_FAREST}, 0::BIGINT AS mismatches, true AS moves_within_sent FROM d"))
def update_modes_paths(s, d):
    return V.update_modes_paths(G.g_social(s, d), 0, 64)


_WIDTHS = [1 << k for k in range(18)]


@register("delta_sweep", O.distances(SOCIAL, 0, f"SELECT CAST(pow(2, k) AS BIGINT) AS delta, reached, farthest, 0::BIGINT AS mismatches, true AS buckets_fall FROM range(18) t(k), ({_FAREST} FROM d)"))
def delta_sweep(s, d):
    return V.delta_sweep(G.g_social(s, d), 0, _WIDTHS)


@register("work_efficiency", O.distances(O.road(28, True), 0, f"{_FAREST}, true AS ordered_relaxes_less FROM d"))
def work_efficiency(s, d):
    return V.work(G.g_road(s, d, 28, True), 0)


@register("order_of_buckets", O.distances(SOCIAL, 0, f"{_FAREST}, true AS monotone, true AS rounds_at_least_buckets, 0::BIGINT AS violations FROM d"))
def order_of_buckets(s, d):
    return V.bucket_order(G.g_social(s, d), 0)


# Graphs -----------------------------------------------------------------------------------------------------------
_SUM = "SELECT count(*) AS n_edges, CAST(sum(weight) AS BIGINT) AS weights, CAST(sum(src * 31 + dst) AS BIGINT) AS ids FROM edges"


def _graph(name: str, make: Callable, sql: str) -> None:
    register(f"graph_{name}", O.plain(sql, _SUM))(lambda s, d: make(s, d).edges.agg(F.count(F.lit(1)).alias("n_edges"), F.sum("weight").alias("weights"), F.sum(F.col("src") * 31 + F.col("dst")).alias("ids")))


for _n, _m, _q in (("road", G.g_road, ROAD), ("social", G.g_social, SOCIAL), ("social_log", lambda s, d: G.g_social(s, d, True), SOCIAL_LOG), ("trade", G.g_trade, O.TRADE), ("web", G.g_web, O.WEB), ("vec", G.g_vec, O.VEC), ("time", G.g_time, O.TIME), ("turn", G.g_turn, O.TURN), ("road_wide", lambda s, d: G.g_road(s, d, 28, True), O.road(28, True))):
    _graph(_n, _m, _q)


def entries() -> tuple[dict, dict]:
    """All queries and their SQL, with the relational operators around the methods."""
    from tideline import relational  # noqa: F401

    return QUERIES, SQL
