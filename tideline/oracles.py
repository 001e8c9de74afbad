"""DuckDB texts of graphs and exact answers, for the SQL beside each registered query."""

from __future__ import annotations


def road(days: int = 28, wide: bool = False) -> str:
    c, w = ("sum(p) % 999 + 1", 1) if wide else ("sum(p) % 500", 500)
    return f"""cells AS (
  SELECT x * 25 + y AS id, x, y, CAST({c} AS BIGINT) AS c FROM (
    SELECT CAST(floor(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) / {days}) AS BIGINT) AS x,
           CAST(c_nationkey AS BIGINT) AS y, CAST(floor(o_totalprice) AS BIGINT) AS p
    FROM orders JOIN customer ON o_custkey = c_custkey) GROUP BY x, y),
edges AS (
  SELECT a.id AS src, b.id AS dst, CAST({w} + (a.c + b.c) // 2 AS BIGINT) AS weight
  FROM cells a JOIN (VALUES (0, 1), (0, -1), (1, 0), (-1, 0)) s(dx, dy) ON true JOIN cells b ON b.x = a.x + dx AND b.y = a.y + dy)"""


def social(log_weights: bool = False) -> str:
    most = "(SELECT greatest(1, CAST(floor(log2(count(DISTINCT src))) AS BIGINT) - 1) FROM pairs)" if log_weights else "999"
    return f"""items AS (SELECT DISTINCT l_orderkey AS o, l_partkey AS p FROM lineitem),
pairs AS (SELECT DISTINCT a.p AS src, b.p AS dst FROM items a JOIN items b ON a.o = b.o AND a.p <> b.p),
edges AS (SELECT src, dst, CAST((7919 * src + 104729 * dst) % {most} + 1 AS BIGINT) AS weight FROM pairs)"""


TRADE = """bought AS (SELECT DISTINCT o_custkey AS a, 1000000 + l_partkey AS b FROM orders JOIN lineitem ON o_orderkey = l_orderkey),
edges AS (SELECT a AS src, b AS dst, 1::BIGINT AS weight FROM bought UNION ALL SELECT b, a, 1 FROM bought)"""

WEB = """links AS (SELECT DISTINCT page_id, href FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages) WHERE href <> ''),
targets AS (SELECT href, 1000000000 + row_number() OVER (ORDER BY encode(href)) - 1 AS id FROM (SELECT DISTINCT href FROM links)),
edges AS (SELECT page_id AS src, id AS dst, CAST((7919 * page_id + 104729 * id) % 999 + 1 AS BIGINT) AS weight FROM links JOIN targets USING (href))"""

WEB_SYM = WEB.replace("edges AS", "one AS") + """,
edges AS (SELECT src, dst, min(weight) AS weight FROM (SELECT * FROM one UNION ALL SELECT dst, src, weight FROM one) GROUP BY src, dst)"""

VEC = """v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings),
near AS (SELECT src, dst, d, row_number() OVER (PARTITION BY src ORDER BY d, dst) AS r FROM (
  SELECT a.vec_id AS src, b.vec_id AS dst, list_distance(a.e, b.e) AS d FROM v a JOIN v b ON a.vec_id <> b.vec_id)),
edges AS (SELECT src, dst, CAST(ceil(round(d * 1000, 6)) AS BIGINT) AS weight FROM near WHERE r <= 5)"""

TIME = """nxt AS (
  SELECT event_id AS src, lead(event_id) OVER w AS dst, floor((epoch_us(lead(ts) OVER w) - epoch_us(ts)) / 1000000) + 1 AS weight FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)
  UNION ALL
  SELECT event_id, lead(event_id) OVER w, floor((epoch_us(lead(ts) OVER w) - epoch_us(ts)) / 1000000) + 1 FROM events WINDOW w AS (PARTITION BY event_type ORDER BY ts, event_id)),
edges AS (SELECT src, dst, CAST(min(weight) AS BIGINT) AS weight FROM nxt WHERE dst IS NOT NULL GROUP BY src, dst)"""

TURN = """edges AS (SELECT conv_id * 1000 + turn AS src, conv_id * 1000 + nxt AS dst, nxt - turn AS weight FROM (
  SELECT conv_id, turn, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS nxt FROM (SELECT DISTINCT conv_id, turn FROM conversations)) WHERE nxt IS NOT NULL)"""


def log_weights(graph: str) -> str:
    """The edges of a graph with weights 1..floor(log2 n) - 1."""
    return graph.replace("edges AS", "heavy AS") + """,
most AS (SELECT greatest(1, CAST(floor(log2(count(*))) AS BIGINT) - 1) AS m FROM (SELECT src FROM heavy UNION SELECT dst FROM heavy)),
edges AS (SELECT src, dst, CAST((7919 * src + 104729 * dst) % m + 1 AS BIGINT) AS weight FROM heavy, most)"""


def plain(graph: str, body: str) -> str:
    return f"WITH {graph}\n{body}"


def distances(graph: str, source: int, select: str = "SELECT id, dist FROM d") -> str:
    return f"""WITH RECURSIVE {graph},
d(id, dist) USING KEY (id) AS (
  SELECT {source}::BIGINT, 0::BIGINT
  UNION
  SELECT e.dst, min(d.dist + e.weight) FROM d JOIN edges e ON e.src = d.id LEFT JOIN recurring.d o ON o.id = e.dst
  WHERE o.id IS NULL OR d.dist + e.weight < o.dist GROUP BY e.dst)
{select}"""


def many_distances(graph: str, sources: list[int], select: str = "SELECT source, id, dist FROM d") -> str:
    rows = ", ".join(f"({s}::BIGINT, {s}::BIGINT, 0::BIGINT)" for s in sources)
    return f"""WITH RECURSIVE {graph},
d(source, id, dist) USING KEY (source, id) AS (
  SELECT * FROM (VALUES {rows})
  UNION
  SELECT d.source, e.dst, min(d.dist + e.weight) FROM d JOIN edges e ON e.src = d.id LEFT JOIN recurring.d o ON o.id = e.dst AND o.source = d.source
  WHERE o.id IS NULL OR d.dist + e.weight < o.dist GROUP BY d.source, e.dst)
{select}"""


def widest(graph: str, source: int, top: int) -> str:
    return f"""WITH RECURSIVE {graph},
d(id, width) USING KEY (id) AS (
  SELECT {source}::BIGINT, {top}::BIGINT
  UNION
  SELECT e.dst, max(least(d.width, e.weight)) FROM d JOIN edges e ON e.src = d.id LEFT JOIN recurring.d o ON o.id = e.dst
  WHERE o.id IS NULL OR least(d.width, e.weight) > o.width GROUP BY e.dst)
SELECT id, width FROM d"""


def core(graph: str, select: str = "SELECT id, coreness FROM core") -> str:
    """The h-index fixpoint from degrees; the graph must be symmetric."""
    return f"""WITH RECURSIVE {graph},
k(id, v) USING KEY (id) AS (
  SELECT src, count(*)::BIGINT FROM edges GROUP BY src
  UNION
  SELECT id, h FROM (
    SELECT id, max(least(nv, r)) AS h, any_value(own) AS own FROM (
      SELECT e.src AS id, n.v AS nv, o.v AS own, row_number() OVER (PARTITION BY e.src ORDER BY n.v DESC) AS r
      FROM edges e JOIN recurring.k n ON n.id = e.dst JOIN recurring.k o ON o.id = e.src) GROUP BY id) WHERE h < own),
core AS (SELECT id, v AS coreness FROM k)
{select}"""


def labels(graph: str, edges: str, nodes: str, select: str) -> str:
    """Smallest reachable id over ``edges`` (src, dst; both ways) for ``nodes`` (id)."""
    return f"""WITH RECURSIVE {graph},
ce AS ({edges}), cn AS ({nodes}),
l(id, low) USING KEY (id) AS (
  SELECT id, id FROM cn
  UNION
  SELECT e.dst, min(l.low) FROM l JOIN ce e ON e.src = l.id JOIN recurring.l o ON o.id = e.dst AND l.low < o.low GROUP BY e.dst)
{select}"""
