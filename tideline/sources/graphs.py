"""Graphs and set systems derived from the given tables.

Edges are ``[src, dst, weight]`` (longs); vertices are ``[id]`` or ``[id, x, y]``. A :class:`Graph` keeps edges
hash-partitioned by ``src`` for pushes and, on demand, by ``dst`` for pulls or by block for local work.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tideline.sources import packed
from tideline.sources.tables import cut, table

EDGE = ["src", "dst", "weight"]


@dataclass
class Graph:
    """An edge table, its vertices, and the partitioned copies that rounds read."""

    edges: DataFrame
    vertices: DataFrame | None = None
    parts: int | None = None
    coords: bool = False
    rows: DataFrame | None = None  # the same edges, packed by source
    _copies: dict = field(default_factory=dict)

    @staticmethod
    def packed_from(edges: DataFrame, unique: bool = False) -> Graph:
        """A graph whose edges are written once, packed; with ``unique`` each pair of ends once."""
        rows = cut(packed.pack(edges, unique))
        return Graph(packed.unpack(rows), rows=rows)

    @property
    def spark(self) -> SparkSession:
        return self.edges.sparkSession

    @property
    def P(self) -> int:
        return self.parts or int(self.spark.conf.get("spark.sql.shuffle.partitions"))

    def checked(self, positive: bool = False) -> Graph:
        """Raises if a weight is negative (or, with ``positive``, zero) or null."""
        low = 1 if positive else 0
        if self.rows is not None:
            least = self.rows.agg(F.min("low")).first()[0]
            if least is not None and least < low:
                raise ValueError("weights must be at least %d" % low)
        elif not self.edges.where(F.col("weight").isNull() | (F.col("weight") < low)).isEmpty():
            raise ValueError("weights must be at least %d" % low)
        return self

    def all_vertices(self) -> DataFrame:
        """Every vertex once: the given ones, or the ends of edges."""
        if self.vertices is not None:
            return self.vertices
        if (files := self.numbered()) is not None:
            return files.vertices(self.spark)
        return self.edges.select(F.explode(F.array("src", "dst")).alias("id")).distinct()

    def numbered(self) -> packed.Numbered | None:
        """The packed edges as files that one task can reach into; None for graphs that aren't packed or can't be numbered."""
        if "files" not in self._copies:
            self._copies["files"] = packed.numbered(self.spark, self.rows) if self.rows is not None else None
        return self._copies["files"]

    def degrees(self) -> DataFrame:
        """``[id, n]``: edges out of each source."""
        if self.rows is not None:
            return packed.sources(self.rows)
        return self.edges.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("n"))

    def pushed(self) -> DataFrame:
        """Edges partitioned by source; written once, read by every round."""
        if "push" not in self._copies:
            self._copies["push"] = cut(self.edges.select(*EDGE).repartition(self.P, "src").sortWithinPartitions("src"))
        return self._copies["push"]

    def adjacent(self) -> DataFrame:
        """``[src, to, by]``: targets and weights of a source as two arrays, partitioned by source. A round that few sources take part in passes over
        the others' edges without a look at each. A hub has several rows, since a row ends with its Arrow batch."""
        if "adjacent" not in self._copies:
            e = self.edges.select(*EDGE).where("src is not null").repartition(self.P, "src").sortWithinPartitions("src")
            self._copies["adjacent"] = cut(e.mapInArrow(_by_source, "src long, to array<long>, by array<long>").repartition(self.P, "src"))
        return self._copies["adjacent"]

    def salted(self, salts: int) -> DataFrame:
        """Edges with a salt of their target, partitioned by source and salt: a hub's edges lie in several partitions."""
        key = f"salt-{salts}"
        if key not in self._copies:
            e = self.edges.select(*EDGE, F.pmod(F.xxhash64("dst"), F.lit(salts)).cast("int").alias("__s"))
            self._copies[key] = cut(e.repartition(self.P, "src", "__s").sortWithinPartitions("src"))
        return self._copies[key]

    def balanced(self) -> DataFrame:
        """Edges in ranges of (source, target): partitions hold equally many edges, whatever the degrees."""
        if "even" not in self._copies:
            self._copies["even"] = cut(self.edges.select(*EDGE).repartitionByRange(self.P, "src", "dst"))
        return self._copies["even"]

    def pulled(self) -> DataFrame:
        """Edges partitioned by target, so a pull aggregates without an exchange."""
        if "pull" not in self._copies:
            self._copies["pull"] = cut(self.edges.select(*EDGE).repartition(self.P, "dst").sortWithinPartitions("dst"))
        return self._copies["pull"]

    def packed(self) -> DataFrame:
        """``[id, adj]``: each source's ``array<struct<dst,weight>>``, partitioned by id."""
        if "pack" not in self._copies:
            self._copies["pack"] = cut(pack_adjacency(self.edges).select(F.col("src").alias("id"), "adj").repartition(self.P, "id"))
        return self._copies["pack"]

    def block_count(self, edges: int = 1_000_000) -> int:
        """As many blocks as leave about ``edges`` edges to each, a task's worth of arrays; at least 8."""
        n = self.edges.count() if self.rows is None else self.rows.agg(F.sum("edges")).first()[0] or 0
        return max(8, -(-n // edges))

    def owners(self, blocks: int, method: str = "range") -> DataFrame:
        """``[id, block]``, see :meth:`blocked`."""
        key = f"owner-{blocks}-{method}"
        if key not in self._copies:
            ids = self.all_vertices().select("id")
            if method == "hash":
                owner = ids.select("id", F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int").alias("block"))
            elif method == "range":
                owner = ids.repartitionByRange(blocks, "id").select("id", F.spark_partition_id().alias("block"))
            else:
                raise ValueError(f"unknown block method {method}")
            self._copies[key] = cut(owner)
        return self._copies[key]

    def blocked(self, blocks: int, method: str = "range") -> tuple[DataFrame, DataFrame]:
        """``[id, block]`` and ``[src, dst, weight, block, dst_block]`` partitioned by block of the source.

        ``range`` blocks hold consecutive ids and keep neighbours of lattice-like graphs together; ``hash`` blocks don't.
        """
        key = f"block-{blocks}-{method}"
        if key not in self._copies:
            owner = self.owners(blocks, method)
            src, dst = owner.toDF("src", "block"), owner.toDF("dst", "dst_block")
            edges = self.edges.join(src, "src").join(dst, "dst").select(*EDGE, "block", "dst_block")
            self._copies[key] = owner, cut(edges.repartition(self.P, "block"))
        return self._copies[key]

    def packed_blocks(self, blocks: int, method: str = "range") -> tuple[DataFrame, DataFrame]:
        """Like :meth:`blocked`, but the edges lie as ``[block, src, dst, weight, dst_block]`` with the bytes of many edges in a row: a round
        ships them to Python as they are."""
        key = f"bytes-{blocks}-{method}"
        if key not in self._copies:
            owner, edges = self.blocked(blocks, method)
            packed = edges.sortWithinPartitions("block", "src").mapInArrow(_by_block, "block int, src binary, dst binary, weight binary, dst_block binary")
            self._copies[key] = owner, cut(packed.repartition(self.P, "block").sortWithinPartitions("block"))
        return self._copies[key]

    def symmetric(self) -> Graph:
        """Both directions of every edge, once, without self-loops; the smallest weight of repeats."""
        return Graph(symmetrize(self.edges), self.vertices, self.parts, self.coords)


def _cuts(keys: np.ndarray) -> np.ndarray:
    """Where runs of equal keys begin, with the end."""
    return np.r_[0, np.flatnonzero(keys[1:] != keys[:-1]) + 1, len(keys)]


def _by_source(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        if b.num_rows:
            src = b["src"].to_numpy()
            at = _cuts(src)
            ends = pa.array(at.astype("i4"))
            yield pa.record_batch([pa.array(src[at[:-1]]), pa.ListArray.from_arrays(ends, b["dst"]), pa.ListArray.from_arrays(ends, b["weight"])], names=["src", "to", "by"])


def _by_block(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names = ["src", "dst", "weight", "dst_block"]
    for b in batches:
        if b.num_rows:
            block, cols = b["block"].to_numpy(), [b[c].to_numpy() for c in names]
            at = _cuts(block)
            yield pa.record_batch([pa.array(block[at[:-1]]), *[pa.array([c[i:j].tobytes() for i, j in zip(at, at[1:])], pa.binary()) for c in cols]], names=["block", *names])


def symmetrize(edges: DataFrame) -> DataFrame:
    both = edges.select(*EDGE).unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "weight"))
    return both.where("src <> dst").groupBy("src", "dst").agg(F.min("weight").alias("weight"))


def pack_adjacency(edges: DataFrame) -> DataFrame:
    return edges.groupBy("src").agg(F.sort_array(F.collect_list(F.struct("dst", "weight"))).alias("adj"))


def induced(edges: DataFrame, ids: DataFrame) -> DataFrame:
    """Edges whose ends are both among ``ids`` ([id])."""
    e = edges.join(ids.toDF("src"), "src", "left_semi")
    return e.join(ids.toDF("dst"), "dst", "left_semi").select(*EDGE)


def hashed_weight(src, dst, most: int):
    """1..most from the two ids, by arithmetic that every engine repeats."""
    return (F.lit(7919) * src + F.lit(104729) * dst) % F.lit(most) + 1


# Lattice of week and nation ------------------------------------------------------------------------------------

def road_cells(spark: SparkSession, sf_dir: str, days: int, wide: bool = False) -> DataFrame:
    """``[id, x, y, c]``: cells of ``days`` days and a nation, with a load."""
    orders, cust = table(spark, sf_dir, "orders"), table(spark, sf_dir, "customer")
    x = F.floor(F.datediff("o_orderdate", F.lit("1995-01-01").cast("date")) / F.lit(days)).cast("long")
    rows = orders.select("o_custkey", x.alias("x"), F.floor("o_totalprice").cast("long").alias("p")).join(cust.select("c_custkey", F.col("c_nationkey").cast("long").alias("y")), F.col("o_custkey") == F.col("c_custkey"))
    load = (F.sum("p") % 999 + 1) if wide else (F.sum("p") % 500)
    return rows.groupBy("x", "y").agg(load.alias("c")).select((F.col("x") * 25 + F.col("y")).alias("id"), "x", "y", "c")


def g_road(spark: SparkSession, sf_dir: str, days: int = 28, wide: bool = False) -> Graph:
    """Neighbouring cells, both ways; the range join on both coordinates is an equi-join on generated offsets."""
    cells = cut(road_cells(spark, sf_dir, days, wide))
    steps = F.array(*[F.struct(F.lit(dx).cast("long").alias("dx"), F.lit(dy).cast("long").alias("dy")) for dx, dy in ((0, 1), (0, -1), (1, 0), (-1, 0))])
    near = cells.select(F.col("id").alias("src"), "x", "y", F.col("c").alias("c1"), F.explode(steps).alias("s")).select("src", "c1", (F.col("x") + F.col("s.dx")).alias("x"), (F.col("y") + F.col("s.dy")).alias("y"))
    w = F.expr("(c1 + c) div 2") + (1 if wide else 500)
    edges = near.join(cells.select(F.col("id").alias("dst"), "x", "y", "c"), ["x", "y"]).select("src", "dst", w.cast("long").alias("weight"))
    edges = cut(edges)
    verts = cells.join(edges.select(F.col("src").alias("id")).distinct(), "id", "left_semi").select("id", "x", "y")
    return Graph(edges, cut(verts), coords=True)


# Co-purchase ---------------------------------------------------------------------------------------------------

def _shared_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``[src, dst]``: parts that share an order, once for each such order."""
    items = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").repartition("l_orderkey").distinct()
    other = items.select("l_orderkey", F.col("l_partkey").alias("dst"))
    return items.join(other, "l_orderkey").where("l_partkey <> dst").select(F.col("l_partkey").alias("src"), "dst")


def social_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    # Dealt by source before repeats go: one shuffle, and what reads the pairs finds them by source.
    return _shared_orders(spark, sf_dir).repartition("src").distinct()


def g_social(spark: SparkSession, sf_dir: str, log_weights: bool = False) -> Graph:
    """Parts that share an order; directed weights 1..999, or 1..floor(log2 n) - 1."""
    weight = lambda most: hashed_weight(F.col("src"), F.col("dst"), most).cast("long").alias("weight")
    # Repeats go when the edges are packed, as a source's edges meet there.
    g = Graph.packed_from(_shared_orders(spark, sf_dir).select("src", "dst", weight(999)), True)
    if not log_weights:
        return g
    most = max(1, packed.sources(g.rows).count().bit_length() - 2)
    return Graph.packed_from(g.edges.select("src", "dst", weight(most)))


def g_trade(spark: SparkSession, sf_dir: str) -> Graph:
    """Customers and the parts that they bought, both ways, weight 1."""
    o = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    li = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    p = o.join(li, F.col("o_orderkey") == F.col("l_orderkey")).select(F.col("o_custkey").alias("a"), (F.col("l_partkey") + 1_000_000).alias("b")).distinct()
    return Graph.packed_from(p.select(F.explode(F.array(F.struct(F.col("a").alias("src"), F.col("b").alias("dst")), F.struct(F.col("b").alias("src"), F.col("a").alias("dst")))).alias("e")).select("e.src", "e.dst", F.lit(1).cast("long").alias("weight")))


def web_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``[page_id, href]``, each pair once."""
    href = F.explode(F.regexp_extract_all("html", F.lit(r'href="([^"]*)"'), 1))
    return table(spark, sf_dir, "pages").select("page_id", href.alias("href")).where("href <> ''").distinct()


def g_web(spark: SparkSession, sf_dir: str, symmetric: bool = False) -> Graph:
    """Pages to link targets. A target's id is 1,000,000,000 and its rank among all targets."""
    links = cut(web_links(spark, sf_dir))
    ids = encode_ids(links.select("href").distinct(), "href", 1_000_000_000)
    pairs = links.join(ids, "href").select(F.col("page_id").alias("src"), F.col("id").alias("dst"))
    edges = pairs.select("src", "dst", hashed_weight(F.col("src"), F.col("dst"), 999).cast("long").alias("weight"))
    return Graph(symmetrize(edges) if symmetric else edges)


def log_weights(graph: Graph) -> Graph:
    """The same edges with weights 1..floor(log2 n) - 1 by the vertices' number (at least 1)."""
    most = max(1, graph.all_vertices().count().bit_length() - 2)
    return Graph(graph.edges.select("src", "dst", hashed_weight(F.col("src"), F.col("dst"), most).cast("long").alias("weight")))


def encode_ids(keys: DataFrame, key: str, base: int = 0) -> DataFrame:
    """``[key, id]``: dense ids in the keys' order. Ranks within range partitions plus the sizes of those before."""
    return ranked(keys, [key]).select(key, (F.lit(base) + F.col("rank")).cast("long").alias("id"))


def _vectors(col: pa.ChunkedArray) -> np.ndarray:
    """A column of equally long lists as one matrix, without a Python object for each number."""
    flat = col.combine_chunks().flatten()
    return flat.to_numpy(zero_copy_only=False).astype(np.float64, copy=False).reshape(len(col), -1)


def _nearest_between(src: np.ndarray, a: np.ndarray, dst: np.ndarray, b: np.ndarray, k: int, strip: int = 512) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The ``k`` nearest of ``b`` for each row of ``a``: a product of matrices tells which rows may be among them, the distances themselves decide."""
    found = []
    bb = np.einsum("ij,ij->i", b, b)
    largest = np.max(bb[np.isfinite(bb)], initial=0.0)
    for at in range(0, len(a), strip):
        x, ids = a[at : at + strip], src[at : at + strip]
        aa = np.einsum("ij,ij->i", x, x)
        rough = aa[:, None] + bb[None, :] - 2 * (x @ b.T)
        rough[~np.isfinite(rough) | (ids[:, None] == dst[None, :])] = np.inf
        # The product's rounding errors are far below this part of the norms.
        last = np.partition(rough, k - 1, axis=1)[:, k - 1] if k < len(b) else np.full(len(x), np.inf)
        i, j = np.nonzero((rough <= (last + 1e-9 * (1 + np.abs(aa) + largest))[:, None]) & (rough < np.inf))
        d = np.sqrt(((b[j] - x[i]) ** 2).sum(1))
        order = np.lexsort((dst[j], d, i))
        i, j, d = i[order], j[order], d[order]
        best = np.arange(len(i)) - np.searchsorted(i, i) < k
        found.append((ids[i[best]], dst[j[best]], d[best]))
    return tuple(np.concatenate(c) for c in zip(*found))


def nearest_rows(vectors: DataFrame, k: int, block: int = 8192) -> DataFrame:
    """``[src, dst, d]``: the ``k`` nearest other rows of each row of ``[id, v]``, exactly, ties to smaller ids.

    All rows are compared, block by block: a task holds two blocks of about ``block`` rows and answers each row of the first with its
    best ``k``, so nothing is broadcast and memory doesn't follow the table. The work is what an exact answer costs.
    """
    n = max(1, -(-vectors.count() // block))
    rows = vectors.select("id", "v", F.pmod(F.xxhash64("id"), F.lit(n)).cast("int").alias("mine"))
    every = F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    left = rows.select(F.col("id").alias("src"), F.col("v").alias("a"), F.col("mine").alias("i"), every.alias("j"))
    right = rows.select(F.col("id").alias("dst"), F.col("v").alias("b"), F.col("mine").alias("y"), every.alias("x"))

    def best(key: tuple, q: pa.Table, r: pa.Table) -> pa.Table:
        src, dst, d = [], [], []
        if q.num_rows and r.num_rows:
            src, dst, d = _nearest_between(q["src"].to_numpy(), _vectors(q["a"]), r["dst"].to_numpy(), _vectors(r["b"]), k)
        return pa.table({"src": pa.array(src, pa.int64()), "dst": pa.array(dst, pa.int64()), "d": pa.array(d, pa.float64())})

    found = left.groupBy("i", "j").cogroup(right.groupBy("x", "y")).applyInArrow(best, "src long, dst long, d double")
    return found.withColumn("r", F.row_number().over(W.partitionBy("src").orderBy("d", "dst"))).where(F.col("r") <= k).select("src", "dst", "d")


def g_vec(spark: SparkSession, sf_dir: str, k: int = 5) -> Graph:
    """The ``k`` nearest vectors of each vector; weight = ceil(1000 * distance)."""
    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("v"))
    near = nearest_rows(e, k)
    return Graph(cut(near.select("src", "dst", F.ceil(F.round(F.col("d") * 1000, 6)).cast("long").alias("weight"))))


def ranked(rows: DataFrame, order: list) -> DataFrame:
    """``rows`` with ``rank``, 0.. in the order: ranks within range partitions plus the sizes of those before."""
    ranged = cut(rows.repartitionByRange(*order).withColumn("__p", F.spark_partition_id()))
    sizes = ranged.groupBy("__p").count().withColumn("__b", F.coalesce(F.sum("count").over(W.orderBy("__p").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
    inside = F.row_number().over(W.partitionBy("__p").orderBy(*order)) - 1
    return ranged.withColumn("__r", inside).join(sizes, "__p").withColumn("rank", (F.col("__b") + F.col("__r")).cast("long")).drop("__p", "__b", "__r", "count")


def tiles(rows: DataFrame, n: int, order: list) -> DataFrame:
    """``rows`` with ``part``, 1..n: equal parts in the order, the first ones a row larger, without one task for all rows."""
    x = ranked(rows, order)
    total = x.count()
    size, more = divmod(total, n)
    first = more * (size + 1)
    r = F.col("rank")
    part = F.when(r < first, F.floor(r / (size + 1))).otherwise(more + F.floor((r - first) / max(1, size)))
    return x.withColumn("part", (part + 1).cast("long")).drop("rank")


def g_time(spark: SparkSession, sf_dir: str) -> Graph:
    """Each event to the next one of its user and the next one of its type; weight = whole seconds between + 1."""
    ev = table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type")
    seconds = lambda a, b: F.floor((F.unix_micros(b.cast("timestamp")) - F.unix_micros(a.cast("timestamp"))) / 1_000_000).cast("long") + 1
    # A type holds a fifth of all events: its chain is made within days, and the last event of a day meets the first of the next day that has one.
    parts = []
    for key in ("user_id", "event_type"):
        day = F.lit(0) if key == "user_id" else F.to_date("ts")
        w = W.partitionBy(key, "__d").orderBy("ts", "event_id")
        rows = ev.withColumn("__d", day).select(key, "__d", "event_id", "ts", F.lead("event_id").over(w).alias("dst"), F.lead("ts").over(w).alias("after"))
        parts.append(rows.where("dst is not null").select(F.col("event_id").alias("src"), "dst", seconds(F.col("ts"), F.col("after")).alias("weight")))
        if key != "user_id":
            ends = ev.withColumn("__d", day).groupBy(key, "__d").agg(F.min(F.struct("ts", "event_id")).alias("first"), F.max(F.struct("ts", "event_id")).alias("last"))
            nxt = ends.select("last", F.lead("first").over(W.partitionBy(key).orderBy("__d")).alias("then")).where("then is not null")
            parts.append(nxt.select(F.col("last.event_id").alias("src"), F.col("then.event_id").alias("dst"), seconds(F.col("last.ts"), F.col("then.ts")).alias("weight")))
    out = parts[0]
    for x in parts[1:]:
        out = out.unionByName(x)
    return Graph(out.groupBy("src", "dst").agg(F.min("weight").alias("weight")))


def g_turn(spark: SparkSession, sf_dir: str) -> Graph:
    """Each turn of a conversation to the next one; id = conversation * 1000 + turn."""
    w = W.partitionBy("conv_id").orderBy("turn")
    t = table(spark, sf_dir, "conversations").select("conv_id", "turn").distinct().select("conv_id", "turn", F.lead("turn").over(w).alias("nxt")).where("nxt is not null")
    return Graph(t.select((F.col("conv_id") * 1000 + F.col("turn")).alias("src"), (F.col("conv_id") * 1000 + F.col("nxt")).alias("dst"), (F.col("nxt") - F.col("turn")).alias("weight")))


# Set systems -----------------------------------------------------------------------------------------------------

def s_supplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("set_id"), F.col("l_partkey").alias("elem_id")).distinct()


def s_customer(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = table(spark, sf_dir, "orders").select("o_orderkey", F.col("o_custkey").alias("set_id"))
    return o.join(table(spark, sf_dir, "lineitem").select("l_orderkey", F.col("l_partkey").alias("elem_id")), F.col("o_orderkey") == F.col("l_orderkey")).select("set_id", "elem_id").distinct()


def s_neighbours(graph: Graph) -> DataFrame:
    """Each vertex covers itself and its neighbours in the symmetrised graph."""
    e = symmetrize(graph.edges).select(F.col("src").alias("set_id"), F.col("dst").alias("elem_id"))
    return e.unionByName(e.select("set_id", F.col("set_id").alias("elem_id")).distinct())


def s_document(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents cover their lower-case ASCII words of four letters and more, by a stable hash of the word."""
    word = F.explode(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]{4,}"), 0))
    return table(spark, sf_dir, "documents").select(F.col("doc_id").alias("set_id"), word.alias("w")).select("set_id", F.xxhash64("w").alias("elem_id")).distinct()


def supplier_costs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("set_id"), (F.floor(F.abs("s_acctbal")).cast("long") % 100 + 1).alias("cost"))
