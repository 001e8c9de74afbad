"""Coreness by peeling, k-core subgraphs, and unordered baselines. Graphs must be symmetric."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tideline.operators.components import connected_components
from tideline.operators.engine import OrderedResult, run_ordered
from tideline.plans.rules import EdgeRule, OrderedProgram, PrioritySpec
from tideline.plans.schedule import Schedule
from tideline.sources.graphs import Graph, induced
from tideline.sources.tables import cut

KCORE = OrderedProgram("kcore", PrioritySpec("low", False), EdgeRule.add(-1, "current"), "kcore")


def kcore(graph: Graph, schedule: Schedule | None = None) -> OrderedResult:
    """The priority is the remaining degree; a vertex's coreness is the bucket that it was taken from (``settled_at``)."""
    degree = graph.degrees().withColumnRenamed("n", "value")
    return run_ordered(KCORE, graph, schedule or Schedule(update="lazy_count"), extra=degree)


def coreness(result: OrderedResult) -> DataFrame:
    """``[id, coreness]``; vertices without an edge have 0."""
    return result.state.select("id", F.coalesce("settled_at", F.lit(0)).alias("coreness"))


def histogram(core: DataFrame) -> DataFrame:
    """``[coreness, n, at_least]``: vertices of each coreness, and of that or a higher one."""
    n = core.groupBy("coreness").agg(F.count(F.lit(1)).alias("n"))
    return n.select("coreness", "n", F.sum("n").over(W.orderBy(F.desc("coreness")).rowsBetween(W.unboundedPreceding, 0)).alias("at_least"))


def subgraph(graph: Graph, core: DataFrame, k: int) -> DataFrame:
    """``[id, component]`` of the vertices in k-cores: maximal connected subgraphs of degree k and more."""
    ids = core.where(F.col("coreness") >= k).select("id")
    comp = connected_components(induced(graph.edges, ids), "src", "dst")
    return ids.join(comp, "id", "left").select("id", F.coalesce("component", "id").alias("component"))


def rescan(graph: Graph) -> DataFrame:
    """Unordered: for each k, look at all that remain again and again. ``[id, coreness]``."""
    e = graph.edges.select("src", "dst")
    left, done, k = cut(e), [], 0
    ids = cut(e.select(F.col("src").alias("id")).distinct())
    while not ids.isEmpty():
        while True:
            deg = left.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("d"))
            low = cut(ids.join(deg, "id", "left").where(F.coalesce("d", F.lit(0)) <= k).select("id"))
            if low.isEmpty():
                break
            done.append(low.withColumn("coreness", F.lit(k).cast("long")))
            ids = cut(ids.join(low, "id", "left_anti"))
            left = cut(left.join(low.toDF("src"), "src", "left_anti").join(low.toDF("dst"), "dst", "left_anti").select("src", "dst"))
        k += 1
    out = graph.spark.createDataFrame([], "id long, coreness long")
    for x in done:
        out = out.unionByName(x)
    return out


def _h_index(ends: np.ndarray, near: np.ndarray, v: np.ndarray) -> np.ndarray:
    """For each stretch of ``near`` up to the next of ``ends``: the most values of at least that many, ``v`` at the most."""
    n = np.diff(ends)
    out, starts = v.copy(), ends[:-1]
    # Most vertices stay as they are: those with enough neighbours of their own value and more.
    lower = np.flatnonzero(np.add.reduceat(near >= np.repeat(v, n), starts, dtype=np.int64) < v)
    if len(lower):
        k = n[lower]
        first = np.cumsum(k) - k
        part = near[np.repeat(starts[lower] - first, k) + np.arange(int(k.sum()))]
        own = np.repeat(np.arange(len(lower)), k)
        part = part[np.lexsort((-part, own))]
        out[lower] = np.maximum.reduceat(np.minimum(part, np.arange(len(part)) - first[own] + 1), first)
    return out


def _packed(edges: DataFrame, most: int) -> DataFrame:
    """``[src, n, dst]``: sources, their numbers of edges and the other ends as bytes, about ``most`` edges a row; edges must be dealt by source and sorted."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        src, dst = np.empty(0, "i8"), np.empty(0, "i8")

        def row(upto: int) -> pa.RecordBatch:
            ids, n = np.unique(src[:upto], return_counts=True)
            return pa.record_batch([pa.array([x.tobytes()], pa.binary()) for x in (ids, n.astype("i8"), dst[:upto])], names=["src", "n", "dst"])

        held: list[tuple[np.ndarray, np.ndarray]] = []
        size = 0
        for b in batches:
            held.append(tuple(b[c].to_numpy() for c in ("src", "dst")))
            size += b.num_rows
            if size >= most:
                src, dst = (np.concatenate([x[k] for x in held]) for k in (0, 1))
                # The last source may go on in the next batch.
                upto = int(np.searchsorted(src, src[-1]))
                if upto:
                    yield row(upto)
                held, size = [(src[upto:], dst[upto:])], len(src) - upto
        if size:
            src, dst = (np.concatenate([x[k] for x in held]) for k in (0, 1))
            yield row(len(src))

    return edges.mapInArrow(rows, "src binary, n binary, dst binary")


def h_index_rounds(graph: Graph, held: int = 4_000_000, dealt: bool = False, most: int = 1_000_000) -> tuple[DataFrame, int]:
    """Unordered: every vertex takes the h-index of its neighbours' values until nothing changes. ``[id, coreness]``, rounds.

    Up to ``held`` vertices with edges, a round is one pass over edges that were packed once, with all values sent to the tasks; what comes
    back are the vertices that changed. Above that rounds are joins. ``dealt``: the edges lie by source already.
    """
    e = graph.edges.select("src", "dst")
    packed = cut(_packed((e if dealt else e.repartition(graph.P, "src")).sortWithinPartitions("src"), most))

    def degrees(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for ids, n in zip(b["src"].to_pylist(), b["n"].to_pylist()):
                yield pa.record_batch([pa.array(np.frombuffer(x, "i8")) for x in (ids, n)], names=["id", "v"])

    value = packed.select("src", "n").mapInArrow(degrees, "id long, v long")
    if value.count() > held:
        return _h_index_joins(graph, cut(e.repartition(graph.P, "dst")), cut(value))
    start = value.toArrow()
    order = np.argsort(start["id"].to_numpy())
    ids, v = start["id"].to_numpy()[order], start["v"].to_numpy()[order].astype("i4")

    def numbered(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for src, n, dst in zip(*(b[c].to_pylist() for c in ("src", "n", "dst"))):
                src, n, dst = (np.frombuffer(x, "i8") for x in (src, n, dst))
                at = np.minimum(np.searchsorted(ids, dst), len(ids) - 1)
                # An end without edges of its own counts as nothing: a place after the last value, which is 0.
                at[ids[at] != dst] = len(ids)
                cols = (np.searchsorted(ids, src).astype("i4"), np.r_[0, np.cumsum(n)].astype("i4"), at.astype("i4"))
                yield pa.record_batch([pa.array([x.tobytes()], pa.binary()) for x in cols], names=["src", "ends", "near"])

    near = cut(packed.mapInArrow(numbered, "src binary, ends binary, near binary"))

    def step(now: np.ndarray):
        def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for row in zip(*(b[c].to_pylist() for c in ("src", "ends", "near"))):
                    src, ends, dst = (np.frombuffer(x, "i4") for x in row)
                    h = _h_index(ends.astype("i8"), now[dst], now[src])
                    moved = np.flatnonzero(h < now[src])
                    yield pa.record_batch([pa.array(src[moved]), pa.array(h[moved])], names=["at", "h"])

        return rows

    v, rounds = np.r_[v, np.int32(0)].astype("i4"), 0
    while True:
        rounds += 1
        moved = near.mapInArrow(step(v), "at int, h int").toArrow()
        if not moved.num_rows:
            break
        v = v.copy()
        v[moved["at"].to_numpy()] = moved["h"].to_numpy()

    def named(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for src in b["src"].to_pylist():
                at = np.frombuffer(src, "i4")
                yield pa.record_batch([pa.array(ids[at]), pa.array(v[at].astype("i8"))], names=["id", "coreness"])

    return near.select("src").mapInArrow(named, "id long, coreness long"), rounds


def _h_index_joins(graph: Graph, e: DataFrame, val: DataFrame) -> tuple[DataFrame, int]:
    """The rounds as joins, for any number of vertices."""
    rounds = 0
    while True:
        rounds += 1
        seen = e.join(val.toDF("dst", "nv"), "dst").groupBy("src", "nv").agg(F.count(F.lit(1)).alias("c"))
        at_least = F.sum("c").over(W.partitionBy("src").orderBy(F.desc("nv")).rowsBetween(W.unboundedPreceding, 0))
        h = seen.withColumn("n", at_least).groupBy(F.col("src").alias("id")).agg(F.max(F.least("n", "nv")).alias("h"))
        new = cut(val.join(h, "id").select("id", F.least("v", "h").alias("v"), (F.col("h") < F.col("v")).alias("moved")))
        if new.where("moved").isEmpty():
            return new.select("id", F.col("v").alias("coreness")), rounds
        val = new.drop("moved")
