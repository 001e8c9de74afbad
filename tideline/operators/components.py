"""Connected components of an edge table by alternating star contraction.

Every round hangs the larger neighbours of each vertex below its smallest neighbour (large star), then the
smaller ones (small star). Only minima are aggregated, so a hub costs one row per map task, and the edge count
never rises. A graph of stars is stable after one round; a path of n vertices needs about log2(n). A caller may have graphs of few edges
done in one task instead, which spares the rounds and their shuffles.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tideline.sources.tables import saved


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.select(F.col("hi").alias("u"), F.col("lo").alias("v")).unionByName(edges.select(F.col("lo").alias("u"), F.col("hi").alias("v")))
    low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    return both.where("v > u").join(low, "u").select(F.col("v").alias("hi"), F.col("m").alias("lo")).distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    low = edges.groupBy("hi").agg(F.min("lo").alias("m"))
    moved = edges.join(low, "hi").where("lo <> m").select(F.col("lo").alias("hi"), F.col("m").alias("lo"))
    return moved.unionByName(low.select("hi", F.col("m").alias("lo"))).distinct()


def _state(edges: DataFrame) -> tuple:
    row = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("hi", "lo").cast("decimal(38,0)"))).first()
    return tuple(row)


def _labels(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The components of all the task's edges: roots hang below the smallest root that an edge shows them, then paths are halved."""
    ends = [(b["hi"].to_numpy(), b["lo"].to_numpy()) for b in batches if b.num_rows]
    if not ends:
        return
    ids, at = np.unique(np.concatenate([x[k] for k in (0, 1) for x in ends]), return_inverse=True)
    hi, lo = np.split(at, 2)
    root = np.arange(len(ids))
    while len(apart := np.flatnonzero(root[hi] != root[lo])):
        x, y = root[hi[apart]], root[lo[apart]]
        np.minimum.at(root, np.maximum(x, y), np.minimum(x, y))
        while not np.array_equal(up := root[root], root):
            root = up
    yield pa.record_batch([pa.array(ids), pa.array(ids[root])], names=["id", "component"])


def connected_components(edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 200, small: int = 0) -> DataFrame:
    """``[id, component]`` for every vertex that has an edge to another one; component is its smallest id.

    ``edges`` needs two long columns; direction, repeats and self-loops don't matter, rows with a null end are
    ignored. Vertices without such an edge aren't in the result. A graph of up to ``small`` different edges is done in one task.
    """
    cur = saved(edges.where(F.col(a) != F.col(b)).select(F.greatest(a, b).alias("hi"), F.least(a, b).alias("lo")).distinct())
    seen = _state(cur)
    if 0 < seen[0] <= small:
        return saved(cur.coalesce(1).mapInArrow(_labels, "id long, component long"))
    for _ in range(max_rounds if seen[0] else 0):
        nxt = saved(_small_star(_large_star(cur)))
        now = _state(nxt)
        cur = nxt
        if now == seen:
            break
        seen = now
    else:
        if seen[0]:
            raise RuntimeError(f"components not stable after {max_rounds} rounds")
    roots = cur.select(F.col("lo").alias("id")).distinct()
    return cur.select(F.col("hi").alias("id"), F.col("lo").alias("component")).unionByName(roots.select("id", F.col("id").alias("component")))
