"""Embedding near-duplicates by a subspace pigeonhole join.

Unit vectors with cosine of at least c are at most 2 - 2c apart in squared distance. After a random rotation the
dimensions are cut into ``blocks`` blocks; the squared distance is the sum over blocks, so in some block it is at
most that block's share of the budget. Each block is a range join of its own: vectors lie on a grid over the block's
first ``grid`` coordinates, twice as wide as the block's reach; every vector has one home cell and probes the cells its
reach touches. Candidates are verified by their cosine in double precision on the original vectors, and a pair counts in the first block
in which the one probes the other's home, so the union needs no second look: cells are whole numbers that each vector gets
once, so no rounding can make two blocks disagree.

Rows with equal vectors and labels collapse first, with their number. Cells and ids travel first; a vector follows only to cells that hold
a home and a probe of another one. A unit of work is a pair of chunks of at most
``chunk`` home rows and probes of one cell, so a cell that holds a third of all rows is many tasks. A unit answers with
numbers of links for each vector and a spanning forest, never with pairs.

Rows whose label is null, whose vector is null, empty, zero or holds null or non-finite values, or whose id is null
link with nothing and are their own component. Vectors of different lengths never link. Repeated rows and equal ids
are linked like other copies. An empty table gives an empty result. Only the named columns are read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tideline.llm.annforest import _codes, _matrix
from tideline.llm.common import Forest
from tideline.operators.components import connected_components
from tideline.sources.tables import cut


def rotation(dim: int, seed: int) -> np.ndarray:
    q, r = np.linalg.qr(np.random.default_rng(seed).standard_normal((dim, dim)))
    return q * np.sign(np.diag(r))


def block_edges(dim: int, blocks: int) -> list[int]:
    n = min(blocks, dim)
    return [dim * i // n for i in range(n + 1)]


def _unit(v: np.ndarray) -> np.ndarray:
    return v / np.sqrt((v * v).sum(1))[:, None]


def _cells(x: np.ndarray, reach: float) -> tuple[np.ndarray, list[np.ndarray]]:
    """Home cells of rows (one number a coordinate), and for each coordinate the other cell that the reach touches (or the same)."""
    at = x / (2 * reach)
    home = np.floor(at).astype(np.int64)
    other = np.where(at - home < 0.5, home - 1, home + 1)
    return home, other


def _marked(classes: DataFrame, cosine: float, blocks: int, grid: int, seed: int) -> DataFrame:
    """``classes`` with ``dim`` and ``marks``: for each block the home cell and the other cell of each coordinate."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            sizes = b["v"].value_lengths().to_numpy()
            for dim in np.unique(sizes).tolist():
                own = b.filter(pa.array(sizes == dim))
                x = _unit(_matrix(own["v"])) @ rotation(dim, seed)
                edges = block_edges(dim, blocks)
                marks = np.zeros((own.num_rows, blocks, 2, grid), np.int32)
                for k, (s, e) in enumerate(zip(edges, edges[1:])):
                    reach = float(np.sqrt(max(0.0, 2 - 2 * cosine) * (e - s) / dim)) + 1e-7
                    g = min(grid, e - s)
                    marks[:, k, 0, :g], marks[:, k, 1, :g] = _cells(x[:, s : s + g], reach)
                ends = np.arange(0, marks.size + 1, blocks * 2 * grid, dtype="i4")
                yield pa.record_batch([*own.columns, pa.array(np.full(own.num_rows, dim, "i4")), pa.ListArray.from_arrays(ends, marks.ravel())], names=[*own.schema.names, "dim", "marks"])

    kinds = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in classes.schema.fields)
    return classes.mapInArrow(rows, f"{kinds}, dim int, marks array<int>")


def _placed(marked: DataFrame, blocks: int, grid: int) -> DataFrame:
    """``[label, dim, block, cell, home, cls]``: home and probe rows of all classes in all blocks; ``cell`` is a hash of the cell."""
    kind = marked.schema["label"].dataType.simpleString()

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            m = b.num_rows
            marks = _codes(b["marks"]).reshape(m, blocks, 2, grid).astype(np.int64) if m else np.zeros((0, blocks, 2, grid), np.int64)
            for dim in np.unique(b["dim"].to_numpy()).tolist():
                own = np.flatnonzero(b["dim"].to_numpy() == dim)
                part = b.take(pa.array(own))
                edges = block_edges(dim, blocks)
                for k, (s, e) in enumerate(zip(edges, edges[1:])):
                    g = min(grid, e - s)
                    for which in range(-1, 1 << g):
                        cell = np.zeros(len(own), np.int64)
                        for j in range(g):
                            cell = (cell * 1_000_003) ^ marks[own, k, max(which, 0) >> j & 1, j]
                        yield pa.record_batch([part["label"], part["dim"], pa.array(np.full(len(own), k, "i4")), pa.array(cell), pa.array(np.full(len(own), which < 0)), part["cls"]], names=["label", "dim", "block", "cell", "home", "cls"])

    return marked.select("label", "dim", "cls", "marks").mapInArrow(rows, f"label {kind}, dim int, block int, cell long, home boolean, cls long")


def _compare(cosine: float, blocks: int, grid: int):
    def unit(key: tuple, t: pa.Table) -> pa.Table:
        t = t.combine_chunks()
        block = key[2].as_py()
        home = t["home"].to_numpy(zero_copy_only=False)
        ids, n = t["cls"].to_numpy(), t["n"].to_numpy()
        v = _matrix(t["v"].combine_chunks() if isinstance(t["v"], pa.ChunkedArray) else t["v"])
        h, p = np.flatnonzero(home), np.flatnonzero(~home)
        empty = pa.table({"cls": pa.array([], pa.int64()), "links": pa.array([], pa.int64()), "to": pa.array([], pa.int64())})
        if not len(h) or not len(p):
            return empty
        u = _unit(v)
        marks = _codes(t["marks"].combine_chunks() if isinstance(t["marks"], pa.ChunkedArray) else t["marks"]).reshape(len(ids), blocks, 2, grid)
        places = {c: i for i, c in enumerate(dict.fromkeys(ids.tolist()))}
        names, forest = list(places), Forest(len(places))
        hp = np.array([places[c] for c in ids[h].tolist()])
        links: dict[int, int] = {}
        step = max(1, (1 << 21) // len(h))
        for at in range(0, len(p), step):
            q = p[at : at + step]
            ok = u[q] @ u[h].T >= cosine - 1e-9
            ok &= ids[q][:, None] != ids[h]
            for r in np.flatnonzero(ok.any(1)).tolist():
                c = np.flatnonzero(ok[r])
                a, b = v[q[r]], v[h[c]]
                cos = (b * a).sum(1) / (np.sqrt((a * a).sum()) * np.sqrt((b * b).sum(1)))
                there, mine = marks[h[c], :, 0], marks[q[r]]
                meets = ((there == mine[:, 0]) | (there == mine[:, 1])).all(2)
                c = c[(cos >= cosine) & ~meets[:, :block].any(1) & meets[:, block]]
                if len(c):
                    me = int(ids[q[r]])
                    links[me] = links.get(me, 0) + int(n[h[c]].sum())
                    i = places[me]
                    for j in np.unique(hp[c]).tolist():
                        forest.join(i, j)
        if not links:
            return empty
        roots = forest.roots()
        return pa.table({"cls": pa.array(names, pa.int64()), "links": pa.array([links.get(c, 0) for c in names], pa.int64()), "to": pa.array([names[r] for r in roots], pa.int64())})

    return unit


def near_duplicates(df: DataFrame, cosine: float = 0.98, blocks: int = 4, grid: int = 3, chunk: int = 2048, seed: int = 5, id_col: str = "vec_id", vec_col: str = "embedding", label_col: str = "label") -> DataFrame:
    """``[vec_id, n_links, component_id, kept]`` for each row of ``df``; see the module for the rules."""
    odd = F.exists("v", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    good = F.coalesce(F.col("vec_id").isNotNull() & F.col("label").isNotNull() & (F.size("v") > 0) & ~odd & F.exists("v", lambda x: x != 0), F.lit(False))
    # Single-precision vectors travel as such; all arithmetic is in double precision.
    kind = "array<float>" if df.schema[vec_col].dataType.simpleString() == "array<float>" else "array<double>"
    rows = df.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vec_col).cast(kind).alias("v"), F.col(label_col).alias("label"))
    rows = cut(rows.withColumn("v", F.transform("v", lambda x: x + F.lit(0).cast(kind[6:-1]))).withColumn("good", good))
    classes = cut(rows.where("good").groupBy("label", "v").agg(F.min("vec_id").alias("cls"), F.count(F.lit(1)).alias("n")))
    marked = cut(_marked(classes.select("cls", "label", "v", "n"), cosine, blocks, grid, seed))
    placed = _placed(marked, blocks, grid)
    cell = ["label", "dim", "block", "cell"]
    # A class's own probe of its home cell is no partner.
    sizes = placed.groupBy(*cell).agg(F.sum(F.col("home").cast("int")).alias("h"), F.sum((~F.col("home")).cast("int")).alias("p")).where("h > 0 and p > 1")
    sizes = sizes.select(*cell, F.ceil(F.col("h") / F.lit(chunk)).cast("int").alias("hs"), F.ceil(F.col("p") / F.lit(chunk)).cast("int").alias("ps"))
    dealt = placed.join(sizes, cell)
    mine = F.pmod(F.xxhash64("cls"), F.when(F.col("home"), F.col("hs")).otherwise(F.col("ps"))).cast("int")
    dealt = dealt.withColumn("mine", mine).withColumn("other", F.explode(F.sequence(F.lit(0), F.when(F.col("home"), F.col("ps")).otherwise(F.col("hs")) - 1)))
    dealt = dealt.withColumn("hp", F.when(F.col("home"), F.col("mine")).otherwise(F.col("other"))).withColumn("pp", F.when(F.col("home"), F.col("other")).otherwise(F.col("mine")))
    told = dealt.select(*cell, "hp", "pp", "home", "cls").join(marked.select("cls", "n", "v", "marks"), "cls")
    found = cut(told.groupBy(*cell, "hp", "pp").applyInArrow(_compare(cosine, blocks, grid), "cls long, links long, to long"))
    comp = connected_components(found.where("cls <> to").select(F.col("cls").alias("a"), F.col("to").alias("b")))
    told = classes.select("label", "v", "cls", "n").join(found.groupBy("cls").agg(F.sum("links").alias("links")), "cls", "left").join(comp, F.col("cls") == F.col("id"), "left")
    told = told.select(F.col("label").alias("__l"), F.col("v").alias("__v"), (F.coalesce("links", F.lit(0)) + F.col("n") - 1).alias("n_links"), F.coalesce("component", "cls").alias("component_id"))
    out = rows.join(told, F.col("good") & (F.col("label") == F.col("__l")) & (F.col("v") == F.col("__v")), "left")
    comp_id = F.coalesce("component_id", "vec_id")
    return out.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), comp_id.alias("component_id"), F.coalesce(F.col("vec_id") == comp_id, F.lit(True)).alias("kept"))
