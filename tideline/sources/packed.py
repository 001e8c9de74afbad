"""Edges packed by source: the bytes of many edges in a row, and numbered edges in files that a single task can reach into.

Rows are ``[src, n, dst, weight, edges, low, high, gaps]``: sources in their order, how many edges each has, the other ends and the weights as
bytes, and the row's edges, least and largest weight and nulls. A source lies in one row. What is read from them are the same edges.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tideline.sources.tables import shared_dir

#: Up to this many vertices are numbered; the driver holds their ids and where their edges lie, 24 bytes each.
HELD = 8_000_000
#: Stands for null in packed ids; a graph that has it isn't numbered.
_NULL = np.iinfo(np.int64).min
_ROW = "src binary, n binary, dst binary, weight binary, edges long, low long, high long, gaps long"


def runs(keys: np.ndarray) -> np.ndarray:
    """Where runs of equal keys begin, with the end."""
    return np.r_[0, np.flatnonzero(keys[1:] != keys[:-1]) + 1, len(keys)] if len(keys) else np.zeros(1, np.int64)


def pack(edges: DataFrame, unique: bool = False, most: int = 1_000_000) -> DataFrame:
    """Packed rows of about ``most`` edges from ``[src, dst, weight]``; with ``unique`` each pair of ends once, for edges whose weight follows from them."""

    def row(src: np.ndarray, dst: np.ndarray, weight: np.ndarray, gaps: int) -> pa.RecordBatch:
        if unique:
            order = np.lexsort((dst, src))
            src, dst, weight = src[order], dst[order], weight[order]
            new = np.r_[True, (src[1:] != src[:-1]) | (dst[1:] != dst[:-1])]
            src, dst, weight = src[new], dst[new], weight[new]
        at = runs(src)
        low, high = int(weight.min()), int(weight.max())
        small = weight.astype("i4") if -(1 << 31) < low and high < 1 << 31 else weight
        told = [[x.tobytes()] for x in (src[at[:-1]], np.diff(at).astype("i8"), dst, small)]
        return pa.record_batch([*[pa.array(x, pa.binary()) for x in told], *[pa.array([x], pa.int64()) for x in (len(src), low, high, gaps)]], names=[f.split()[0] for f in _ROW.split(", ")])

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, ...]] = []
        size = gaps = 0
        for b in batches:
            gaps += sum(b[c].null_count for c in ("src", "dst", "weight"))
            held.append(tuple(b[c].fill_null(_NULL).to_numpy() for c in ("src", "dst", "weight")))
            size += b.num_rows
            if size >= most:
                cols = [np.concatenate(x) for x in zip(*held)]
                # The last source may go on in the next batch.
                upto = int(np.searchsorted(cols[0], cols[0][-1]))
                if upto:
                    yield row(*[c[:upto] for c in cols], gaps)
                    gaps = 0
                held, size = [tuple(c[upto:] for c in cols)], len(cols[0]) - upto
        if size:
            yield row(*[np.concatenate(x) for x in zip(*held)], gaps)

    return edges.select("src", "dst", "weight").repartition("src").sortWithinPartitions("src").mapInArrow(rows, _ROW)


def unpack(rows: DataFrame) -> DataFrame:
    """The edges, ``[src, dst, weight]``."""

    def edges(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for src, n, dst, weight in zip(*(b[c].to_pylist() for c in ("src", "n", "dst", "weight"))):
                dst = np.frombuffer(dst, "i8")
                cols = [np.repeat(np.frombuffer(src, "i8"), np.frombuffer(n, "i8")), dst, np.frombuffer(weight, f"i{len(weight) // len(dst)}").astype("i8")]
                for i in range(0, len(dst), 100_000):
                    part = [c[i : i + 100_000] for c in cols]
                    yield pa.record_batch([pa.array(c, mask=c == _NULL) for c in part], names=["src", "dst", "weight"])

    return rows.select("src", "n", "dst", "weight").mapInArrow(edges, "src long, dst long, weight long")


def sources(rows: DataFrame) -> DataFrame:
    """``[id, n]``: each source and its number of edges."""

    def ids(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for src, n in zip(b["src"].to_pylist(), b["n"].to_pylist()):
                src = np.frombuffer(src, "i8")
                yield pa.record_batch([pa.array(src, mask=src == _NULL), pa.array(np.frombuffer(n, "i8"))], names=["id", "n"])

    return rows.select("src", "n").mapInArrow(ids, "id long, n long")


def folder(spark: SparkSession) -> str | None:
    """A path below which driver and tasks can open files of the shared folder; None where that isn't a file system of the machines."""
    shared_dir(spark)
    try:
        fs, path = pafs.FileSystem.from_uri(spark.sparkContext.getCheckpointDir())
    except (pa.ArrowException, ValueError, OSError):
        return None
    return path if isinstance(fs, pafs.LocalFileSystem) else None


@dataclass
class Numbered:
    """Edges whose ends are numbers, in files of the shared folder. ``base``: ``ids`` (sorted), ``at`` and ``deg`` of the sources below it;
    ``files``: their names, and the number of the first edge in each."""

    base: str
    files: list[str]
    firsts: np.ndarray
    wide: str
    count: int
    edges: int

    def vertices(self, spark: SparkSession) -> DataFrame:
        path = f"{self.base}-ids.npy"

        def ids(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                if b.num_rows:
                    yield pa.record_batch([pa.array(np.load(path))], names=["id"])

        return spark.range(0, 1, 1, 1).mapInArrow(ids, "id long")

    def ids(self) -> np.ndarray:
        return np.load(f"{self.base}-ids.npy")

    def open(self, weights: bool = True) -> Reach:
        return Reach(self, weights)


class Reach:
    """The numbered edges as a task sees them; only what is looked at is read."""

    def __init__(self, of: Numbered, weights: bool):
        self.at, self.deg, self.firsts = np.load(f"{of.base}-at.npy"), np.load(f"{of.base}-deg.npy"), of.firsts
        self.near = [np.memmap(f, "i4", "r") for f in of.files]
        self.by = [np.memmap(f"{f}.w", of.wide, "r") for f in of.files] if weights else None

    def out(self, of: np.ndarray, most: int = 2_000_000) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray | None]]:
        """The edges out of some vertices, about ``most`` at a time: the place in ``of`` of an edge's source, its other end, its weight."""
        place = np.flatnonzero((of < len(self.deg)) & (self.deg[np.minimum(of, len(self.deg) - 1)] > 0)) if len(self.deg) else np.empty(0, "i8")
        start = self.at[of[place]]
        order = np.argsort(start, kind="stable")
        place, start = place[order], start[order]
        deg = self.deg[of[place]]
        file = np.searchsorted(self.firsts, start, "right") - 1
        ends = np.cumsum(deg)
        # A part ends with its file, or when it has enough.
        cuts = runs(file * (int(ends[-1]) // most + 2) + (ends - deg) // most) if len(place) else [0]
        for i, j in zip(cuts[:-1], cuts[1:]):
            d = deg[i:j]
            e = np.cumsum(d)
            edge = np.repeat(start[i:j] - self.firsts[file[i]] - (e - d), d) + np.arange(e[-1])
            yield np.repeat(place[i:j], d), self.near[file[i]][edge], self.by[file[i]][edge] if self.by else None


def numbered(spark: SparkSession, rows: DataFrame, ends: np.ndarray | None = None) -> Numbered | None:
    """The edges of packed rows as files; None if they can't be, or have nulls or too many vertices. With ``ends`` (sorted) the other ends are
    numbers of these ids, otherwise both ends are numbered together."""
    path = folder(spark)
    total = rows.agg(F.sum("edges"), F.min("low"), F.max("high"), F.sum("gaps"), F.sum(F.octet_length("n") / 8)).first()
    if path is None or total[3] or (total[4] or 0) > HELD:
        return None
    told = sources(rows).toArrow()
    src = told["id"].to_numpy()
    ids, wide = np.sort(src), "i4" if total[0] and -(1 << 31) < total[1] and total[2] < 1 << 31 else "i8"
    while True:
        base = f"{path}/numbered-{uuid.uuid4().hex}"
        keys = ids if ends is None else ends
        np.save(f"{base}-ids.npy", ids)
        np.save(f"{base}-keys.npy", keys)
        lies = rows.select("src", "n", "dst", "weight").mapInArrow(_filed(base, wide), "file string, src binary, n binary, lost binary").toArrow()
        lost = [np.frombuffer(x, "i8") for x in lies["lost"].to_pylist()]
        lost = np.unique(np.concatenate(lost)) if lost else np.empty(0, "i8")
        if not len(lost):
            break
        if ends is not None or len(ids) + len(lost) > HELD:
            return None
        ids = np.sort(np.r_[ids, lost])
    at, deg = np.zeros(len(ids), "i8"), np.zeros(len(ids), "i8")
    files, firsts, upto = [], [], 0
    for f, s, n in zip(*(lies[c].to_pylist() for c in ("file", "src", "n"))):
        s, n = (np.frombuffer(x, "i8") for x in (s, n))
        if not files or files[-1] != f:
            files.append(f)
            firsts.append(upto)
        i = np.searchsorted(ids, s)
        at[i], deg[i] = upto + np.cumsum(n) - n, n
        upto += int(n.sum())
    np.save(f"{base}-at.npy", at)
    np.save(f"{base}-deg.npy", deg)
    return Numbered(base, files, np.array(firsts, "i8"), wide, len(ids), upto)


def _filed(base: str, wide: str):
    """Writes a task's edges as numbers to a file of its own (a task that is run again takes another), and says where they lie."""

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, name = np.load(f"{base}-keys.npy", mmap_mode="r"), f"{base}-{uuid.uuid4().hex}"
        with open(name, "wb") as near, open(f"{name}.w", "wb") as by:
            for b in batches:
                for src, n, dst, weight in zip(*(b[c].to_pylist() for c in ("src", "n", "dst", "weight"))):
                    dst = np.frombuffer(dst, "i8")
                    i = np.searchsorted(keys, dst)
                    lost = keys[np.minimum(i, len(keys) - 1)] != dst
                    near.write(i.astype("i4").tobytes())
                    by.write(np.frombuffer(weight, f"i{len(weight) // len(dst)}").astype(wide).tobytes())
                    yield pa.record_batch([pa.array([x], t) for x, t in ((name, pa.string()), (src, pa.binary()), (n, pa.binary()), (np.unique(dst[lost]).tobytes(), pa.binary()))], names=["file", "src", "n", "lost"])

    return write
