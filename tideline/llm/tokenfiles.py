"""Token ids in files of independent Zstandard frames with a seek table and checksums.

Documents are range-sorted by id; every task writes one file. A file is

    data frames     one or more whole documents each: their ids, little-endian unsigned 32-bit
    directory       a frame with a row for each document: id, number of ids, data frame, a flag (1: the id is null)
    seek table      a skippable frame in the seekable format: for each frame its packed size, its plain size and
                    the low 32 bits of XXH64 (seed 0) of its plain bytes; then the number of frames, 0x80, a magic number

so a reader takes the end of the file, then the directory, then only the frames of the documents asked for, and
checks each. A file has a name of its own for each attempt of a task, and the manifest (a parquet table beside the files)
names those of the attempts that counted: a lost executor leaves at most a file that nobody refers to.

Files lie in the shared folder, through the file system that its URI names. Ids that are null come first, then ascending
ids; equal ids in the order of their texts' hashes. A null or empty text is just its end id. Repeated rows each come back.
An empty table gives an empty result. Only the named columns are read.
"""

from __future__ import annotations

import struct
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
import xxhash
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tideline.llm.common import encoder, forgetting, pieces
from tideline.sources.tables import shared_dir

#: Fixed values of the seekable format.
_SKIPPABLE, _SEEKABLE, _CHECKED = 0x184D2A5E, 0x8F92EAB1, 0x80
_ENTRY = np.dtype([("doc", "<i8"), ("n", "<u4"), ("frame", "<u4"), ("null", "<u1")])


def _system(uri: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(uri)


def resolved(spark: SparkSession, folder: str) -> str:
    """The folder's full URI as Spark understands it: a path without a scheme lies in Spark's default file system, for the
    files as for the manifest. A small table in the folder tells which one that is."""
    if "://" in folder:
        return folder
    spark.range(1).write.mode("overwrite").parquet(f"{folder}/place.parquet")
    return spark.read.parquet(f"{folder}/place.parquet").inputFiles()[0].rpartition("/place.parquet/")[0]


class FrameWriter:
    """One file; documents go in one after the other."""

    def __init__(self, out, frame_bytes: int = 1 << 18, level: int = 3):
        self.out, self.most, self.zip = out, frame_bytes, zstandard.ZstdCompressor(level=level)
        self.table: list[tuple[int, int, int]] = []
        self.entries: list[tuple[int, int, int, int]] = []
        self.held: list[bytes] = []
        self.size = 0

    def _frame(self, plain: bytes) -> None:
        packed = self.zip.compress(plain)
        self.out.write(packed)
        self.table.append((len(packed), len(plain), xxhash.xxh64_intdigest(plain) & 0xFFFFFFFF))

    def add(self, doc: int | None, ids: np.ndarray) -> None:
        raw = ids.astype("<u4").tobytes()
        if self.held and self.size + len(raw) > self.most:
            self._flush()
        self.entries.append((doc or 0, len(ids), len(self.table), doc is None))
        self.held.append(raw)
        self.size += len(raw)

    def _flush(self) -> None:
        if self.held:
            self._frame(b"".join(self.held))
            self.held, self.size = [], 0

    def end(self) -> None:
        self._flush()
        self._frame(np.array(self.entries, dtype=_ENTRY).tobytes())
        rows = b"".join(struct.pack("<III", *t) for t in self.table)
        self.out.write(struct.pack("<II", _SKIPPABLE, len(rows) + 9) + rows + struct.pack("<IBI", len(self.table), _CHECKED, _SEEKABLE))


class FrameReader:
    """Documents of one file, in any order; ``frames_read`` counts the frames it had to unpack."""

    def __init__(self, file):
        self.file, self.frames_read = file, 0
        size = file.size()
        n, flags, magic = struct.unpack("<IBI", self._at(size - 9, 9))
        if magic != _SEEKABLE or flags != _CHECKED:
            raise ValueError("no seek table")
        table = self._at(size - 9 - 12 * n - 8, 12 * n + 8)
        if struct.unpack("<II", table[:8]) != (_SKIPPABLE, 12 * n + 9):
            raise ValueError("no seek table")
        self.table = np.frombuffer(table[8:], dtype=[("packed", "<u4"), ("plain", "<u4"), ("sum", "<u4")])
        self.starts = np.r_[0, np.cumsum(self.table["packed"].astype("i8"))]
        self.entries = np.frombuffer(self.frame(n - 1), dtype=_ENTRY)
        ends = np.cumsum(self.entries["n"].astype("i8"))
        self.first = ends - self.entries["n"]
        self.frame_first = {int(f): int(s) for f, s in zip(self.entries["frame"][::-1], self.first[::-1])}

    def _at(self, start: int, size: int) -> bytes:
        self.file.seek(int(start))
        return self.file.read(int(size))

    def frame(self, k: int) -> bytes:
        plain = zstandard.ZstdDecompressor().decompress(self._at(self.starts[k], self.table["packed"][k]), max_output_size=int(self.table["plain"][k]))
        if len(plain) != self.table["plain"][k] or xxhash.xxh64_intdigest(plain) & 0xFFFFFFFF != self.table["sum"][k]:
            raise ValueError(f"frame {k} is damaged")
        self.frames_read += 1
        return plain

    def documents(self, wanted: np.ndarray | None = None) -> Iterator[tuple[int | None, int, np.ndarray]]:
        """(id, ids before it in this file, its ids) of the entries at ``wanted`` (all, if None), each frame unpacked once."""
        held, ids = -1, None
        for i in range(len(self.entries)) if wanted is None else sorted(int(x) for x in wanted):
            e = self.entries[i]
            if e["frame"] != held:
                held, ids = e["frame"], np.frombuffer(self.frame(int(e["frame"])), dtype="<u4")
            s = int(self.first[i]) - self.frame_first[int(e["frame"])]
            yield None if e["null"] else int(e["doc"]), int(self.first[i]), ids[s : s + int(e["n"])]

    def find(self, doc: int) -> np.ndarray:
        """Places of an id in the directory."""
        return np.flatnonzero((self.entries["doc"] == doc) & (self.entries["null"] == 0))


_MANIFEST = "part int, file string, docs long, ids long, bytes long"


def write(docs: DataFrame, vocabulary: str, folder: str | None = None, end_id: int = 0, frame_bytes: int = 1 << 18, id_col: str = "doc_id", text_col: str = "text") -> str:
    """Writes all documents of ``docs`` and returns the folder that holds the files and ``manifest.parquet``."""
    spark = docs.sparkSession
    folder = resolved(spark, folder or f"{shared_dir(spark)}/tokens-{uuid.uuid4().hex}")
    _system(folder)[0].create_dir(_system(folder)[1], recursive=True)

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task = TaskContext.get()
        part, name = task.partitionId(), f"part-{task.partitionId():06d}-{task.taskAttemptId()}-{uuid.uuid4().hex}.zst"
        fs, path = _system(f"{folder}/{name}")
        out = writer = None
        n = ids = 0
        for b in pieces(batches, "text", 1 << 20):
            if out is None:
                fs.create_dir(path.rpartition("/")[0], recursive=True)
                out = fs.open_output_stream(path, compression=None)
                writer = FrameWriter(out, frame_bytes)
            flat, at = encoder(vocabulary).encode(b["text"])
            for doc, s, e in zip(b["doc_id"].to_pylist(), at[:-1].tolist(), at[1:].tolist()):
                writer.add(doc, np.r_[flat[s:e], np.uint32(end_id)])
                n, ids = n + 1, ids + e - s + 1
        if out is not None:
            writer.end()
            size = out.tell()
            out.close()
            yield pa.record_batch([pa.array([part], pa.int32()), pa.array([name]), pa.array([n], pa.int64()), pa.array([ids], pa.int64()), pa.array([size], pa.int64())], names=[x.split()[0] for x in _MANIFEST.split(", ")])

    keyed = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    # The text's hash is part of the range, so that many rows with one id, or with none, are dealt to many tasks.
    order = [F.col("doc_id").asc_nulls_first(), F.xxhash64("text")]
    ordered = keyed.repartitionByRange(*order).sortWithinPartitions(*order)
    ordered.mapInArrow(forgetting(rows), _MANIFEST).write.parquet(f"{folder}/manifest.parquet")
    return folder


def read(spark: SparkSession, folder: str) -> DataFrame:
    """``[doc_id, start, n_tokens, ids]`` of all documents of a folder; ids as little-endian unsigned 32-bit integers."""
    folder = resolved(spark, folder)
    files = spark.read.parquet(f"{folder}/manifest.parquet")
    # One row a file: a running sum over the manifest is small. A number of tasks that is asked for stays as it is: one for each file.
    n = max(1, files.count())
    placed = files.withColumn("base", F.coalesce(F.sum("ids").over(W.orderBy("part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))).select("file", "base")

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for name, base in zip(b["file"].to_pylist(), b["base"].to_pylist()):
                fs, path = _system(f"{folder}/{name}")
                with fs.open_input_file(path) as f:
                    held, size = [], 0
                    for d, s, ids in FrameReader(f).documents():
                        held.append((d, base + s, len(ids), ids.tobytes()))
                        size += len(ids)
                        if size > 1 << 20:
                            yield _batch(held)
                            held, size = [], 0
                    if held:
                        yield _batch(held)

    return placed.repartitionByRange(n, "base").mapInArrow(rows, "doc_id long, start long, n_tokens long, ids binary")


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    return pa.record_batch([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int64(), pa.int64(), pa.int64(), pa.binary()))], names=["doc_id", "start", "n_tokens", "ids"])
