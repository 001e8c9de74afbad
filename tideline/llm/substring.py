"""Exact removal of word windows that an earlier document already has.

A document's windows of ``window`` words are cut into super-k-mers: runs of consecutive windows with the same
minimiser, the smallest hash among the window's ``gram``-word grams. A first pass over the texts keeps only
(minimiser, document, run); a minimiser that only one distinct text has needs no further look, since equal windows
have equal minimisers. The others travel as packed strings (the run's words, joined by a space) to their
minimiser's bucket, where sorting the windows brings equal ones together, smallest document first. There hashes only
choose buckets; windows are compared as bytes.

Equal whole texts collapse first (SHA-256), so a large group of copies costs one text. Buckets over ``hot`` rows are
not gathered: their windows go out one by one under a cryptographic digest of their bytes (BLAKE2b, 128 bits), and the smallest document
for each digest is found by a partial aggregate before the shuffle; then every document that has it is told by a join that Spark may split.
Among 2^44 windows the chance that two different ones share a digest is below 2^-40; sending their bytes instead would be some
ten times the text of such a bucket.

Nulls, empties, repeats: a null text has no words. A row with a null id neither removes nor loses words. Repeated
rows count as one document and each come back. Two texts under one id are judged apart, and neither is the other's earlier document. Documents under ``window`` words keep everything. An empty table gives
an empty result. Only the named columns are read; ``kept`` and the counts are added to them.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from tideline.llm.common import MEMORIES, forgetting, pieces, runs
from tideline.sources.tables import cut

_MULT = np.uint64(0x9E3779B97F4A7C15)


class _WordHash(dict):
    """XXH64 of words, remembered up to a bound."""

    def __missing__(self, w: bytes) -> int:
        if len(self) > 200_000:
            self.clear()
        self[w] = h = xxhash.xxh64_intdigest(w)
        return h


_HASHES = _WordHash()
MEMORIES["word hashes"] = _HASHES.clear


def super_kmers(words: list[bytes], window: int = 50, gram: int = 16) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Minimiser, first window and number of windows of each run of a document's windows."""
    n = len(words) - window + 1
    if n < 1:
        return np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0, np.int64)
    h = np.fromiter(map(_HASHES.__getitem__, words), np.uint64, len(words))
    g = np.zeros(len(words) - gram + 1, dtype=np.uint64)
    for j in range(gram):
        g = g * _MULT + h[j : len(g) + j]
    g ^= g >> np.uint64(31)
    g *= _MULT
    g ^= g >> np.uint64(29)
    # The minimum over 2^k places, then over any longer stretch from two of those.
    span, low, have = window - gram + 1, g, 1
    while 2 * have <= span:
        low = np.minimum(low[: len(low) - have], low[have:])
        have *= 2
    m = np.minimum(low[:n], low[span - have : span - have + n])
    first = np.flatnonzero(np.r_[True, m[1:] != m[:-1]])
    return m[first].view(np.int64), first, np.diff(np.r_[first, n])


def _keyed(docs: DataFrame, id_col: str, text_col: str, carry: list[str]) -> DataFrame:
    """Texts by id and tag. Carried columns share one column with the text, so that every use of the texts can read one shuffle."""
    text = F.col(text_col)
    body = F.struct(text.alias("text"), *[F.col(c).alias(f"c{i}") for i, c in enumerate(carry)]) if carry else text
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), text.isNull().alias("bare"), body.alias("text"), F.xxhash64(text.cast("string")).alias("tag"))


def _opened(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The batches with the text, and what it carries, in columns of their own."""
    for b in batches:
        if pa.types.is_struct(b["text"].type):
            rest = {n: b[n] for n in b.schema.names if n != "text"}
            names = [f.name for f in b["text"].type]
            b = pa.record_batch(rest | dict(zip(names, b["text"].flatten())))
        yield b


def _first_pass(keyed: DataFrame, window: int, gram: int) -> DataFrame:
    schema = "doc_id long, tag long, th binary, mz array<long>, at array<long>, n array<long>"

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in pieces(batches, "text"):
            raw = [t.encode() for t in b["text"].to_pylist()]
            found = [super_kmers(t.split(), window, gram) for t in raw]
            keep = [i for i, f in enumerate(found) if len(f[0])]
            if not keep:
                continue
            ends = np.r_[0, np.cumsum([len(found[i][0]) for i in keep])].astype("i4")
            cols = [pa.ListArray.from_arrays(ends, np.concatenate([found[i][c] for i in keep])) for c in range(3)]
            whole = pa.array([hashlib.sha256(raw[i]).digest() for i in keep], pa.binary())
            yield pa.record_batch([b["doc_id"].take(pa.array(keep)), b["tag"].take(pa.array(keep)), whole, *cols], names=["doc_id", "tag", "th", "mz", "at", "n"])

    return keyed.where("doc_id is not null and text is not null").mapInArrow(forgetting(rows), schema)


_PACKED = "mz long, doc_id long, tag long, at long, packed binary"


def _pack(window: int):
    """A function of batches of texts: packed strings of the runs that they are asked for."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in pieces(_opened(batches), "text"):
            out = []
            for d, g, t, asked in zip(*(b[c].to_pylist() for c in ("doc_id", "tag", "text", "runs"))):
                ws = t.encode().split()
                out += [(r["mz"], d, g, r["at"], b" ".join(ws[r["at"] : r["at"] + r["n"] + window - 1])) for r in asked]
            for at in range(0, len(out), 5000):
                cols = list(zip(*out[at : at + 5000]))
                yield pa.record_batch([pa.array(c, k) for c, k in zip(cols, (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.binary()))], names=["mz", "doc_id", "tag", "at", "packed"])

    return rows


def windows_of(packed: bytes, window: int) -> list[bytes]:
    """The windows of a packed string, each as the bytes of its words."""
    ends = np.cumsum([len(w) + 1 for w in packed.split(b" ")])
    starts = np.r_[0, ends[:-1]].tolist()
    return [packed[a : b - 1] for a, b in zip(starts, ends[window - 1 :].tolist())]


def _spans(hits: list[int], window: int) -> list[tuple[int, int]]:
    """Word ranges that the windows starting at the sorted ``hits`` cover."""
    out: list[tuple[int, int]] = []
    for x in hits:
        if out and x <= out[-1][1]:
            out[-1] = (out[-1][0], x + window)
        else:
            out.append((x, x + window))
    return out


_SPAN = "doc_id long, tag long, s long, e long"


def _span_batch(rows: list[tuple[int, int, int, int]]) -> pa.RecordBatch:
    return pa.record_batch([pa.array([r[k] for r in rows], pa.int64()) for k in range(4)], names=["doc_id", "tag", "s", "e"])


def _sorted_buckets(texts: DataFrame, window: int) -> DataFrame:
    cold = texts.mapInArrow(_pack(window), _PACKED)

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out: list[tuple[int, int, int, int]] = []
        for g in runs(batches, ["mz"]):
            least: dict[bytes, int] = {}
            for p, d in zip(g["packed"], g["doc_id"]):
                least[p] = min(d, least.get(p, d))
            places = sorted((w, d, p, i) for p, d in least.items() for i, w in enumerate(windows_of(p, window)))
            owner: dict[bytes, list[int]] = {p: [0] * (1 + p.count(b" ") - window + 1) for p in least}
            last, first = None, 0
            for w, d, p, i in places:
                if w != last:
                    last, first = w, d
                owner[p][i] = first
            for p, d, tag, at in zip(g["packed"], g["doc_id"], g["tag"], g["at"]):
                out += [(d, tag, s, e) for s, e in _spans([at + i for i, o in enumerate(owner[p]) if o < d], window)]
            if len(out) > 20_000:
                yield _span_batch(out)
                out = []
        if out:
            yield _span_batch(out)

    return cold.repartition("mz").sortWithinPartitions("mz").mapInArrow(rows, _SPAN)


def _hot_windows(texts: DataFrame, window: int) -> DataFrame:
    pack = _pack(window)

    def digests(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in pack(batches):
            out: list[tuple[bytes, int, int, list[int]]] = []
            for p, d, tag, at in zip(*(b[c].to_pylist() for c in ("packed", "doc_id", "tag", "at"))):
                where: dict[bytes, list[int]] = {}
                for i, w in enumerate(windows_of(p, window)):
                    where.setdefault(hashlib.blake2b(w, digest_size=16).digest(), []).append(at + i)
                out += [(k, d, tag, v) for k, v in where.items()]
            for at in range(0, len(out), 10_000):
                cols = list(zip(*out[at : at + 10_000]))
                yield pa.record_batch([pa.array(c, k) for c, k in zip(cols, (pa.binary(), pa.int64(), pa.int64(), pa.list_(pa.int64())))], names=["k", "doc_id", "tag", "hits"])

    found = texts.mapInArrow(digests, "k binary, doc_id long, tag long, hits array<long>")
    owner = found.groupBy("k").agg(F.min("doc_id").alias("first"), F.max("doc_id").alias("last")).where("first < last").select("k", "first")
    lost = found.join(owner, "k").where("first < doc_id").select("doc_id", "tag", F.explode("hits").alias("s"))
    return lost.select("doc_id", "tag", "s", (F.col("s") + window).alias("e"))


def remove_repeats(docs: DataFrame, window: int = 50, gram: int = 16, hot: int = 512, id_col: str = "doc_id", text_col: str = "text", carry: list[str] | None = None) -> DataFrame:
    """``[doc_id, text, n_words, n_removed, kept]`` for each row of ``docs``; kept joins the words left by a space.

    The columns named in ``carry`` (none of those five) follow, unchanged.
    """
    carry = carry or []
    first = cut(_first_pass(_keyed(docs, id_col, text_col, []).drop("bare"), window, gram))
    # Ids and a short tag of the text name a document from here on; the digest only brings copies together.
    leads = cut(first.groupBy("th").agg(F.min(F.struct("doc_id", "tag")).alias("d")).select("d.doc_id", "d.tag"))
    kmers = first.join(leads, ["doc_id", "tag"], "left_semi").select("doc_id", "tag", F.explode(F.arrays_zip("mz", "at", "n")).alias("r")).select("doc_id", "tag", "r.mz", "r.at", "r.n")
    shared = kmers.groupBy("mz").agg(F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi"), F.count(F.lit(1)).alias("c")).where("lo < hi").select("mz", (F.col("c") > hot).alias("hot"))
    asked = kmers.join(shared, "mz").groupBy("doc_id", "tag").agg(F.collect_set(F.struct("mz", "hot", "at", "n")).alias("runs"))
    # Both kinds of run read one shuffle of the texts.
    keyed = _keyed(docs, id_col, text_col, carry)
    texts = keyed.where("doc_id is not null and not bare").drop("bare")

    def asking(hot_ones: bool) -> DataFrame:
        own = asked.withColumn("runs", F.filter("runs", lambda r: r["hot"] == F.lit(hot_ones))).where(F.size("runs") > 0)
        return texts.join(own, ["doc_id", "tag"]).select("doc_id", "tag", "text", "runs")

    spans = _sorted_buckets(asking(False), window).unionByName(_hot_windows(asking(True), window))
    spans = spans.groupBy("doc_id", "tag").agg(F.collect_set(F.struct("s", "e")).alias("spans"))
    judged = leads.join(spans, ["doc_id", "tag"], "left").select("doc_id", "tag", F.coalesce("spans", F.array().cast("array<struct<s:long,e:long>>")).alias("spans"))
    # A text that isn't the first of its copies has each of its windows in the first one.
    schema = StructType.fromDDL("doc_id long, text string, n_words long, n_removed long, kept string")
    for c in carry:
        schema = schema.add(c, docs.schema[c].dataType)

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in pieces(_opened(batches), "text"):
            out = []
            for d, t, cuts in zip(b["doc_id"].to_pylist(), b["text"].to_pylist(), b["spans"].to_pylist()):
                ws = (t or "").encode().split()
                n = len(ws)
                gone = np.zeros(n, dtype=bool)
                if cuts is not None:
                    for x in cuts:
                        gone[x["s"] : x["e"]] = True
                elif d is not None and n >= window:
                    gone[:] = True
                lost = int(gone.sum())
                kept = b" ".join(ws) if not lost else b" ".join(w for w, x in zip(ws, gone.tolist()) if not x)
                out.append((d, t, n, lost, kept.decode()))
            cols = list(zip(*out))
            own = [pa.array(c, k) for c, k in zip(cols, (pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string()))]
            yield pa.record_batch([*own, *[b[f"c{i}"] for i in range(len(carry))]], names=schema.names)

    bare = keyed.where("doc_id is null or bare").select("doc_id", "text", F.lit(None).cast("array<struct<s:long,e:long>>").alias("spans"))
    return texts.join(judged, ["doc_id", "tag"], "left").select("doc_id", "text", "spans").unionByName(bare).mapInArrow(rows, schema)


def digest(kept: str) -> str:
    """Lowercase SHA-256 of a kept text."""
    return hashlib.sha256(kept.encode()).hexdigest()
