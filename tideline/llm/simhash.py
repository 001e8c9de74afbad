"""SimHash near-duplicate detection with bit-sliced comparison.

Fingerprints of whole texts are made in Arrow batches. Equal fingerprints collapse before anything is compared.
Links come from exact blocking: the 64 bits are cut into ``radius + 2`` blocks, and two fingerprints at most
``radius`` bits apart agree on some pair of blocks, so every pair of blocks is one bucket key. Within a bucket the
bits stand vertically (one long integer per bit, one column per fingerprint); a query's distances to all columns
are counted at once by carry-save addition, and a block is given up when no column can still be within the
radius. A bucket answers with a spanning forest of its links, never with its pairs. Buckets over ``block`` rows are
dealt to tasks by pairs of chunks, so no task holds more than two chunks.

Nulls, empties, repeats: a null or empty text has fingerprint zero and links like any other. A row with a null id
gets a fingerprint and the component of other rows with that fingerprint, else null; it makes no link of its own.
Repeated rows each come back. An empty table gives an empty result. Only the named columns are read.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tideline.llm.common import Forest, pieces, runs
from tideline.operators.components import connected_components
from tideline.sources.tables import cut

BITS = 64
_LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))


def fingerprint(text: str | None, words: int = 3) -> int:
    """Unsigned 64-bit SimHash of a text's word shingles (XXH64, seed 42)."""
    ws = (text or "").encode().translate(_LOWER).split()
    if not ws:
        return 0
    if len(ws) <= words:
        hashes = np.array([xxhash.xxh64_intdigest(b" ".join(ws), 42)], dtype=np.uint64)
    else:
        buf, ends = b" ".join(ws), np.cumsum([len(w) + 1 for w in ws]) - 1
        starts = np.r_[0, ends[:-1] + 1]
        h = xxhash.xxh64_intdigest
        spans = zip(starts[: len(ws) - words + 1].tolist(), ends[words - 1 :].tolist())
        hashes = np.fromiter((h(buf[a:b], 42) for a, b in spans), np.uint64, len(ws) - words + 1)
    ones = np.zeros(BITS, dtype=np.int64)
    for at in range(0, len(hashes), 1 << 15):
        ones += np.unpackbits(hashes[at : at + (1 << 15)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * ones > len(hashes), bitorder="little").tobytes(), "little")


def fingerprints(docs: DataFrame, words: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``[doc_id long, fp long]``, a row for each row of ``docs``; fp holds the 64 bits as a signed number."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in pieces(batches, "text"):
            fps = np.fromiter((fingerprint(t, words) for t in b["text"].to_pylist()), np.uint64, b.num_rows)
            yield pa.record_batch([b["doc_id"], pa.array(fps.view(np.int64))], names=["doc_id", "fp"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(rows, "doc_id long, fp long")


def bit_planes(fps: np.ndarray) -> list[int]:
    """Plane k has bit j set where fingerprint j has bit k set."""
    bits = np.unpackbits(fps.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    return [int.from_bytes(np.packbits(bits[:, k], bitorder="little").tobytes(), "little") for k in range(BITS)]


def sliced_links(fps: np.ndarray, radius: int, skip: int = 0) -> Forest:
    """Union-find over the positions of ``fps`` that joins those at most ``radius`` bits apart.

    ``skip``: bits on which all are known to agree. Columns that are already in the query's tree, or before it,
    start as given up, so a dense group costs about one pass per member.
    """
    n, full = len(fps), (1 << len(fps)) - 1
    planes = bit_planes(fps)
    order = [k for k in range(BITS) if not skip >> k & 1]
    limit, width = radius + 1, (radius + 1).bit_length()
    forest = Forest(n)
    for i, fp in enumerate(fps.tolist()):
        gone = ((1 << (i + 1)) - 1) | forest.mask[forest.find(i)]
        if gone == full:
            continue
        count = [0] * width
        for k in order:
            carry = planes[k] ^ full if fp >> k & 1 else planes[k]
            for w in range(width):
                count[w], carry = count[w] ^ carry, count[w] & carry
            over = full
            for w in range(width):
                over &= count[w] if limit >> w & 1 else count[w] ^ full
            gone |= over
            if gone == full:
                break
        near = full & ~gone
        while near:
            j = (near & -near).bit_length() - 1
            forest.join(i, j)
            near &= ~forest.mask[forest.find(i)]
    return forest


def near_links(distinct: DataFrame, radius: int = 2, block: int = 4096) -> DataFrame:
    """``[a, b]``: a spanning forest of the links between the rows of ``[rep, fp]``, whose fps are distinct."""
    n_blocks = radius + 2
    edges = [BITS * i // n_blocks for i in range(n_blocks + 1)]
    masks = [sum((1 << edges[x + 1]) - (1 << edges[x]) for x in pair) for pair in combinations(range(n_blocks), 2)]
    signed = [m - (1 << 64) if m >> 63 else m for m in masks]
    keyed = distinct.select("rep", "fp", F.explode(F.array(*[F.struct(F.lit(k).alias("k"), F.col("fp").bitwiseAND(F.lit(m).cast("long")).alias("v")) for k, m in enumerate(signed)])).alias("x")).select("rep", "fp", "x.k", "x.v")
    shared = keyed.groupBy("k", "v").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    chunks = F.ceil(F.col("n") / F.lit(block)).cast("int")
    mine = F.pmod(F.xxhash64("fp"), "s").cast("int")
    units = keyed.join(shared, ["k", "v"]).withColumn("s", chunks).withColumn("i", mine).withColumn("j", F.explode(F.sequence(F.lit(0), F.col("s") - 1)))
    units = units.select("k", "v", F.least("i", "j").alias("i"), F.greatest("i", "j").alias("j"), "fp", "rep")
    keys = ["k", "v", "i", "j"]

    def link(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for g in runs(batches, keys):
            if len(g["fp"]) < 2:
                continue
            fps = np.array(g["fp"], dtype=np.int64).view(np.uint64)
            root = sliced_links(fps, radius, masks[g["k"][0]]).roots()
            pairs = [(x, r) for x, r in enumerate(root) if x != r]
            if pairs:
                yield pa.record_batch([pa.array([g["rep"][x] for x, _ in pairs], pa.int64()), pa.array([g["rep"][r] for _, r in pairs], pa.int64())], names=["a", "b"])

    return units.repartition(*keys).sortWithinPartitions(*keys).mapInArrow(link, "a long, b long")


def near_duplicates(docs: DataFrame, words: int = 3, radius: int = 2, id_col: str = "doc_id", text_col: str = "text", small: int = 0) -> DataFrame:
    """``[doc_id, fp, component_id]`` for each row of ``docs``; see the module for the rules. Up to ``small`` links are joined in one task."""
    fps = cut(fingerprints(docs, words, id_col, text_col))
    distinct = cut(fps.where("doc_id is not null").groupBy("fp").agg(F.min("doc_id").alias("rep")))
    comp = connected_components(near_links(distinct, radius), small=small)
    classes = distinct.join(comp, distinct["rep"] == comp["id"], "left").select("fp", F.coalesce("component", "rep").alias("component_id"))
    return fps.join(classes, "fp", "left").select("doc_id", "fp", "component_id")


#: Ids that may be broadcast: at some 24 bytes each, 48 MB at the most.
SIEVE = 2_000_000
#: Links that may be joined in one task: at some 100 bytes each, 25 MB at the most.
ONE_TASK = 250_000


def keep_one(docs: DataFrame, words: int = 3, radius: int = 2, sieve: int = SIEVE) -> DataFrame:
    """The documents of ``docs`` that lead their group; repeated rows of a leader shrink to one, null ids stay. Two texts under a
    leader's id both stay.

    What goes, and the leaders that are there more than once, are looked for without their texts. While these are at most ``sieve`` ids they are broadcast,
    and the texts of all other rows stay where they are.
    """
    own = docs.columns
    near = near_duplicates(docs, words, radius, "doc_id", "text", ONE_TASK).where("doc_id is not null")
    ids = cut(near.groupBy(F.col("doc_id").alias("__id")).agg(F.max(F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(False))).alias("__leads"), F.count(F.lit(1)).alias("__rows")))
    odd = ids.where("not __leads or __rows > 1").select("__id", "__leads")
    if odd.count() <= sieve:
        odd = F.broadcast(odd)
    tagged = docs.join(odd, docs["doc_id"].cast("long") == F.col("__id"), "left")
    lead = tagged.where("__leads").withColumn("__hash", F.xxhash64("text")).dropDuplicates(["doc_id", "__hash"])
    # Ids that are null meet no other, so they are among the rows without a mark.
    return tagged.where("__leads is null").select(*own).unionByName(lead.select(*own))


def keep_similar(docs: DataFrame, words: int = 5) -> DataFrame:
    """The first document of each group of texts whose word shingles have a Jaccard similarity of 4/5 and more.

    Such texts' fingerprints are some ten of 64 bits apart, texts without anything in common 32 on average: a radius that
    reaches most of the former has no block plan that prunes. So fingerprints here are parity sketches, whose distance is a bound and loses
    no pair, buckets come from the shingles themselves, and what passes is verified; see :mod:`tideline.llm.shingles`.
    """
    from tideline.llm import shingles

    return shingles.keep_one(docs, words)
