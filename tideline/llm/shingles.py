"""Near-duplicates by exact Jaccard similarity of word shingles (4/5 and more), without a fingerprint's misses.

Shingles are known by 64-bit hashes. Two sets that similar share a shingle among the first n - ceil(0.8 n) + 1 of each,
in any order that is the same for all; the order here is by hash with frequent shingles last, so that a common
passage seldom makes a bucket. Frequent ones are looked for in a sample: it shapes the buckets, never the result.

Candidates travel as numbers. Every member of a bucket is paired with the smallest one, each pair once whatever the number of buckets
that offer it; then buckets whose members are not all in one group yet compare the rest. A pair is looked at through parity
sketches first: an element toggles one bit, so two sketches differ in at most as many bits as the sets differ in elements, and a pair
beyond that bound is none. A sketch has about a bit for each shingle, so that it tells long texts apart too; the longer one of
two is folded. What is left is verified on the texts: a star's middle travels once for each ``fan`` of its members.
Buckets of up to ``small`` rows send no sketches, since their pairs are few and recur from bucket to bucket. Larger ones
compare sketches where they are, dealt in parts over ``block`` rows, and answer with a spanning forest of what may be similar, never with
its pairs. The trees of all these buckets together make cells: two similar sets that a large bucket holds and that are not in one group yet lie in
one cell. A cell's texts meet once, dealt in parts over ``deal`` shingles, and answer with a spanning forest of the pairs that are similar. Texts that take part in nothing stay where they are:
while the keys of those that do are at most ``SIEVE`` rows they are broadcast as hashes, and only rows with such a hash meet the exact join.

Nulls, empties, repeats: a null or empty text has no shingle and equals others like it; a text of fewer words than a
shingle is one shingle. Rows with a null id are in no group. Two texts under one id are two documents. An empty table
gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tideline.llm.common import forgetting, pieces, runs
from tideline.llm.simhash import _LOWER, ONE_TASK
from tideline.llm.substring import _HASHES, _MULT
from tideline.operators.components import connected_components
from tideline.sources.tables import cut

#: Least bits of a sketch.
WIDTH = 256
#: Keys that may be broadcast: at some 24 bytes each, 48 MB at the most.
SIEVE = 2_000_000


def shingles(text: str | None, words: int = 5) -> np.ndarray:
    """Sorted distinct hashes of a text's shingles, ASCII letters folded to lower case."""
    ws = (text or "").encode().translate(_LOWER).split()
    if not ws:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(_HASHES.__getitem__, ws), np.uint64, len(ws))
    k = min(words, len(ws))
    g = np.zeros(len(ws) - k + 1, dtype=np.uint64)
    for j in range(k):
        g = g * _MULT + h[j : len(g) + j]
    g ^= g >> np.uint64(31)
    g *= _MULT
    g ^= g >> np.uint64(29)
    return np.unique(g)


def similar(x: np.ndarray, y: np.ndarray) -> bool:
    """Whether two sets have a Jaccard similarity of 4/5 and more; equal empty ones do."""
    both = len(np.intersect1d(x, y, assume_unique=True))
    return 9 * both >= 4 * (len(x) + len(y))


def sketch(s: np.ndarray) -> bytes:
    """Parity of the shingles that fall on each bit; as many bits as the next power of two has from the set's size on."""
    width = max(WIDTH, 1 << max(0, len(s) - 1).bit_length())
    odd = np.bincount((s & np.uint64(width - 1)).astype("i8"), minlength=width) & 1
    return np.packbits(odd.astype(bool), bitorder="little").tobytes()


def folded(rows: np.ndarray, width: int) -> np.ndarray:
    """Sketches (a row each, of bytes) as sketches of ``width`` bytes: bits that share a place there add up."""
    while rows.shape[1] > width:
        half = rows.shape[1] // 2
        rows = rows[:, :half] ^ rows[:, half:]
    return rows


def may_be(a: bytes, b: bytes, n: int) -> bool:
    """Whether two sets of ``n`` elements together can be similar, by their sketches."""
    if len(a) != len(b):
        w = min(len(a), len(b))
        a, b = (folded(np.frombuffer(x, np.uint8)[None], w).tobytes() for x in (a, b))
    return 9 * (int.from_bytes(a, "little") ^ int.from_bytes(b, "little")).bit_count() <= n


def _frequent(docs: DataFrame, words: int, sample: int, most: int = 1 << 20) -> np.ndarray:
    """Sorted hashes that a sample of the documents has often, ``most`` of them at the most."""
    n = docs.count()
    some = docs.where(F.pmod(F.xxhash64("doc_id"), F.lit(max(1, n // sample))) == 0)

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in pieces(batches, "text"):
            yield pa.record_batch([pa.array(np.concatenate([shingles(t, words) for t in b["text"].to_pylist()]).view(np.int64))], names=["h"])

    found = some.select("text").mapInArrow(forgetting(rows), "h long").groupBy("h").count().where("count > 3").orderBy(F.desc("count"), "h").limit(most).select("h").toArrow()
    return np.sort(found["h"].to_numpy().view(np.uint64))


def _signed(docs: DataFrame, words: int, common: np.ndarray) -> DataFrame:
    """For each row: a digest of its set, the set's size and sketch, and the shingles that lead it."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in pieces(batches, "text"):
            name, size, bits, lead = [], [], [], []
            for t in b["text"].to_pylist():
                s = shingles(t, words)
                n = len(s)
                ordered = s
                if len(common):
                    often = common[np.minimum(np.searchsorted(common, s), len(common) - 1)] == s
                    ordered = np.concatenate([s[~often], s[often]])
                name.append(hashlib.blake2b(s.tobytes(), digest_size=16).digest())
                size.append(n)
                bits.append(sketch(s))
                lead.append(ordered[: n - (4 * n + 4) // 5 + 1])
            ends = np.r_[0, np.cumsum([len(x) for x in lead])].astype("i4")
            flat = pa.ListArray.from_arrays(ends, pa.array(np.concatenate(lead).view(np.int64)))
            yield pa.record_batch([b["doc_id"], b["tag"], pa.array(name, pa.binary()), pa.array(size, pa.int64()), pa.array(bits, pa.binary()), flat], names=["doc_id", "tag", "th", "n", "sketch", "lead"])

    return docs.mapInArrow(forgetting(rows), "doc_id long, tag long, th binary, n long, sketch binary, lead array<long>")


_PAIR = "a long, b long"


def _batch(pairs: list[tuple[int, int]]) -> pa.RecordBatch:
    return pa.record_batch([pa.array([p[k] for p in pairs], pa.int64()) for k in (0, 1)], names=["a", "b"])


def _possible(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """The pairs that pass their sketches."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x in batches:
            cols = [x[c].to_pylist() for c in ("a", "b", "na", "nb", "sa", "sb")]
            yield _batch([(a, b) for a, b, na, nb, sa, sb in zip(*cols) if may_be(sa, sb, na + nb)])

    one, two = (sets.select(F.col("v").alias(k), F.col("n").alias("n" + k), F.col("sketch").alias("s" + k)) for k in "ab")
    return pairs.join(one, "a").join(two, "b").where("5 * na >= 4 * nb and 5 * nb >= 4 * na").mapInArrow(rows, _PAIR)


def _near(group: np.ndarray, n: np.ndarray, sketches: list[bytes]) -> Iterator[tuple[int, np.ndarray]]:
    """Places of sets, each with places of others in different groups whose sketches let them be similar; each pair once. What the caller
    changes in ``group`` counts from then on."""
    width = np.array([len(x) for x in sketches])
    for w in np.unique(width).tolist():
        own, wider = np.flatnonzero(width == w), np.flatnonzero((width >= w) & (width <= 2 * w))
        rows = np.concatenate([folded(np.frombuffer(sketches[i], np.uint8)[None], w) for i in wider.tolist()]).view(np.uint64)
        place = np.searchsorted(wider, own)
        step = max(1, (1 << 22) // (len(wider) * rows.shape[1]))
        for at in range(0, len(own), step):
            i, p = own[at : at + step], place[at : at + step]
            far = np.bitwise_count(rows[p][:, None] ^ rows[None]).sum(2, dtype=np.int64)
            ok = (9 * far <= n[i][:, None] + n[wider]) & (group[i][:, None] != group[wider]) & ((width[wider] > w) | (wider > i[:, None]))
            for x in np.flatnonzero(ok.any(1)).tolist():
                yield int(i[x]), wider[ok[x]]


def _joined(label: np.ndarray, x: int, others: np.ndarray) -> list[int]:
    """Gives all of the others' labels' members the label of ``x``; one of the others for each label that went."""
    gone, first = np.unique(label[others], return_index=True)
    new = gone != label[x]
    if new.any():
        label[np.isin(label, gone[new])] = label[x]
    return others[first[new]].tolist()


def _paired(dealt: DataFrame, keys: list[str], pairs_of) -> DataFrame:
    """Distinct pairs that a function of a unit's columns gives."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out: set[tuple[int, int]] = set()
        for g in runs(batches, keys):
            for pair in pairs_of(g):
                out.add(pair)
                if len(out) > 200_000:
                    yield _batch(list(out))
                    out = set()
        if out:
            yield _batch(list(out))

    return dealt.repartition(*keys).sortWithinPartitions(*keys).mapInArrow(rows, _PAIR).distinct()


def _few(g: dict[str, list]) -> Iterator[tuple[int, int]]:
    """All pairs of a small bucket's members in different groups."""
    for x, (a, c) in enumerate(zip(g["v"], g["c"])):
        for b, e in zip(g["v"][:x], g["c"][:x]):
            if c != e:
                yield (a, b) if a < b else (b, a)


def _many(g: dict[str, list]) -> Iterator[tuple[int, int]]:
    """A spanning forest of the pairs of a large bucket's members in different groups that may be similar."""
    tree = np.arange(len(g["v"]))
    for x, others in _near(np.array(g["c"]), np.array(g["n"]), g["sketch"]):
        for y in _joined(tree, x, others):
            yield min(g["v"][x], g["v"][y]), max(g["v"][x], g["v"][y])


def _links(v: list[int], group: list[int], sets: list[np.ndarray]) -> list[tuple[int, int]]:
    """Similar pairs that join the groups of the sets as all similar pairs would."""
    label, n = np.unique(np.array(group), return_inverse=True)[1], np.array([len(s) for s in sets])
    if label.max() == 0:
        return []
    names, flat = np.unique(np.concatenate(sets), return_inverse=True)
    ends = np.cumsum(n)
    own = [flat[e - k : e] for e, k in zip(ends.tolist(), n.tolist())]
    marked, out = np.zeros(len(names), bool), []
    for x, others in _near(label, n, [sketch(s) for s in sets]):
        others = others[label[others] != label[x]]
        if not len(others):
            continue
        marked[own[x]] = True
        both = np.add.reduceat(marked[np.concatenate([own[y] for y in others.tolist()])], np.r_[0, np.cumsum(n[others])[:-1]], dtype=np.int64)
        marked[own[x]] = False
        out += [(min(v[x], v[y]), max(v[x], v[y])) for y in _joined(label, x, others[9 * both >= 4 * (n[x] + n[others])])]
    return out


def _rest(told: DataFrame, sets: DataFrame, tried: DataFrame, small: int, block: int) -> tuple[DataFrame, DataFrame]:
    """Of ``[h, size, v, c]`` with one h and different c: from small buckets the distinct pairs that pass the sketches and weren't tried,
    from larger ones a forest of the pairs that pass."""
    few = _paired(told.where(F.col("size") <= small).select("h", "v", "c"), ["h"], _few)
    parts = F.ceil(F.col("size") / F.lit(block)).cast("int")
    units = told.where(F.col("size") > small).join(sets.select("v", "n", "sketch"), "v").withColumn("s", parts).withColumn("i", F.pmod(F.xxhash64("v"), "s").cast("int")).withColumn("o", F.explode(F.sequence(F.lit(0), F.col("s") - 1)))
    many = _paired(units.select("h", F.least("i", "o").alias("i"), F.greatest("i", "o").alias("j"), "v", "c", "n", "sketch"), ["h", "i", "j"], _many)
    return _possible(few.join(tried, ["a", "b"], "left_anti"), sets), many


def _in_cells(forest: DataFrame, comp: DataFrame, sets: DataFrame, docs: DataFrame, words: int, deal: int) -> DataFrame:
    """Similar pairs that join, within each tree of the forest, the groups ``[v, component]`` of its sets as all similar pairs would."""
    cells = connected_components(forest, small=ONE_TASK).select(F.col("id").alias("v"), F.col("component").alias("cell"))
    rows = cut(cells.join(sets.select("v", "n", "doc_id", "tag"), "v").join(comp, "v", "left").withColumn("c", F.coalesce("component", "v")))
    parts = rows.groupBy("cell").agg(F.ceil(F.sum("n") / F.lit(deal)).cast("int").alias("s"))
    need = rows.join(parts, "cell").select("doc_id", "tag", "cell", "v", "c", "s", F.pmod(F.xxhash64("v"), "s").cast("int").alias("i"))
    sieve = _sieve(rows)
    some = docs if sieve is None else docs.join(sieve, F.xxhash64("doc_id", "tag") == F.col("__k"), "left_semi")
    met = some.join(need, ["doc_id", "tag"]).withColumn("o", F.explode(F.sequence(F.lit(0), F.col("s") - 1)))
    keys = ["cell", "i", "j"]
    units = met.select("cell", F.least("i", "o").alias("i"), F.greatest("i", "o").alias("j"), "v", "c", "text")

    def links(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for g in runs(pieces(batches, "text"), keys):
            yield _batch(_links(g["v"], g["c"], [shingles(t, words) for t in g["text"]]))

    return units.repartition(*keys).sortWithinPartitions(*keys).mapInArrow(forgetting(links), _PAIR).distinct()


def _sieve(keys: DataFrame, doc_id: str = "doc_id", tag: str = "tag") -> DataFrame | None:
    """Hashes of the keys, if they are few enough to be broadcast."""
    hashes = keys.select(F.xxhash64(doc_id, tag).alias("__k")).distinct()
    return F.broadcast(hashes) if hashes.count() <= SIEVE else None


def _verified(pairs: DataFrame, sets: DataFrame, docs: DataFrame, words: int, fan: int) -> DataFrame:
    """The pairs whose sets are similar."""
    key = sets.select("v", "doc_id", "tag")
    stars = pairs.groupBy("a").agg(F.ceil(F.count(F.lit(1)) / F.lit(fan)).cast("int").alias("s"))
    middle = stars.join(key, stars["a"] == key["v"]).select("doc_id", "tag", "a", F.explode(F.sequence(F.lit(0), F.col("s") - 1)).alias("part"), F.lit(None).cast("long").alias("b"))
    others = pairs.join(stars, "a").join(key, F.col("b") == F.col("v")).select("doc_id", "tag", "a", F.pmod(F.xxhash64("b"), "s").cast("int").alias("part"), "b")
    need = cut(middle.unionByName(others))
    sieve = _sieve(need)
    some = docs if sieve is None else docs.join(sieve, F.xxhash64("doc_id", "tag") == F.col("__k"), "left_semi")
    texts = some.join(need, ["doc_id", "tag"]).select("a", "part", "b", "text")

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = np.empty(0, np.uint64)
        for batch in pieces(batches, "text"):
            good = []
            for a, b, t in zip(*(batch[c].to_pylist() for c in ("a", "b", "text"))):
                if b is None:
                    held = shingles(t, words)
                elif similar(held, shingles(t, words)):
                    good.append((a, b))
            yield _batch(good)

    return texts.repartition("a", "part").sortWithinPartitions("a", "part", F.col("b").asc_nulls_first()).mapInArrow(forgetting(rows), _PAIR).distinct()


def groups(docs: DataFrame, words: int = 5, block: int = 4096, fan: int = 1000, small: int = 32, sample: int = 4096, deal: int = 1 << 17, id_col: str = "doc_id", text_col: str = "text") -> tuple[DataFrame, DataFrame]:
    """``[doc_id, tag, th, rows]`` of every different text that has an id (a hash of it, a digest of its set, how many rows it
    is), and ``[th, c]``, the group of each set."""
    named = docs.where(F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(F.col(text_col)).alias("tag"), F.col(text_col).alias("text"))
    signed = cut(_signed(named, words, _frequent(named, words, sample)))
    told = cut(signed.groupBy("doc_id", "tag", "th").agg(F.count(F.lit(1)).alias("rows")))
    one = cut(told.groupBy("th").agg(F.min(F.struct("doc_id", "tag")).alias("d")).select("th", "d.doc_id", "d.tag").withColumn("v", F.monotonically_increasing_id()))
    lead = signed.join(one.select("v", "doc_id", "tag"), ["doc_id", "tag"])
    sets = cut(lead.select("v", "n", "sketch", "doc_id", "tag").dropDuplicates(["v"]))
    # One shuffle serves the least member of a bucket and its rows.
    entries = lead.select("v", F.explode("lead").alias("h")).repartition("h")
    shared = entries.groupBy("h").agg(F.min("v").alias("lo"), F.max("v").alias("hi"), F.count(F.lit(1)).alias("size")).where("lo < hi").drop("hi")
    rows = cut(entries.join(shared, "h").select("h", "size", "lo", "v"))
    stars = cut(rows.where("v > lo").select(F.col("lo").alias("a"), F.col("v").alias("b")).distinct())
    good = cut(_verified(cut(_possible(stars, sets)), sets, named, words, fan))
    comp = cut(connected_components(good, small=ONE_TASK).select(F.col("id").alias("v"), "component"))
    found = rows.select("h", "size", "v").join(comp, "v", "left").select("h", "size", "v", F.coalesce("component", "v").alias("c"))
    mixed = found.groupBy("h").agg(F.min("c").alias("lo"), F.max("c").alias("hi")).where("lo < hi").select("h")
    few, many = _rest(cut(found.join(mixed, "h")), sets, stars, small, block)
    links = good.unionByName(_verified(cut(few), sets, named, words, fan))
    if (forest := cut(many)).count():
        links = links.unionByName(_in_cells(forest, comp, sets, named, words, deal))
    comp = connected_components(links, small=ONE_TASK)
    named_sets = one.join(comp, one["v"] == comp["id"], "left").select("th", F.coalesce("component", "v").alias("c"))
    return told, named_sets


def keep_one(docs: DataFrame, words: int = 5, block: int = 4096) -> DataFrame:
    """The document with the smallest id of each group; repeated rows of it shrink to one, null ids stay."""
    own = docs.columns
    told, sets = groups(docs, words, block)
    lead = told.join(sets, "th").groupBy("c").agg(F.min(F.struct("doc_id", "tag", "rows")).alias("d"))
    lead = cut(lead.select(F.col("d.doc_id").alias("doc_id"), F.col("d.tag").alias("tag"), (F.col("d.rows") > 1).alias("many")))
    # Texts that go, or that are there more than once, meet the exact join; the others pass.
    odd = told.select("doc_id", "tag").join(lead.where(~F.col("many")), ["doc_id", "tag"], "left_anti")
    sieve = _sieve(odd)
    tagged = docs.where("doc_id is not null").withColumn("__hash", F.xxhash64("text"))
    hit = F.xxhash64(F.col("doc_id").cast("long"), "__hash") == F.col("__k")
    some = tagged if sieve is None else tagged.join(sieve, hit, "left_semi")
    some = some.join(lead.toDF("__lead", "__tag", "__many"), (F.col("doc_id") == F.col("__lead")) & (F.col("__hash") == F.col("__tag")))
    kept = [some.where(~F.col("__many")), some.where("__many").dropDuplicates(["doc_id", "__hash"]), docs.where("doc_id is null")]
    if sieve is not None:
        kept.append(tagged.join(sieve, hit, "left_anti"))
    out = kept[0].select(*own)
    for x in kept[1:]:
        out = out.unionByName(x.select(*own))
    return out
