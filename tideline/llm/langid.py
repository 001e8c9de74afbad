"""Language identification by hyperdimensional profiles.

Each letter has a random vector of +1 and -1 of ``dim`` places, made from its code point alone. An n-gram's vector binds
its letters: each letter's vector is rotated by its place in the n-gram and they are multiplied. A document's vector bundles
(sums) those of all its n-grams, a language's prototype those of all its training documents. The language is the one
whose prototype has the largest cosine with the document; equal cosines go to the smaller name.

Letters are what Unicode calls alphabetic, in lower case; every run of anything else is one gap, which is a letter too.
Training adds up prototypes within each task and sends one vector a language and task, whatever the number of rows. The
model on the driver is languages times ``dim`` numbers; over ``max_languages`` it refuses.

Nulls, empties, repeats: a text that is null or has no letter is ``und`` with score 0, as is every text where nothing
was learned. Rows with a null id count as not held out by the query, and train if the condition given says so. Repeated
rows each come back and each train. Only the named columns are read.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tideline.llm.common import MEMORIES, forgetting, pieces

UNKNOWN = "und"
_GAP = 1


@lru_cache(maxsize=1)
def _letters() -> np.ndarray:
    """Code point of the lower-case letter for each code point; 1 for anything that isn't one."""
    out = np.full(0x110000, _GAP, dtype=np.int64)
    for c in range(0x110000):
        if (x := chr(c)).isalpha():
            low = x.lower()
            out[c] = ord(low) if len(low) == 1 else c
    return out


def letter_runs(text: str, gram: int = 3, block: int = 1 << 17) -> Iterator[np.ndarray]:
    """A text as code points of letters, with one gap before, between and after its words, in blocks of about ``block``.

    A block begins with the last ``gram - 1`` codes of the one before, so every n-gram stands in exactly one block.
    """
    held = np.array([_GAP], np.int64)
    for at in range(0, len(text), block):
        code = _letters()[np.frombuffer(text[at : at + block].encode("utf-32-le", "replace"), dtype="<u4")]
        code = np.r_[held, code, _GAP] if at + block >= len(text) else np.r_[held, code]
        code = code[np.r_[True, (code[1:] != _GAP) | (code[:-1] != _GAP)]]
        yield code
        held = code[max(0, len(code) - gram + 1) :]


class Space:
    """The random space: letters to vectors, n-grams to vectors, both remembered up to a bound (and what one call asks for)."""

    def __init__(self, dim: int, gram: int, seed: int, limit: int = 20_000):
        self.dim, self.gram, self.seed, self.limit = dim, gram, seed, limit
        self.letters: dict[int, np.ndarray] = {}
        self.keys = np.empty(0, np.int64)
        self.grams = np.empty((0, dim), np.int8)

    def letter(self, c: int) -> np.ndarray:
        if c not in self.letters:
            if len(self.letters) > 2 * self.limit:
                self.letters.clear()
            self.letters[c] = np.random.default_rng([self.seed, c]).choice(np.array([-1, 1], np.int8), self.dim)
        return self.letters[c]

    def _bind(self, keys: np.ndarray) -> np.ndarray:
        """The vectors of n-grams: their letters' vectors, each rotated by its place, multiplied."""
        out = np.ones((len(keys), self.dim), np.int8)
        for place in range(self.gram):
            code, at = np.unique(keys >> (21 * (self.gram - 1 - place)) & 0x1FFFFF, return_inverse=True)
            out *= np.roll(np.stack([self.letter(c) for c in code.tolist()]), place, axis=1)[at]
        return out

    def rows(self, keys: np.ndarray) -> np.ndarray:
        """Places of n-grams (sorted, distinct keys) in ``grams``."""
        at = np.searchsorted(self.keys, keys)
        known = (at < len(self.keys)) & (self.keys[np.minimum(at, len(self.keys) - 1)] == keys) if len(self.keys) else np.zeros(len(keys), bool)
        if not known.all():
            old = (self.keys, self.grams) if len(self.keys) < self.limit else (self.keys[:0], self.grams[:0])
            new = np.setdiff1d(keys, old[0], assume_unique=True)
            allk = np.r_[old[0], new]
            order = np.argsort(allk, kind="stable")
            self.keys, self.grams = allk[order], np.concatenate([old[1], self._bind(new)])[order]
            at = np.searchsorted(self.keys, keys)
        return at

    def _grams(self, text: str) -> Iterator[np.ndarray]:
        """The n-grams of a text, block by block; a text of fewer letters than an n-gram is one, filled up with gaps."""
        any_, last = False, np.empty(0, np.int64)
        for code in letter_runs(text, self.gram):
            last = code
            n = len(code) - self.gram + 1
            if n > 0 and (any_ or len(code) > 2 or (code != _GAP).any()):
                k = np.zeros(n, np.int64)
                for p in range(self.gram):
                    k = (k << 21) | code[p : n + p]
                any_ = True
                yield k
        if not any_ and (last != _GAP).any():
            k = 0
            for c in [*last.tolist(), *[_GAP] * self.gram][: self.gram]:
                k = (k << 21) | c
            yield np.array([k], np.int64)

    def bundles(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """The vectors of texts, and which of them have a letter. Memory is the remembered n-grams and one block of codes."""
        out, has = np.zeros((len(texts), self.dim), np.float32), np.zeros(len(texts), bool)
        keys: list[np.ndarray] = []
        owner: list[np.ndarray] = []
        held = 0
        for i, t in enumerate(texts):
            for k in self._grams(t or ""):
                has[i] = True
                keys.append(k)
                owner.append(np.full(len(k), i))
                held += len(k)
                if held > 1 << 18:
                    self._bundle(np.concatenate(keys), np.concatenate(owner), out)
                    keys, owner, held = [], [], 0
        if keys:
            self._bundle(np.concatenate(keys), np.concatenate(owner), out)
        return out, has

    def _bundle(self, keys: np.ndarray, owner: np.ndarray, out: np.ndarray, block: int = 2048) -> None:
        """Adds n-grams to their documents' vectors, ``block`` distinct ones at a time. Sums of whole numbers, exact below 2^24 n-grams a text, so the order doesn't matter."""
        distinct, at = np.unique(keys, return_inverse=True)
        pair, count = np.unique(at * len(out) + owner, return_counts=True)
        gram, doc = pair // len(out), pair % len(out)
        cuts = np.searchsorted(gram, np.arange(0, len(distinct) + block, block))
        for n, (s, e) in enumerate(zip(cuts[:-1], cuts[1:])):
            where = self.rows(distinct[n * block : (n + 1) * block])
            vec = self.grams[where].astype(np.float32)
            order = np.argsort(doc[s:e], kind="stable") + s
            d, g, c = doc[order], gram[order] - n * block, count[order].astype(np.float32)
            ends = np.r_[0, np.flatnonzero(np.diff(d)) + 1, len(d)]
            for x, y in zip(ends[:-1], ends[1:]):
                out[d[x]] += c[x:y] @ vec[g[x:y]]


@lru_cache(maxsize=2)
def space(dim: int, gram: int, seed: int) -> Space:
    return Space(dim, gram, seed)


MEMORIES["space"] = space.cache_clear


def train(docs: DataFrame, text_col: str = "text", lang_col: str = "lang", dim: int = 1024, gram: int = 3, seed: int = 7, max_languages: int = 1000) -> dict[str, np.ndarray]:
    """Prototype of each non-null language of ``docs``: the sum of its documents' vectors, each of length one."""

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[str, np.ndarray] = {}
        for b in pieces(batches, "text", 1 << 19):
            vec, has = space(dim, gram, seed).bundles(b["text"].to_pylist())
            size = np.linalg.norm(vec, axis=1)
            langs = np.array(b["lang"].to_pylist(), dtype=object)
            for lang in set(langs[has].tolist()):
                own = (langs == lang) & has & (size > 0)
                sums[lang] = sums.get(lang, 0) + (vec[own] / size[own, None]).sum(0, dtype=np.float64)
        if sums:
            # Rounded, so that the order in which tasks end can't move a later sum of doubles.
            flat = [np.rint(v * 2**20).astype(np.int64) for v in sums.values()]
            yield pa.record_batch([pa.array(list(sums)), pa.array(flat, pa.list_(pa.int64()))], names=["lang", "v"])

    rows = docs.select(F.col(text_col).alias("text"), F.col(lang_col).alias("lang")).where("lang is not null and text is not null")
    parts = rows.mapInArrow(forgetting(add), "lang string, v array<long>").select("lang", F.posexplode("v").alias("k", "x")).groupBy("lang", "k").agg(F.sum("x").alias("x"))
    found = parts.groupBy("lang").agg(F.array_sort(F.collect_list(F.struct("k", "x"))).alias("v")).select("lang", F.col("v.x").alias("v")).limit(max_languages + 1).collect()
    if len(found) > max_languages:
        raise ValueError(f"more than {max_languages} languages")
    return {r["lang"]: np.array(r["v"], np.float64) / 2**20 for r in sorted(found, key=lambda r: r["lang"])}


def predict(docs: DataFrame, model: dict[str, np.ndarray], text_col: str = "text", dim: int = 1024, gram: int = 3, seed: int = 7) -> DataFrame:
    """``docs`` with ``lang_pred`` and ``score`` (the cosine, at least 0); columns of these names are replaced."""
    names = [n for n, v in model.items() if np.linalg.norm(v) > 0]
    proto = np.array([model[n] / np.linalg.norm(model[n]) for n in names]).reshape(len(names), dim)
    base = docs.drop("lang_pred", "score")
    kept = [c for c in base.columns if c != text_col]
    fields = base.select(*kept, text_col).schema
    schema = fields.add("lang_pred", "string").add("score", "double")

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in pieces(batches, text_col, 1 << 19):
            vec, has = space(dim, gram, seed).bundles(b[text_col].to_pylist())
            pred, score = [UNKNOWN] * b.num_rows, np.zeros(b.num_rows)
            if names:
                size = np.linalg.norm(vec.astype(np.float64), axis=1)
                cos = vec @ proto.T / np.where(size > 0, size, 1)[:, None]
                best = cos.argmax(1)
                score = np.clip(np.where(has, cos[np.arange(len(best)), best], 0), 0, 1)
                pred = [names[k] if h else UNKNOWN for k, h in zip(best.tolist(), has.tolist())]
            yield pa.record_batch([*b.columns, pa.array(pred, pa.string()), pa.array(score)], names=[*b.schema.names, "lang_pred", "score"])

    return base.select(*kept, text_col).mapInArrow(forgetting(rows), schema)


def held_out(id_col: str = "doc_id", folds: int = 5) -> Column:
    """Whether a document's fold is the first: CRC-32 of its id as text, modulo ``folds``."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % folds == 0, F.lit(False))


def identify(docs: DataFrame, train_on: Column | None = None, **params) -> DataFrame:
    """``docs`` with ``lang_pred`` and ``score``, learned from its own rows that ``train_on`` picks (all, if None)."""
    model = train(docs if train_on is None else docs.where(train_on), **params)
    return predict(docs, model, **params)
