"""What several operators share: words, the tokenizers of public vocabularies, Arrow helpers."""

from __future__ import annotations

import ctypes
import os
import re
from collections.abc import Callable, Iterable, Iterator
from functools import lru_cache
from itertools import chain, repeat

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Words are runs of anything but these bytes; ``bytes.split()`` splits at the same ones.
WORD_PATTERN = r"[^\x20\x09-\x0D]+"

#: The white space of the tokenizers' patterns. Python's own class also holds 1C to 1F, theirs doesn't.
_SPACE = r"\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
_CHUNK = re.compile(f"[{_SPACE}]*[^{_SPACE}]+|[{_SPACE}]+")
#: For RE2: two white characters in a row, or the mark that splits chunks.
_ODD = "[" + re.sub(r"\\[xu]([0-9a-f]+)", r"\\x{\1}", _SPACE) + "]{2}|\\x00"

_ENDED = r"([A-Za-z])([!-@\[-`{-~])"

_MARK = "!"

#: Chunks that are one word of Latin letters, after a blank or a line's end at the most: their letters stand alone under NFC, and the
#: lower case of each is a letter of its own. Both vocabularies take such a word as a whole.
_WORD = r"^[ \n]?[A-Za-z\x{c0}-\x{d6}\x{d8}-\x{f6}\x{f8}-\x{ff}]+$"

#: Distinct chunks over which a worker forgets those that it didn't use lately. A bound of memory, not of results.
MEMO_LIMIT = 300_000


#: What a worker remembers for each operator, by name: how to forget it.
MEMORIES: dict[str, Callable[[], None]] = {}


def forgetting(fn: Callable) -> Callable:
    """A function of batches whose worker forgets, at the task's end, what it remembered: workers that wait for their next task hold little."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from fn(batches)
        finally:
            forget()

    return run


def forget() -> None:
    for drop in MEMORIES.values():
        drop()
    # Free memory goes back to the machine, which the JVM and other workers share.
    pa.default_memory_pool().release_unused()
    if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):
        trim(0)


def _byte_letters() -> dict[int, str]:
    """The letter by which byte-level vocabularies write each byte: printable ones as they are, the others in order from U+0100 on."""
    shown = {*range(33, 127), *range(161, 173), *range(174, 256)}
    hidden = [b for b in range(256) if b not in shown]
    return {b: chr(b) if b in shown else chr(256 + hidden.index(b)) for b in range(256)}


_BYTES = _byte_letters()


@lru_cache(maxsize=4)
def _tokenizer(path: str):
    # A task has one core; threads of the library would only cost memory.
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


class ChunkEncoder:
    """Token ids of whole texts, the same as ``encode(text, add_special_tokens=False)`` of the library.

    Both vocabularies split a text before every run of white space that follows something else, and after a letter that
    an ASCII digit or sign follows, whatever stands around it. So a text's ids are the ids of its chunks (white space, then the rest) in their order, and a
    chunk that was seen before needs no second encoding. Arrow splits the texts, numbers the distinct chunks and looks them up.

    A new chunk that is a plain word goes straight to the vocabulary's merges, without the library's steps around them; that this is the
    same is tried out on some words when the encoder is made. Other chunks go through the library.

    What is remembered is flat: the chunks' places by chunk, their ids as one pool. Over ``limit`` chunks, those that no
    text used since the last time go; what is forgotten is encoded anew.
    """

    def __init__(self, path: str, limit: int = MEMO_LIMIT):
        self.tok, self.limit = _tokenizer(path), limit
        added = [re.escape(t.content) for t in self.tok.get_added_tokens_decoder().values()]
        self.odd = "|".join([_ODD, *added])
        ids = lambda t: self.tok.encode(t, add_special_tokens=False).ids
        self.folds = "Lowercase()" in repr(self.tok.normalizer) and not ids(" \n\t") and ids(" Ab") == ids("ab") == ids("\nAB")
        # A sign with an id of its own, which only this sign has: many chunks around it are one text for the library.
        mark = ids(_MARK)
        self.mark = mark[0] if self.folds and len(mark) == 1 and ids(f"a {_MARK} b") == [*ids("a"), *mark, *ids("b")] else None
        self.known: dict[str, int] = {}
        self.pool, self.size, self.used = np.empty(0, "<u4"), np.empty(0, "i8"), np.empty(0, bool)
        self.break_ids = ids("\n")
        tries = ["a", "the", "Words", "ISN", "qxzvjk", "caf\u00e9", "\u00c9T\u00c9", "\u00fcber\u00df", "\u00fe\u00d0\u00d8\u00f8", "a" * 40]
        self.plain = all(self._words([c])[0] == ids(c) for t in tries for c in (t, " " + t, "\n" + t))

    def _keys(self, chunks: pa.Array) -> pa.Array:
        """Chunks with the same key have the same ids: some vocabularies drop white space and case. Other letters than
        ASCII stay as they are, since their case depends on more than the letter."""
        if not self.folds:
            return chunks
        return pc.if_else(pc.string_is_ascii(chunks), pc.ascii_lower(pc.ascii_trim(chunks, characters=" \t\n\r")), chunks)

    def _chunks(self, texts: pa.Array) -> pa.ListArray:
        odd = pc.match_substring_regex(texts, self.odd)
        marked = pc.replace_substring(pc.replace_substring(texts, " ", "\0 "), "\n", "\0\n")
        # No token of either vocabulary holds a letter and then an ASCII character that isn't one.
        split = pc.split_pattern(pc.replace_substring_regex(marked, _ENDED, "\\1\0\\2"), "\0")
        if not pc.any(odd).as_py():
            return split
        own = iter([_CHUNK.findall(t) for t in texts.filter(odd).to_pylist()])
        return pa.array([next(own) if o else c for o, c in zip(odd.to_pylist(), split.to_pylist())], split.type)

    def _words(self, chunks: list[str]) -> tuple[list[int], list[int]]:
        """The ids of chunks that are plain words, one after the other, and where each chunk's end."""
        merged, out, ends = self.tok.model.tokenize, [], []
        for c in chunks:
            if c[0] == "\n":
                out += self.break_ids
                c = c[1:]
            if self.folds:
                c = c.lstrip(" ").lower()
            if not c.isascii():
                c = c.encode().decode("latin-1").translate(_BYTES)
            elif c[0] == " ":
                c = _BYTES[32] + c[1:]
            out += [t.id for t in merged(c)]
            ends.append(len(out))
        return out, ends

    def _ids(self, chunks: list[str]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """The ids of some chunks after the others, and how many each of these has."""
        for at in range(0, len(chunks), 500):
            some = chunks[at : at + 500]
            if self.mark is not None and not any(_MARK in c for c in some):
                flat = np.array(self.tok.encode(f" {_MARK} ".join(some), add_special_tokens=False).ids, "<u4")
                cuts = np.flatnonzero(flat == self.mark)
                if len(cuts) == len(some) - 1:
                    yield flat[flat != self.mark], np.diff(np.r_[-1, cuts, len(flat)]) - 1
                    continue
            ids = [e.ids for e in self.tok.encode_batch_fast(some, add_special_tokens=False)]
            size = np.fromiter(map(len, ids), "i8", len(ids))
            yield np.fromiter(chain.from_iterable(ids), "<u4", int(size.sum())), size

    def _places(self, keys: pa.Array) -> np.ndarray:
        """Where each key stands among the known chunks; unknown ones are encoded and become known."""
        names, known = keys.to_pylist(), self.known
        at = np.fromiter(map(known.get, names, repeat(-1)), "i8", len(names))
        if len(missing := np.flatnonzero(at < 0)):
            new = keys.take(pa.array(missing)).unique()
            word = pc.match_substring_regex(new, _WORD) if self.plain else pa.array(np.zeros(len(new), bool))
            # Chunks with the mark come last, so that they spoil few of the texts that hold many.
            other = new.filter(pc.invert(word))
            marked = pc.match_substring(other, _MARK)
            words, others = new.filter(word).to_pylist(), [*other.filter(pc.invert(marked)).to_pylist(), *other.filter(marked).to_pylist()]
            own, ends = self._words(words)
            ids, counts = [np.array(own, "<u4")], [np.diff(np.array([0, *ends], "i8"))]
            for flat, n in self._ids(others):
                ids.append(flat)
                counts.append(n)
            known.update(zip(chain(words, others), range(len(known), len(known) + len(new))))
            self.pool = np.concatenate([self.pool, *ids])
            self.size = np.concatenate([self.size, *counts])
            self.used = np.r_[self.used, np.zeros(len(new), bool)]
            at[missing] = [known[names[i]] for i in missing.tolist()]
        self.used[at] = True
        return at

    def _forget(self) -> None:
        keep = self.used
        self.known = dict(zip((c for c, k in zip(self.known, keep.tolist()) if k), range(int(keep.sum()))))
        self.pool, self.size = self.pool[np.repeat(keep, self.size)], self.size[keep]
        self.used = np.zeros(len(self.known), bool)

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """All ids as one uint32 array, and where each text's ids begin in it (with the end); null is an empty text."""
        if len(self.known) > self.limit:
            self._forget()
        texts = texts.cast(pa.large_string()).fill_null("")
        chunks = self._chunks(texts)
        coded = chunks.flatten().dictionary_encode()
        place = self._places(self._keys(coded.dictionary))
        at = place[coded.indices.to_numpy(zero_copy_only=False)]
        first = np.cumsum(self.size) - self.size
        n = self.size[at]
        ends = np.cumsum(n)
        flat = self.pool[np.repeat(first[at] - (ends - n), n) + np.arange(ends[-1] if len(ends) else 0)]
        counts = chunks.value_lengths().to_numpy(zero_copy_only=False).astype("i8")
        return flat, np.r_[0, ends][np.r_[0, np.cumsum(counts)]]


@lru_cache(maxsize=2)
def encoder(path: str) -> ChunkEncoder:
    """The task's encoder for a vocabulary."""
    return ChunkEncoder(path)


MEMORIES["encoder"] = encoder.cache_clear


def pieces(batches: Iterable[pa.RecordBatch], text: str, max_bytes: int = 1 << 20) -> Iterator[pa.RecordBatch]:
    """The rows of the batches again, in slices that hold about ``max_bytes`` of text or a single row."""
    for b in batches:
        if not b.num_rows:
            continue
        size = np.cumsum(pc.binary_length(b[text]).fill_null(0).to_numpy(zero_copy_only=False).astype("i8") + 8)
        at = 0
        while at < b.num_rows:
            upto = max(at + 1, int(np.searchsorted(size, (size[at - 1] if at else 0) + max_bytes, "right")))
            yield b.slice(at, upto - at)
            at = upto


def runs(batches: Iterable[pa.RecordBatch], keys: list[str]) -> Iterator[dict[str, list]]:
    """Groups of rows with equal keys, as columns of Python values, from batches that are sorted by them."""
    held: dict[str, list] | None = None
    held_key = None
    for b in batches:
        if not b.num_rows:
            continue
        cols = {n: b[n].to_pylist() for n in b.schema.names}
        ks = list(zip(*(cols[k] for k in keys)))
        cuts = [0] + [i for i in range(1, len(ks)) if ks[i] != ks[i - 1]] + [len(ks)]
        for s, e in zip(cuts, cuts[1:]):
            part = {n: v[s:e] for n, v in cols.items()}
            if held is not None and held_key == ks[s]:
                for n, v in part.items():
                    held[n].extend(v)
            else:
                if held is not None:
                    yield held
                held, held_key = part, ks[s]
    if held is not None:
        yield held


class Forest:
    """Union-find over positions 0..n-1 that keeps a bit mask of each tree's members."""

    def __init__(self, n: int):
        self.up, self.mask = list(range(n)), [1 << i for i in range(n)]

    def find(self, i: int) -> int:
        while self.up[i] != i:
            self.up[i] = self.up[self.up[i]]
            i = self.up[i]
        return i

    def join(self, i: int, j: int) -> None:
        i, j = self.find(i), self.find(j)
        if i != j:
            self.up[j], self.mask[i], self.mask[j] = i, self.mask[i] | self.mask[j], 0

    def roots(self) -> list[int]:
        return [self.find(i) for i in range(len(self.up))]


def word_count(text: Column) -> Column:
    """Number of words of a text; null has none."""
    return F.coalesce(F.regexp_count(text, F.lit(r"[^ \t\n\x0B\f\r]+")), F.lit(0)).cast("long")


def arrow_map(df: DataFrame, fn: Callable, schema: str) -> DataFrame:
    """``mapInArrow`` under a name that says what it is for: rows that only Python can compute."""
    return df.mapInArrow(fn, schema)
