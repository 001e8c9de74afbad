"""Token counts of greedy longest-match word pieces in linear time, without building the pieces.

The vocabulary is a trie. Walking a word, a step that has no child is a failure: the longest match on the way to this
node, and those on what is left of it, are popped at once, and the walk goes on at the failure link's node, which
stands for the letters that remain. Each node knows how many tokens its failure pops, so each letter costs one step
forward and its share of pops; nothing is matched twice.

A word that can't be split into pieces of the vocabulary is one unknown token, as is one longer than ``max_chars``
(None: no such limit). Words are remembered by each worker up to a bound, as texts repeat them.

A null or empty text has no word and no token. Repeated rows and null ids each come back. An empty table gives an
empty result. All columns but clashing ones (``n_words``, ``n_tokens``, ``n_unknown``) are kept.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from tideline.llm.common import pieces


class Automaton:
    """Greedy longest match over a vocabulary whose first pieces begin with ``mark`` and whose later ones don't."""

    def __init__(self, vocabulary: Iterable[str], mark: str):
        self.mark = mark
        kids: list[dict[str, int]] = [{}]
        final = [False]
        for piece in vocabulary:
            node = 0
            for c in piece:
                if c not in kids[node]:
                    kids.append({})
                    final.append(False)
                    kids[node][c] = len(kids) - 1
                node = kids[node][c]
            final[node] = final[node] or node != 0
        self.kids, self.final = kids, final
        self.fail: list[int | None] = [None] * len(kids)
        self.pops = [0] * len(kids)
        level = [0]
        while level:
            level = [self._link(p, c, n) for p in level for c, n in kids[p].items()]

    def _link(self, parent: int, c: str, node: int) -> int:
        if self.final[node]:
            self.fail[node], self.pops[node] = 0, 1
            return node
        at, popped = self.fail[parent], self.pops[parent]
        while at is not None and c not in self.kids[at]:
            popped += self.pops[at]
            at = self.fail[at]
        if at is not None:
            self.fail[node], self.pops[node] = self.kids[at][c], popped
        return node

    def count(self, word: str) -> int | None:
        """Pieces of a word; None if it can't be split."""
        kids, fail, pops = self.kids, self.fail, self.pops
        node, total = 0, 0
        for c in self.mark + word:
            while c not in kids[node]:
                total += pops[node]
                nxt = fail[node]
                if nxt is None:
                    return None
                node = nxt
            node = kids[node][c]
        while node:
            total += pops[node]
            nxt = fail[node]
            if nxt is None:
                return None
            node = nxt
        return total


def greedy(word: str, vocabulary: set[str], mark: str) -> int | None:
    """The same by trying the longest piece first, for tests."""
    rest, n = mark + word, 0
    while rest:
        size = next((k for k in range(len(rest), 0, -1) if rest[:k] in vocabulary), 0)
        if not size:
            return None
        rest, n = rest[size:], n + 1
    return n


def pieces_of(model: str) -> tuple[list[str], str]:
    """The ordinary pieces of a sentencepiece model and the mark that begins a word."""
    from sentencepiece import SentencePieceProcessor

    sp = SentencePieceProcessor(model_file=model)
    plain = [sp.id_to_piece(i) for i in range(sp.get_piece_size()) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) or sp.is_unused(i))]
    return plain, "▁"


@lru_cache(maxsize=2)
def _automaton(model: str) -> tuple[Automaton, dict[str, int]]:
    return Automaton(*pieces_of(model)), {}


def counts(docs: DataFrame, model: str, text_col: str = "text", max_chars: int | None = None, memo: int = 500_000) -> DataFrame:
    """``docs`` with ``n_words``, ``n_tokens`` and ``n_unknown`` (words that are one unknown token)."""
    base = docs.drop("n_words", "n_tokens", "n_unknown")
    schema = T.StructType(list(base.schema.fields)).add("n_words", "long").add("n_tokens", "long").add("n_unknown", "long")

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        auto, known = _automaton(model)
        for b in pieces(batches, text_col):
            words = pc.split_pattern_regex(b[text_col].cast(pa.large_string()).fill_null(""), "[\\x20\\x09-\\x0D]+")
            coded = words.flatten().dictionary_encode()
            names = coded.dictionary.to_pylist()
            if len(known) > memo:
                known.clear()
            for w in names:
                if w not in known:
                    n = 0 if not w else None if max_chars and len(w) > max_chars else auto.count(w)
                    known[w] = -1 if n is None else n
            size = np.fromiter((known[w] for w in names), np.int64, len(names))[coded.indices.to_numpy(zero_copy_only=False)]
            real = np.fromiter((bool(w) for w in names), bool, len(names))[coded.indices.to_numpy(zero_copy_only=False)]
            at = np.r_[0, np.cumsum(words.value_lengths().to_numpy(zero_copy_only=False))]
            total = lambda x: np.diff(np.r_[0, np.cumsum(x, dtype=np.int64)][at])
            out = [total(real), total(np.abs(size)), total(size < 0)]
            yield pa.record_batch([*b.columns, *map(pa.array, out)], names=[*b.schema.names, "n_words", "n_tokens", "n_unknown"])

    return base.mapInArrow(rows, schema)
