"""Packing of tokenised documents into sequences by multiway differencing.

A document's ids (with an end id) are cut into full sequences and a rest; the rest is cut into pieces of at most
``piece`` ids. Each task gathers pieces until they fill ``windows`` sequences and splits them by the
Karmarkar-Karp differencing method: every piece starts as a partition of its own, and the two partitions with the largest
imbalance are merged again and again, the fullest window of one onto the emptiest of the other. If a window ends
above the capacity, the number of windows rises by one and the pieces are split anew. What a task has left at its end
is cut so that the last sequences' lengths are powers of two, which need no padding.

Work is per task and streams: nothing is shuffled, and memory is one slice of texts and one group of pieces. Sequence
numbers hold the task's partition and a counter, so reruns over the same input agree.

Nulls, empties, repeats: a null or empty text is just its end id. Repeated rows and null ids are packed like others. An
empty table gives an empty result.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tideline.llm.common import encoder, forgetting, pieces


def difference(sizes: list[int], k: int) -> list[list[int]]:
    """Positions of ``sizes`` in ``k`` groups of nearly equal sums."""
    left: list[int] = []
    right: list[int] = []
    n = len(sizes)

    def single(i: int) -> tuple[np.ndarray, np.ndarray]:
        sums, node = np.zeros(k, np.int64), np.full(k, -1, np.int64)
        sums[0], node[0] = sizes[i], i
        return sums, node

    heap: list[tuple[int, int, tuple | None]] = [(-s, i, None) for i, s in enumerate(sizes)]
    heapq.heapify(heap)
    count = n
    while len(heap) > 1:
        _, i, a = heapq.heappop(heap)
        _, j, b = heap[0]
        (sa, na), (sb, nb) = a or single(i), b or single(j)
        sb, nb = sb[::-1], nb[::-1]
        s = sa + sb
        node = np.where(na < 0, nb, na)
        both = np.flatnonzero((na >= 0) & (nb >= 0))
        node[both] = n + len(left) + np.arange(len(both))
        left += na[both].tolist()
        right += nb[both].tolist()
        order = np.argsort(-s, kind="stable")
        s, node = s[order], node[order]
        s -= s[-1]
        heapq.heapreplace(heap, (-int(s[0]), count, (s, node)))
        count += 1
    groups = []
    _, i, last = heap[0]
    for top in (last or single(i))[1].tolist():
        out, stack = [], [top]
        while stack:
            x = stack.pop()
            if x >= n:
                stack += (left[x - n], right[x - n])
            elif x >= 0:
                out.append(x)
        groups.append(sorted(out))
    return groups


def fill(sizes: list[int], capacity: int) -> list[list[int]]:
    """Groups of ``sizes`` of at most ``capacity``: the fewest windows that differencing can do, from the least possible."""
    if not sizes:
        return []
    k = max(1, -(-sum(sizes) // capacity))
    while True:
        groups = difference(sizes, k)
        if all(sum(sizes[i] for i in g) <= capacity for g in groups):
            return [g for g in groups if g]
        k += 1


class _Packer:
    """One task's pieces on their way into sequences."""

    def __init__(self, capacity: int, piece: int, windows: int, base: int):
        self.capacity, self.piece, self.room, self.next = capacity, piece, windows * capacity, base
        self.held: list[tuple] = []
        self.held_n = 0
        self.out: list[tuple] = []

    def _emit(self, group: list[tuple]) -> None:
        at = 0
        for doc, start, ids, total in group:
            self.out.append((doc, start, len(ids), ids.tobytes(), total, self.next, at))
            at += len(ids)
        self.next += 1

    def add(self, doc: int | None, ids: np.ndarray) -> None:
        n, full = len(ids), len(ids) // self.capacity * self.capacity
        for s in range(0, full, self.capacity):
            self._emit([(doc, s, ids[s : s + self.capacity], n)])
        for s in range(full, n, self.piece):
            part = ids[s : s + self.piece].copy()
            self.held.append((doc, s, part, n))
            self.held_n += len(part)
        if self.held_n >= self.room:
            self._split(self.held)
            self.held, self.held_n = [], 0

    def _split(self, parts: list[tuple]) -> None:
        for g in fill([len(p[2]) for p in parts], self.capacity) if parts else []:
            self._emit([parts[i] for i in g])

    def end(self) -> None:
        """The last pieces: what doesn't fill whole sequences goes into sequences whose lengths are powers of two."""
        extra, tail = self.held_n % self.capacity, []
        while extra:
            doc, start, ids, n = self.held.pop()
            take = min(extra, len(ids))
            tail.append((doc, start + len(ids) - take, ids[len(ids) - take :], n))
            if take < len(ids):
                self.held.append((doc, start, ids[: len(ids) - take], n))
            extra -= take
        self._split(self.held)
        rest = sum(len(p[2]) for p in tail)
        while rest:
            room = want = 1 << (rest.bit_length() - 1)
            group = []
            while want:
                doc, start, ids, n = tail.pop()
                group.append((doc, start, ids[:want], n))
                if len(ids) > want:
                    tail.append((doc, start + want, ids[want:], n))
                want -= len(group[-1][2])
            self._emit(group)
            rest -= room


SCHEMA = "doc_id long, start long, length long, ids binary, doc_tokens long, sequence_id long, offset long"
_TYPES = (pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.int64(), pa.int64(), pa.int64())


def pack(docs: DataFrame, vocabulary: str, end_id: int = 1, capacity: int = 2048, piece: int = 512, windows: int = 256, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row for each piece: its document, its place there, its ids (little-endian, 32 bits), its sequence and place there."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p = _Packer(capacity, piece, windows, TaskContext.get().partitionId() << 40)

        def drain() -> Iterator[pa.RecordBatch]:
            for at in range(0, len(p.out), 2000):
                yield pa.record_batch([pa.array(c, t) for c, t in zip(zip(*p.out[at : at + 2000]), _TYPES)], names=[x.split()[0] for x in SCHEMA.split(", ")])
            p.out = []

        for b in pieces(batches, "text", 1 << 20):
            flat, at = encoder(vocabulary).encode(b["text"])
            for doc, s, e in zip(b["doc_id"].to_pylist(), at[:-1].tolist(), at[1:].tolist()):
                p.add(doc, np.r_[flat[s:e], np.uint32(end_id)].astype("<u4"))
            yield from drain()
        p.end()
        yield from drain()

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(forgetting(rows), SCHEMA)
