"""Approximate set cover on the ordered engine, and sequential greedy cover as its yardstick."""

from __future__ import annotations

import heapq
import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tideline.operators.engine import Metrics, run_ordered
from tideline.plans.rules import EdgeRule, OrderedProgram, PrioritySpec
from tideline.plans.schedule import Schedule
from tideline.sources import packed
from tideline.sources.graphs import Graph, ranked
from tideline.sources.tables import cut, saved

#: Pairs of set and element that one task may hold: 64 MB as they come, some 300 MB with their indexes. More are dealt with by rounds of jobs.
AT_ONCE = 4_000_000
#: Pairs that lie in files, both ways, for one task that reads what it needs of them: 16 bytes each.
FILED = 400_000_000


class System:
    """A system ``[set_id, elem_id]`` that was read once: its pairs, each once, and where there are many, files of them both ways."""

    def __init__(self, system: DataFrame):
        self.spark = system.sparkSession
        self.rows = cut(packed.pack(system.select(F.col("set_id").alias("src"), F.col("elem_id").alias("dst"), F.lit(0).cast("long").alias("weight")), True))
        self.all_pairs = packed.unpack(self.rows).select(F.col("src").alias("set_id"), F.col("dst").alias("elem_id"))
        self.pairs = self.all_pairs.where("set_id is not null and elem_id is not null")
        self.count = self.rows.agg(F.sum("edges")).first()[0] or 0
        self._files: tuple | None = None

    @staticmethod
    def of(system: DataFrame | System) -> System:
        return system if isinstance(system, System) else System(system)

    def files(self) -> tuple[packed.Numbered, packed.Numbered] | None:
        """Elements by set and sets by element, if both can be numbered."""
        if self._files is None:
            back = cut(packed.pack(packed.unpack(self.rows).select(F.col("dst").alias("src"), F.col("src").alias("dst"), "weight")))
            size = self.rows.agg(F.sum(F.octet_length("n") / 8), F.sum("gaps")).first()
            far = back.agg(F.sum(F.octet_length("n") / 8)).first()[0] or 0
            self._files = ()
            if not size[1] and max(size[0] or 0, far) <= packed.HELD:
                ends = [np.sort(packed.sources(r).select("id").toArrow()["id"].to_numpy()) for r in (self.rows, back)]
                both = packed.numbered(self.spark, self.rows, ends[1]), packed.numbered(self.spark, back, ends[0])
                self._files = both if all(both) else ()
        return self._files or None


@dataclass
class Cover:
    chosen: DataFrame  # set_id, gain, round, bucket
    metrics: Metrics

    @property
    def rounds(self) -> int:
        return self.metrics.rounds

    @property
    def buckets(self) -> int:
        return self.metrics.buckets


class _Election:
    """What a round does with the sets of its bucket; the hook of the engine's program.

    A round takes the sets of ``width`` buckets, and only these are counted anew: a count can only have fallen since, so a set that is elsewhere
    can't be worth more than its bucket. The best bucket among the new counts is the true best one unless it lies below those taken;
    then everything moves and the next round goes on there. Sets that belong to it compete, each of their uncovered elements going to the one of the smallest rank (an arithmetic hash of
    set, round and seed). A set that wins at least a (1 - accept) part of what the bucket promises is chosen. The set of the
    smallest rank wins all its elements, so a round with sets that belong here chooses one.

    Buckets are fused like those of paths: while the sets of a round have at most ``at_once`` uncovered elements together, one task holds
    all elections among them, one after the other, until the best bucket lies below those taken.
    """

    def __init__(self, pairs: DataFrame, eps: float, accept: float, seed: int, cost: DataFrame | None, width: int, at_once: int = AT_ONCE, files: tuple | None = None):
        self.files, self.open = files, None
        self.width, self.at_once, self.number = width, at_once, 0
        self.pairs, self.eps, self.accept, self.seed, self.cost = pairs, eps, accept, seed, cost
        self.covered: list[DataFrame] = []
        self.chosen: list[DataFrame] = []

    def bucket(self) -> Column:
        """floor(log base 1+eps of uncovered elements per cost)."""
        return F.floor(F.log(F.col("n") / F.col("cost")) / F.log(F.lit(1 + self.eps)) + 1e-9)

    def worth(self, pairs: DataFrame) -> DataFrame:
        return self.valued(pairs.groupBy("set_id").agg(F.count(F.lit(1)).alias("n")))

    def valued(self, n: DataFrame) -> DataFrame:
        n = n.join(self.cost, "set_id") if self.cost is not None else n.withColumn("cost", F.lit(1).cast("long"))
        return n.withColumn("b", self.bucket())

    def _gone(self) -> DataFrame:
        out = self.covered[0]
        for x in self.covered[1:]:
            out = out.unionByName(x)
        return out

    def __call__(self, popped: DataFrame, cur: int, number: int) -> DataFrame:
        if self.files:
            return self._reached(popped, cur)
        live = popped.select(F.col("id").alias("set_id")).join(self.pairs, "set_id")
        live = saved(live.join(self._gone(), "elem_id", "left_anti").select("set_id", "elem_id") if self.covered else live.select("set_id", "elem_id"))
        if live.count() <= self.at_once:
            return self._fused(popped, live, cur)
        worth = self.worth(live)
        top = worth.agg(F.max("b")).first()[0]
        self.number += 1
        new = self._elect(live, worth, top, self.number) if top is not None and top > cur - self.width else worth.limit(0)
        told = popped.select("id").join(worth.select(F.col("set_id").alias("id"), F.col("b").alias("new")), "id", "left")
        told = told.join(new.select(F.col("set_id").alias("id"), F.lit(True).alias("won")), "id", "left")
        return told.select("id", F.least("new", F.lit(cur)).cast("long").alias("new"), (F.col("new").isNotNull() & F.col("won").isNull()).alias("keep"))

    def _elect(self, live: DataFrame, worth: DataFrame, top: int, number: int) -> DataFrame:
        """The sets that are chosen from bucket ``top``; their elements count as covered from here on."""
        rank = (F.col("set_id") * 7919 + F.lit((number * 104729 + self.seed * 15485863) % 1_000_003)) * 31 % 1_000_003
        here = worth.where(F.col("b") == top).select("set_id", "cost", rank.alias("rank"))
        won = live.join(here, "set_id").groupBy("elem_id").agg(F.min(F.struct("rank", "set_id", "cost")).alias("w"))
        won = won.groupBy(F.col("w.set_id").alias("set_id"), F.col("w.cost").alias("cost")).agg(F.count(F.lit(1)).alias("gain"))
        new = saved(won.where(F.col("gain") >= (1 - self.accept) * (1 + self.eps) ** top * F.col("cost") - 1e-9).select("set_id", "gain"))
        self._take(live, new.select("set_id", "gain", F.lit(number).alias("round"), F.lit(top).cast("long").alias("bucket")))
        return new

    def _take(self, live: DataFrame, new: DataFrame) -> None:
        self.chosen.append(new)
        self.covered.append(saved(live.join(new.select("set_id"), "set_id", "left_semi").select("elem_id").distinct()))
        if len(self.covered) > 8:
            # Elements that are covered leave the table of pairs from time to time, not in every round.
            self.pairs, self.covered = saved(self.pairs.join(self._gone(), "elem_id", "left_anti").select("set_id", "elem_id")), []

    def _reached(self, popped: DataFrame, cur: int) -> DataFrame:
        """All elections of the window in one task, over files; which elements are left goes from window to window as a file, too."""
        rows = popped.select(F.col("id").alias("set_id"))
        rows = rows.join(self.cost, "set_id") if self.cost is not None else rows.withColumn("cost", F.lit(1))
        step = _filed_elections(*self.files, self.eps, self.accept, self.seed, cur - self.width, self.number, self.open)
        out = saved(rows.select("set_id", F.col("cost").cast("double").alias("cost")).repartition(1).mapInArrow(step, f"{_ELECTED}, open string"))
        told = out.agg(F.max("round"), F.max("open")).first()
        self.number, self.open = told[0] or self.number, told[1] or self.open
        self.chosen.append(out.where("gain is not null").select("set_id", "gain", "round", "bucket"))
        return self._told(popped, out.where("gain is null and set_id is not null"), cur)

    def _told(self, popped: DataFrame, left: DataFrame, cur: int) -> DataFrame:
        told = popped.select("id").join(left.select(F.col("set_id").alias("id"), F.col("bucket").alias("new")), "id", "left")
        return told.select("id", F.least("new", F.lit(cur)).cast("long").alias("new"), F.col("new").isNotNull().alias("keep"))

    def _fused(self, popped: DataFrame, live: DataFrame, cur: int) -> DataFrame:
        rows = live.join(self.cost, "set_id") if self.cost is not None else live.withColumn("cost", F.lit(1))
        rows = rows.select("set_id", "elem_id", F.col("cost").cast("double").alias("cost"))
        step = _elections(self.eps, self.accept, self.seed, cur - self.width, self.number)
        out = saved(rows.groupBy().applyInArrow(step, _ELECTED))
        new = out.where("gain is not null").select("set_id", "gain", "round", "bucket")
        most = new.agg(F.max("round")).first()[0]
        if most is not None:
            self.number = most
            self._take(live, new)
        return self._told(popped, out.where("gain is null"), cur)


#: A chosen set with its gain, its election and its bucket; or a set that is left (``gain`` is null) with the bucket that it has now.
_ELECTED = "set_id long, gain long, round int, bucket long"


def _elections(eps: float, accept: float, seed: int, low: int, number: int):
    """All elections among some sets, down to bucket ``low``; the same rules as those of :class:`_Election`."""

    def step(t: pa.Table) -> pa.Table:
        ids, first, s = np.unique(t["set_id"].to_numpy(), return_index=True, return_inverse=True)
        cost = t["cost"].to_numpy()[first]
        elems, e = np.unique(t["elem_id"].to_numpy(), return_inverse=True)
        rows, at = [], number
        while True:
            n = np.bincount(s, minlength=len(ids))
            b = np.full(len(ids), np.iinfo(np.int64).min)
            left = np.flatnonzero(n)
            b[left] = np.floor(np.log(n[left] / cost[left]) / np.log(1 + eps) + 1e-9).astype("i8")
            if not len(left) or (top := int(b.max())) <= low:
                break
            at += 1
            here = np.flatnonzero(b == top)
            rank = (ids[here] % 1_000_003 * 7919 + (at * 104729 + seed * 15485863) % 1_000_003) * 31 % 1_000_003
            place = np.full(len(ids), len(ids))
            place[here[np.lexsort((ids[here], rank))]] = np.arange(len(here))
            meets = place[s] < len(ids)
            ps, pe = s[meets], e[meets]
            best = np.full(len(elems), len(ids))
            np.minimum.at(best, pe, place[ps])
            gain = np.bincount(ps[best[pe] == place[ps]], minlength=len(ids))
            won = np.zeros(len(ids), bool)
            won[here] = gain[here] >= (1 - accept) * (1 + eps) ** top * cost[here] - 1e-9
            rows.append((ids[won], gain[won], at, top))
            gone = np.zeros(len(elems), bool)
            gone[e[won[s]]] = True
            stay = ~gone[e]
            s, e = s[stay], e[stay]
        sizes = [len(r[0]) for r in rows]
        per = lambda i: np.repeat([r[i] for r in rows], sizes) if rows else np.empty(0, "i8")
        cat = lambda i: np.concatenate([r[i] for r in rows]) if rows else np.empty(0, "i8")
        null = lambda kind: pa.nulls(len(left), kind)
        return pa.table({
            "set_id": pa.array(np.r_[cat(0), ids[left]], pa.int64()), "gain": pa.concat_arrays([pa.array(cat(1), pa.int64()), null(pa.int64())]),
            "round": pa.concat_arrays([pa.array(per(2).astype("i4"), pa.int32()), null(pa.int32())]), "bucket": pa.array(np.r_[per(3), b[left]], pa.int64()),
        })

    return step


def _filed_elections(by_set: packed.Numbered, by_elem: packed.Numbered, eps: float, accept: float, seed: int, low: int, number: int, open_at: str | None):
    """As :func:`_elections`, over files: an election reads the elements of the sets that compete, and counts fall with the elements that go."""

    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = [b for b in batches if b.num_rows]
        if not got:
            return
        t = pa.Table.from_batches(got)
        ids, sets, elems = by_set.ids(), by_set.open(False), by_elem.open(False)
        mine = np.searchsorted(ids, t["set_id"].to_numpy())
        cost = np.ones(len(ids))
        cost[mine] = t["cost"].to_numpy()
        open_ = np.load(open_at) if open_at else np.ones(by_elem.count, bool)
        n, at = np.zeros(len(ids), "i8"), number
        for place, e, _ in sets.out(mine):
            n[mine] += np.bincount(place[open_[e]], minlength=len(mine))
        while True:
            left = mine[n[mine] > 0]
            b = np.floor(np.log(n[left] / cost[left]) / np.log(1 + eps) + 1e-9).astype("i8")
            if not len(left) or (top := int(b.max())) <= low:
                break
            at += 1
            here = left[b == top]
            rank = (ids[here] % 1_000_003 * 7919 + (at * 104729 + seed * 15485863) % 1_000_003) * 31 % 1_000_003
            here = here[np.lexsort((ids[here], rank))]
            best = np.full(len(open_), len(here))
            for place, e, _ in sets.out(here):
                stays = open_[e]
                np.minimum.at(best, e[stays], place[stays])
            gain = np.bincount(best, minlength=len(here) + 1)[:-1]
            won = gain >= (1 - accept) * (1 + eps) ** top * cost[here] - 1e-9
            yield _elected(ids[here[won]], gain[won], at, np.full(int(won.sum()), top))
            gone = np.zeros(len(open_), bool)
            for _, e, _ in sets.out(here[won]):
                gone[e] = True
            gone &= open_
            open_ &= ~gone
            for _, s, _ in elems.out(np.flatnonzero(gone)):
                np.subtract.at(n, s, 1)
        path = f"{by_elem.base}-open-{uuid.uuid4().hex}.npy"
        np.save(path, open_)
        yield _elected(ids[left], None, None, b)
        yield pa.record_batch([*[pa.nulls(1, k) for k in (pa.int64(), pa.int64(), pa.int32(), pa.int64())], pa.array([path])], names=["set_id", "gain", "round", "bucket", "open"])

    return step


def _elected(ids: np.ndarray, gain: np.ndarray | None, at: int | None, bucket: np.ndarray) -> pa.RecordBatch:
    n = len(ids)
    gains = pa.nulls(n, pa.int64()) if gain is None else pa.array(gain, pa.int64())
    rounds = pa.nulls(n, pa.int32()) if at is None else pa.array(np.full(n, at, "i4"))
    return pa.record_batch([pa.array(ids, pa.int64()), gains, rounds, pa.array(bucket, pa.int64()), pa.nulls(n, pa.string())], names=["set_id", "gain", "round", "bucket", "open"])


def set_cover(system: DataFrame | System, eps: float = 0.1, accept: float = 0.1, seed: int = 1, costs: DataFrame | None = None, width: int = 16, at_once: int = AT_ONCE) -> Cover:
    """Sets that together hold every element of ``[set_id, elem_id]``: buckets of value per cost, the highest first.

    A set without a row in ``costs`` (``[set_id, cost]``, positive) can't be chosen.
    """
    system = System.of(system)
    spark, pairs = system.spark, system.pairs
    files = system.files() if at_once < system.count <= FILED else None
    hook = _Election(pairs, eps, accept, seed, costs.select("set_id", "cost") if costs is not None else None, width, at_once, files)
    n = packed.sources(system.rows).toDF("set_id", "n") if files else pairs.groupBy("set_id").agg(F.count(F.lit(1)).alias("n"))
    first = cut(hook.valued(n).select(F.col("set_id").alias("id"), F.col("b").cast("long").alias("value")))
    program = OrderedProgram("set_cover", PrioritySpec("high", False), EdgeRule("hook"), "set_cover", (hook,))
    sets = Graph(spark.createDataFrame([], "src long, dst long, weight long"), first.select("id"))
    res = run_ordered(program, sets, Schedule(width=width), extra=first)
    out = spark.createDataFrame([], "set_id long, gain long, round int, bucket long")
    for x in hook.chosen:
        out = out.unionByName(x)
    return Cover(cut(out), res.metrics)


def greedy(system: DataFrame | System, at_once: int = AT_ONCE, filed: int = FILED) -> DataFrame:
    """``[step, set_id, gain]``: one best set a step, the smallest id on ties.

    A set that is the best one (most uncovered elements, then the smallest id) of every uncovered element that it has is picked with what it is worth now:
    only a better set that shares an element could change that, and none can become better. So all such sets are taken at once
    until at most ``at_once`` pairs of a set and an uncovered element are left, which one task works off step by step. Worth never
    rises from step to step and ids rise among equals, so the steps are the ranks of the picks by both. Up to ``filed`` pairs lie in files
    instead, and a task reads the pairs that a step touches.
    """
    system = System.of(system)
    spark, pairs, count = system.spark, system.pairs, system.count
    files = system.files() if at_once < count <= filed else None
    picks = spark.createDataFrame([], "set_id long, gain long")
    if files:
        picks = saved(spark.range(0, 1, 1, 1).mapInArrow(_filed_steps(*files), "set_id long, gain long"))
        return _stepped(picks)
    while count > at_once:
        n = pairs.groupBy("set_id").agg(F.count(F.lit(1)).alias("n"))
        worth = pairs.join(n, "set_id").select("elem_id", "set_id", F.struct("n", (-F.col("set_id")).alias("id")).alias("w"))
        best = worth.groupBy("elem_id").agg(F.max("w").alias("best"))
        new = worth.join(best, "elem_id").groupBy("set_id").agg(F.min(F.col("w") == F.col("best")).alias("all"), F.max("w.n").alias("gain")).where("all")
        new = saved(new.select("set_id", "gain"))
        picks = picks.unionByName(new)
        gone = pairs.join(new.select("set_id"), "set_id", "left_semi").select("elem_id").distinct()
        pairs = saved(pairs.join(gone, "elem_id", "left_anti").select("set_id", "elem_id"))
        count = pairs.count()
    picks = picks.unionByName(pairs.groupBy().applyInArrow(_steps, "set_id long, gain long"))
    return _stepped(picks)


def _stepped(picks: DataFrame) -> DataFrame:
    return ranked(picks, [F.desc("gain"), "set_id"]).select((F.col("rank") + 1).cast("int").alias("step"), "set_id", "gain")


def _steps(t: pa.Table) -> pa.Table:
    """The picks of sequential greedy cover among the pairs of one task."""
    ids, s = np.unique(t["set_id"].to_numpy(), return_inverse=True)
    elems, e = np.unique(t["elem_id"].to_numpy(), return_inverse=True)
    by_set, by_elem = e[np.argsort(s, kind="stable")], s[np.argsort(e, kind="stable")]
    n = np.bincount(s, minlength=len(ids))
    sets, holds = np.r_[0, np.cumsum(n)], np.r_[0, np.cumsum(np.bincount(e, minlength=len(elems)))]
    open_ = np.ones(len(elems), bool)
    heap = [(-int(x), i) for i, x in enumerate(n)]
    heapq.heapify(heap)
    found, gains = [], []
    while heap:
        told, i = heap[0]
        if not n[i]:
            heapq.heappop(heap)
        elif -told != n[i]:
            heapq.heapreplace(heap, (-int(n[i]), i))
        else:
            found.append(i)
            gains.append(-told)
            new = by_set[sets[i] : sets[i + 1]]
            new = new[open_[new]]
            open_[new] = False
            deg = holds[new + 1] - holds[new]
            ends = np.cumsum(deg)
            np.subtract.at(n, by_elem[np.repeat(holds[new] - (ends - deg), deg) + np.arange(ends[-1])], 1)
    return pa.table({"set_id": pa.array(ids[found] if found else [], pa.int64()), "gain": pa.array(gains, pa.int64())})


def _filed_steps(by_set: packed.Numbered, by_elem: packed.Numbered):
    """As :func:`_steps`, over files."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if not sum(b.num_rows for b in batches):
            return
        ids, sets, elems = by_set.ids(), by_set.open(False), by_elem.open(False)
        n, open_ = sets.deg.copy(), np.ones(by_elem.count, bool)
        heap = [(-int(x), i) for i, x in enumerate(n)]
        heapq.heapify(heap)
        found, gains = [], []
        while heap:
            told, i = heap[0]
            if not n[i]:
                heapq.heappop(heap)
            elif -told != n[i]:
                heapq.heapreplace(heap, (-int(n[i]), i))
            else:
                found.append(i)
                gains.append(-told)
                new = np.concatenate([e for _, e, _ in sets.out(np.array([i]))])
                new = new[open_[new]]
                open_[new] = False
                for _, s, _ in elems.out(new):
                    np.subtract.at(n, s, 1)
        yield pa.record_batch([pa.array(ids[found] if found else [], pa.int64()), pa.array(gains, pa.int64())], names=["set_id", "gain"])

    return work


def verdict(system: DataFrame, cover: DataFrame) -> DataFrame:
    """One row: elements, how many stay uncovered, and chosen sets that gained nothing."""
    elems = system.select("elem_id").distinct()
    held = system.join(cover.select("set_id").distinct(), "set_id", "left_semi").select("elem_id").distinct()
    a = elems.agg(F.count(F.lit(1)).alias("n_elements"))
    b = elems.join(held, "elem_id", "left_anti").agg(F.count(F.lit(1)).alias("uncovered"))
    c = cover.agg(F.count(F.when(F.col("gain") < 1, 1)).alias("empty_picks"))
    return a.join(F.broadcast(b)).join(F.broadcast(c))
