"""The ordered loop: take the next bucket, send its updates along edges, re-bucket, until nothing is active.

The driver holds no rows. State is a DataFrame with one row a vertex,

    id, value (null: never reached), h (added to the value to give the priority), active, settled_at (bucket of the last pop)

hash-partitioned by id like the edges, so a round has one exchange, that of the messages, reduced before it. A round is one job:
its counters ride along as an Observation and the new state goes to the shared folder with ``checkpoint``. Vertices that are
final may be moved out of the state (``open_buckets``), so a round costs what is still open. What two rounds back was written is deleted.

A program with hooks is run round by round like the others: its hooks get the bucket and say what becomes of each of its vertices.

Where the edges are packed in files (``sources/packed.py``) plain pushed rounds are worked off in one task that reads no more of them than
the frontiers' (``operators/reach.py``); what follows is for all others.

Eager runs cut the graph into blocks. A block's bins live in one Arrow group: improvements of own vertices apply at once, those of
others leave as messages. With fusion the block goes on with its current bucket while that is small enough.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from dataclasses import asdict, dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from tideline.operators import reach
from tideline.plans.rules import OrderedProgram, constant_sum
from tideline.plans.schedule import Schedule, validate
from tideline.sources.graphs import Graph
from tideline.sources.tables import Store, cut, saved, shared_dir

#: Frontiers up to this many rows (of three longs) may be broadcast: 24 MB at most.
BROADCAST_ROWS = 1_000_000
#: Partitions over which ``balance=salted`` deals a hub's edges.
SALTS = 8


@dataclass
class Metrics:
    """What a run cost. ``rounds`` are global barriers; ``inner_rounds`` happened inside blocks or chained plans; ``shuffles`` are the
    exchanges that rounds plan (of messages, of frontiers or of blocks); ``released`` counts folders given back. ``work``, in ``row``, is the
    number of rows that the algorithm itself handled: vertices taken, edges relaxed, priorities moved."""

    rounds: int = 0
    inner_rounds: int = 0
    buckets: int = 0
    revisits: int = 0
    relaxations: int = 0
    inserts: int = 0
    visited: int = 0
    violations: int = 0
    jobs: int = 0
    pulls: int = 0
    released: int = 0
    shuffles: int = 0
    seconds: float = 0.0
    order: list = field(default_factory=list)

    def row(self) -> dict:
        out = {k: v for k, v in asdict(self).items() if k != "order"}
        return out | {"work": self.visited + self.relaxations + self.inserts}


@dataclass
class RoundView:
    """What a stop condition may look at: the bucket that would be next, its least priority, the watched vertex's value."""

    bucket: int
    least: int
    watched: int | None
    metrics: Metrics


@dataclass
class OrderedResult:
    state: DataFrame
    metrics: Metrics

    def values(self, name: str = "value") -> DataFrame:
        """``[id, name]`` of the vertices that have a value."""
        return self.state.where("value is not null").select("id", F.col("value").alias(name))

    def save(self, path: str) -> None:
        """State and metrics as parquet below ``path``."""
        self.state.write.parquet(f"{path}/state")
        self.state.sparkSession.createDataFrame([self.metrics.row()]).write.parquet(f"{path}/metrics")


@contextmanager
def steady(spark: SparkSession, parts: int) -> Iterator[None]:
    """Inside the loop: one fixed number of partitions and no re-planning, so that partitionings match from round to round."""
    want = {"spark.sql.adaptive.enabled": "false", "spark.sql.shuffle.partitions": str(parts)}
    had = {k: spark.conf.get(k) for k in want}
    try:
        for k, v in want.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in had.items():
            spark.conf.set(k, v)


def _callback(delta: int):
    @F.pandas_udf("long")
    def bucket(p):
        return p.map(lambda x: None if x is None or x != x else int(x) // delta)

    return bucket


class BucketQueue:
    """The queue's operators over a state DataFrame: ready bucket, emptiness, finality, current priority."""

    def __init__(self, program: OrderedProgram, schedule: Schedule, state: DataFrame):
        self.program, self.schedule, self.state = program, schedule, state
        self.cur: int | None = None

    def sql(self) -> str:
        """The bucket of a row as SQL text: whole plans are built from few strings, since a round is planned anew each time."""
        return bucket_sql(self.schedule.delta)

    def bucket(self) -> Column:
        if self.schedule.callback:
            return _callback(self.schedule.delta)(F.expr("value + h"))
        return F.expr(self.sql())

    @property
    def current(self) -> int | None:
        return self.cur

    def ready(self) -> Column:
        """Whether a row belongs to the buckets in hand."""
        low = self.program.spec.order == "low"
        edge = f"< {self.cur + self.schedule.width}" if low else f"> {self.cur - self.schedule.width}"
        if self.schedule.callback:
            return F.coalesce(F.col("active") & ((self.bucket() < self.cur + self.schedule.width) if low else (self.bucket() > self.cur - self.schedule.width)), F.lit(False))
        return F.expr(f"coalesce(active AND ({self.sql()} {edge}), false)")

    def pop(self) -> DataFrame:
        return self.state.where(self.ready())

    def done(self) -> bool:
        return self.cur is None

    def final(self, ids: DataFrame) -> DataFrame:
        """``[id, final]`` for the ids given: their bucket lies before the one in hand, or nothing is left."""
        b = self.bucket()
        passed = F.lit(True) if self.cur is None else (b < self.cur if self.program.spec.order == "low" else b > self.cur)
        s = self.state.select("id", F.coalesce(passed & ~F.col("active"), F.lit(False)).alias("final"))
        return ids.select("id").join(s, "id", "left").select("id", F.coalesce("final", F.lit(False)).alias("final"))

    def is_final(self, v: int) -> bool:
        row = self.final(self.state.where(F.col("id") == v).select("id")).first()
        return bool(row and row["final"])

    def counters(self, watch: int | None) -> list[Column]:
        best = "min" if self.program.spec.order == "low" else "max"
        first = F.expr(f"{best}(CASE WHEN active THEN {self.sql()} END) AS next") if not self.schedule.callback else getattr(F, best)(F.when(F.col("active"), self.bucket())).alias("next")
        return [first, F.expr("count_if(active) AS n_active"), F.expr(f"max(CASE WHEN id = {watch if watch is not None else 'null'} THEN value END) AS watched")]


def bucket_sql(delta: int, value: str = "value + h") -> str:
    return f"({value})" if delta == 1 else f"(({value}) div {delta}L)"


def _div(p: Column, delta: int) -> Column:
    return p if delta == 1 else F.call_function("div", p, F.lit(delta).cast("long"))


def initial_state(program: OrderedProgram, graph: Graph, start: dict[int, int] | None, extra: DataFrame | None) -> DataFrame:
    """One row a vertex; ``extra`` ([id, h] or [id, value]) adds to priorities or gives first values."""
    verts = graph.all_vertices().select("id")
    if start:
        verts = verts.unionByName(graph.spark.createDataFrame([(v,) for v in start], "id long")).distinct()
    cols = extra.columns if extra is not None else []
    if extra is not None:
        verts = verts.join(extra, "id", "left")
    value = F.col("value") if "value" in cols else F.lit(None).cast("long")
    for v, x in (start or {}).items():
        value = F.when(F.col("id") == v, F.lit(x).cast("long")).otherwise(value)
    h = F.coalesce("h", F.lit(0)).cast("long") if "h" in cols else F.lit(0).cast("long")
    return verts.select("id", value.alias("value"), h.alias("h")).select("*", F.col("value").isNotNull().alias("active"), F.lit(None).cast("long").alias("settled_at"))


def messages(frontier: DataFrame, graph: Graph, program: OrderedProgram, schedule: Schedule, size: int, pull: bool) -> DataFrame:
    """``[dst, new, n]``: the reduced updates along the frontier's out-edges and how many they were."""
    rule, f = program.rule, frontier.selectExpr("id AS src", "value AS __v")
    small = size <= BROADCAST_ROWS // 50
    if pull:
        sent = graph.pulled().join(F.broadcast(f), "src")
    elif schedule.balance == "edge" and size <= BROADCAST_ROWS:
        # Partitions of equally many edges know nothing of the frontier's partitioning, so the frontier comes to them.
        sent = graph.balanced().join(F.broadcast(f), "src")
    elif schedule.balance == "salted" and small:
        sent = graph.salted(SALTS).join(F.broadcast(f), "src")
    elif schedule.balance == "salted":
        # A hub's edges lie in several partitions, and its frontier row goes to each; the edges stay where they are.
        f = f.withColumn("__s", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        sent = graph.salted(SALTS).join(f.hint("shuffle_hash"), ["src", "__s"])
    else:
        sent = graph.adjacent().join(F.broadcast(f) if small else f.hint("shuffle_hash"), "src").selectExpr("__v", "inline(arrays_zip(to, by)) AS (dst, weight)")
    if rule.kind == "add":
        const = constant_sum(rule)
        if const and schedule.update == "lazy_count":
            return sent.groupBy("dst").agg(F.expr("count(1) AS n")).selectExpr("dst", f"n * {const.delta} AS new", "n")
        amount = F.lit(rule.delta) if isinstance(rule.delta, int) else rule.delta(F.col("weight"))
        return sent.select("dst", amount.cast("long").alias("new")).groupBy("dst").agg(F.sum("new").alias("new"), F.count(F.lit(1)).alias("n"))
    best = "min" if rule.kind == "lower" else "max"
    return sent.select("dst", rule.new(F.col("__v"), F.col("weight")).alias("new")).groupBy("dst").agg(F.expr(f"cast({best}(new) AS long) AS new"), F.expr("count(1) AS n"))


def better(kind: str, new: Column, old: Column) -> Column:
    return F.coalesce(new.isNotNull() & (old.isNull() | ((new < old) if kind == "lower" else (new > old))), F.lit(False))


def lazy_round(q: BucketQueue, graph: Graph, size: int, pull: bool, bound: int | None) -> DataFrame:
    """The state after one round, with columns ``__n`` (messages), ``__changed`` and ``__popped`` for the counters."""
    rule, spec = q.program.rule, q.program.spec
    msgs = messages(q.pop(), graph, q.program, q.schedule, size, pull)
    return merge(q, msgs, bound)


def better_sql(kind: str, bound: int | None, old: str = "value") -> str:
    more = "" if bound is None else f" AND new + h < {bound}"
    return f"(new IS NOT NULL AND ({old} IS NULL OR new {'<' if kind == 'lower' else '>'} {old}){more})"


_ROW = ["id", "value", "h", "active", "settled_at"]


def side_by_side(q: BucketQueue, told: DataFrame, **columns: str) -> DataFrame:
    """Each row of the state with the ``told`` columns (name to type) of its id, null where there are none, and ``__popped``.

    Both lie by id already, so a union and an aggregate put them together without an exchange. A join would do the same, but its
    estimated size is a product, which over rounds grows to numbers with millions of digits.
    """
    own = q.state.withColumn("__popped", q.ready()).selectExpr(*_ROW, "__popped", *[f"CAST(null AS {t}) AS {c}" for c, t in columns.items()])
    other = told.selectExpr("id", "CAST(null AS long) AS value", "CAST(null AS long) AS h", "CAST(null AS boolean) AS active", "CAST(null AS long) AS settled_at", "CAST(null AS boolean) AS __popped", *columns)
    return own.union(other).groupBy("id").agg(*[F.expr(f"max({c}) AS {c}") for c in [*_ROW[1:], "__popped", *columns]]).where("h IS NOT NULL")


def merge(q: BucketQueue, msgs: DataFrame, bound: int | None) -> DataFrame:
    """Reduced messages into the state."""
    rule = q.program.rule
    s = side_by_side(q, msgs.withColumnRenamed("dst", "id"), new="long", n="long")
    settled = f"CASE WHEN __popped THEN {q.cur}L ELSE settled_at END AS settled_at"
    if rule.kind == "add":
        floor = {None: None, "current": q.cur}.get(rule.floor, rule.floor)
        moved = "value + new" if floor is None else f"greatest(value + new, {floor}L)"
        changed = "(active AND NOT __popped AND new IS NOT NULL" + (")" if floor is None else f" AND value <> {floor})")
        back = f"{changed} AND (new {'>' if rule.sign < 0 else '<'} 0 OR {bucket_sql(q.schedule.delta, f'({moved})')} {'<' if q.program.spec.order == 'low' else '>'} {q.cur})"
        return s.selectExpr("id", f"CASE WHEN {changed} THEN {moved} ELSE value END AS value", "h", "active AND NOT __popped AS active", settled, "coalesce(n, 0) AS __n", f"{changed} AS __changed", "__popped", f"coalesce({back}, false) AS __back")
    ch = better_sql(rule.kind, bound)
    # An accepted offer before the bucket in hand breaks the order: a negative weight, or an estimate that isn't consistent.
    back = f"{ch} AND {bucket_sql(q.schedule.delta, 'new + h')} {'<' if q.program.spec.order == 'low' else '>'} {q.cur}"
    return s.selectExpr("id", f"CASE WHEN {ch} THEN new ELSE value END AS value", "h", f"{ch} OR (active AND NOT __popped) AS active", settled, "coalesce(n, 0) AS __n", f"{ch} AS __changed", "__popped", f"coalesce({back}, false) AS __back")


def hooked_round(q: BucketQueue, number: int) -> DataFrame:
    """The state after the program's hooks have dealt with the bucket in hand."""
    popped = q.pop().select("id", "value")
    told = q.program.hooks[0](popped, q.cur, number)
    for hook in q.program.hooks[1:]:
        told = hook(told, q.cur, number)
    s = side_by_side(q, told.select("id", "new", "keep"), new="long", keep="boolean")
    stays = "(active AND (NOT __popped OR coalesce(keep, false)))"
    moved = "(__popped AND new IS NOT NULL AND NOT new <=> value)"
    back = f"{stays} AND {moved} AND {bucket_sql(q.schedule.delta, 'new + h')} {'<' if q.program.spec.order == 'low' else '>'} {q.cur}"
    return s.selectExpr("id", f"CASE WHEN {moved} THEN new ELSE value END AS value", "h", f"{stays} AS active", f"CASE WHEN __popped AND NOT coalesce(keep, false) THEN {q.cur}L ELSE settled_at END AS settled_at", "CAST(__popped AS long) AS __n", f"{moved} AS __changed", "__popped", f"coalesce({back}, false) AS __back")


def chained_hops(q: BucketQueue, graph: Graph, hops: int, bound: int | None) -> DataFrame:
    """Several hops of the bucket in one plan. A hop reads the state once: every row sends itself and, if it is in the bucket,
    an offer to each neighbour; one aggregate by id puts them together."""
    rule = q.program.rule
    best = F.min if rule.kind == "lower" else F.max
    s = q.state.select("*", F.lit(0).cast("long").alias("__n"), F.lit(False).alias("__changed"), F.lit(False).alias("__popped"), F.lit(False).alias("__back"))
    adj = graph.packed()
    for _ in range(hops):
        x = s.join(adj, "id", "left").withColumn("__go", q.ready())
        me = F.struct(F.col("id").alias("to"), F.col("value").alias("v"), F.lit(True).alias("own"))
        offers = F.transform("adj", lambda e: F.struct(e["dst"].alias("to"), rule.new(F.col("value"), e["weight"]).cast("long").alias("v"), F.lit(False).alias("own")))
        sent = F.concat(F.array(me), F.when(F.col("__go") & F.col("adj").isNotNull(), offers).otherwise(F.array().cast("array<struct<to:long,v:long,own:boolean>>")))
        y = x.select(F.explode(sent).alias("m"), "h", "active", "settled_at", "__go", "__n", "__changed", "__popped", "__back")
        own = lambda c: F.max(F.when(F.col("m.own"), F.col(c)))
        g = y.groupBy(F.col("m.to").alias("id")).agg(own("m.v").alias("old"), best(F.when(~F.col("m.own"), F.col("m.v"))).alias("new"), F.count(F.when(~F.col("m.own"), 1)).alias("got"), *[own(c).alias(c) for c in ("h", "active", "settled_at", "__go", "__n", "__changed", "__popped", "__back")])
        ch = better(rule.kind, F.col("new"), F.col("old"))
        ch = ch if bound is None else ch & (F.col("new") + F.col("h") < bound)
        s = g.where("h is not null").select("id", F.when(ch, F.col("new")).otherwise(F.col("old")).alias("value"), "h", (ch | (F.col("active") & ~F.col("__go"))).alias("active"), F.when(F.col("__go"), F.lit(q.cur).cast("long")).otherwise(F.col("settled_at")).alias("settled_at"), (F.col("__n") + F.col("got")).alias("__n"), (F.col("__changed") | ch).alias("__changed"), (F.col("__popped") | F.col("__go")).alias("__popped"), (F.col("__back") | (ch & F.coalesce(F.expr(f"{bucket_sql(q.schedule.delta, 'new + h')} {'<' if q.program.spec.order == 'low' else '>'} {q.cur}"), F.lit(False)))).alias("__back"))
    return s


_OUT = "kind int, block int, id long, value long, h long, active boolean, settled_at long, n long"


def block_step(program: OrderedProgram, schedule: Schedule, cur: int):
    """The work of one block in one round, as a cogroup function over its state rows and its out-edges."""
    rule, delta, add = program.rule, schedule.delta, program.rule.kind == "add"
    limit = schedule.fuse_limit if schedule.update == "eager_fused" else 0
    none = np.iinfo(np.int64).max

    def step(key: tuple, s: pa.Table, e: pa.Table) -> pa.Table:
        block = key[0].as_py()
        ids = s["id"].to_numpy()
        order = np.argsort(ids)
        ids = ids[order]
        value = s["value"].fill_null(none).to_numpy()[order].copy()
        h, active = s["h"].to_numpy()[order], s["active"].to_numpy()[order].copy()
        settled = s["settled_at"].fill_null(none).to_numpy()[order].copy()
        flat = lambda c, kind: np.frombuffer(b"".join(e[c].to_pylist()), kind)
        src = np.searchsorted(ids, flat("src", "i8"))
        by = np.argsort(src, kind="stable")
        dst, weight, to = flat("dst", "i8")[by], flat("weight", "i8")[by], flat("dst_block", "i4")[by]
        first = np.searchsorted(src[by], np.arange(len(ids) + 1))
        mine = to == block
        place = np.where(mine, np.searchsorted(ids, dst), -1)
        in_hand = lambda: active & (value != none) & ((value + np.where(value != none, h, 0)) // delta <= cur)
        frontier, rounds, relaxed, inserted, popped, back = np.flatnonzero(in_hand()), 0, 0, 0, 0, 0
        sent_to: list[np.ndarray] = []
        sent_at: list[np.ndarray] = []
        sent_v: list[np.ndarray] = []
        while len(frontier):
            rounds += 1
            popped += len(frontier)
            active[frontier] = False
            settled[frontier] = cur
            deg = first[frontier + 1] - first[frontier]
            ends = np.cumsum(deg)
            edge = np.repeat(first[frontier] - (ends - deg), deg) + np.arange(ends[-1] if len(ends) else 0)
            new = np.full(len(edge), -1) if add else rule.new(np.repeat(value[frontier], deg), weight[edge])
            relaxed += len(edge)
            here = mine[edge]
            sent_to.append(to[edge][~here])
            sent_at.append(dst[edge][~here])
            sent_v.append(new[~here])
            p, v = place[edge][here], new[here]
            if add:
                # One decrement at a time, each an insertion of its own, down to the bucket in hand.
                before = value.copy()
                np.add.at(value, p[active[p]], -1)
                value[active] = np.where(before[active] > cur, np.maximum(value[active], cur), before[active])
                inserted += int((before - value).sum())
                frontier = np.empty(0, np.int64)
                break
            old = value.copy()
            np.minimum.at(value, p, v)
            inserted += int((v < old[p]).sum())
            moved = np.flatnonzero(value < old)
            back += int(((value[moved] + h[moved]) // delta < cur).sum())
            active[moved] = True
            frontier = moved[(value[moved] + h[moved]) // delta <= cur]
            if not 0 < len(frontier) <= limit:
                break
        cat = lambda parts, kind: np.concatenate(parts) if parts else np.empty(0, kind)
        tb, td, tv = cat(sent_to, np.int32), cat(sent_at, np.int64), cat(sent_v, np.int64)
        m, k = len(ids), len(td)
        null = lambda x: pa.array(x, pa.int64(), mask=x == none)
        kinds = np.r_[np.zeros(m, "i4"), np.ones(k, "i4"), np.arange(2, 7, dtype="i4")]
        counts = np.r_[np.zeros(m + k, "i8"), relaxed, inserted, popped, rounds, back]
        return pa.table({
            "kind": kinds, "block": np.r_[np.full(m, block, "i4"), tb, np.full(5, -1)].astype("i4"), "id": np.r_[ids, td, np.full(5, -1)],
            "value": pa.concat_arrays([null(value), pa.array(tv, pa.int64()), pa.nulls(5, pa.int64())]), "h": np.r_[h, np.zeros(k + 5, "i8")],
            "active": np.r_[active, np.zeros(k + 5, bool)], "settled_at": pa.concat_arrays([null(settled), pa.nulls(k + 5, pa.int64())]), "n": counts,
        })

    return step


def eager_round(q: BucketQueue, edges: DataFrame, active_blocks: list[int], parts: int, store: Store) -> tuple[DataFrame, DataFrame]:
    """The state after one round, and the counters by kind. ``state`` has a ``block`` column and is partitioned by it."""
    rule = q.program.rule
    here = F.col("block").isin(active_blocks)
    out = store.cut(q.state.where(here).groupBy("block").cogroup(edges.where(here).groupBy("block")).applyInArrow(block_step(q.program, q.schedule, q.cur), _OUT))
    rest = q.state.where(~here).select(F.lit(0).alias("kind"), "block", "id", "value", "h", "active", "settled_at")
    rows = out.where("kind < 2").drop("n").unionByName(rest).repartition(parts, "block")
    own = lambda c: F.max(F.when(F.col("kind") == 0, F.col(c)))
    got = (F.sum if rule.kind == "add" else F.min)(F.when(F.col("kind") == 1, F.col("value")))
    g = rows.groupBy("block", "id").agg(own("value").alias("old"), got.alias("new"), own("h").alias("h"), own("active").alias("act"), own("settled_at").alias("settled_at")).where("h is not null")
    if rule.kind == "add":
        ch = F.coalesce(F.col("act") & F.col("new").isNotNull() & (F.col("old") > q.cur), F.lit(False))
        new, act = F.greatest(F.col("old") + F.col("new"), F.lit(q.cur).cast("long")), F.col("act")
    else:
        ch = better("lower", F.col("new"), F.col("old"))
        new, act = F.col("new"), F.col("act") | ch
    state = g.select("block", "id", F.when(ch, new).otherwise(F.col("old")).alias("value"), "h", act.alias("active"), "settled_at", ch.alias("__changed"))
    return state, out.where("kind > 1").groupBy("kind").agg(F.sum("n").alias("n"), F.max("n").alias("most"))


def run_ordered(program: OrderedProgram, graph: Graph, schedule: Schedule | None = None, start: dict[int, int] | None = None, extra: DataFrame | None = None, stop: Callable[[RoundView], bool] | None = None, watch: int | None = None, prune: bool = False, max_rounds: int = 1_000_000) -> OrderedResult:
    """Runs a program to its end or to ``stop``; ``prune`` drops offers that can't beat the watched vertex's value."""
    schedule = schedule or Schedule()
    validate(program, schedule)
    shared_dir(graph.spark)
    began, m = time.monotonic(), Metrics()
    eager = schedule.update.startswith("eager")
    files = graph.numbered() if reach.fits(program, schedule) else None
    if files is not None:
        state = initial_state(program, graph, start, extra)
        if eager:
            owner = graph.owners(schedule.blocks or graph.block_count(), schedule.layout)
            state = state.join(owner, "id", "left").withColumn("block", F.coalesce("block", F.lit(0)))
        final = reach.rounds(state, files, program, schedule, m, RoundView, stop, watch, prune, max_rounds)
        m.seconds = time.monotonic() - began
        return OrderedResult(final, m)
    with steady(graph.spark, graph.P):
        state = initial_state(program, graph, start, extra)
        edges = None
        if eager:
            owner, edges = graph.packed_blocks(schedule.blocks or graph.block_count(), schedule.layout)
            state = state.join(owner, "id", "left").withColumn("block", F.coalesce("block", F.lit(0))).repartition(graph.P, "block")
        else:
            state = state.repartition(graph.P, "id")
        q, lake = BucketQueue(program, schedule, state), Store(graph.spark)
        view = _settle(q, m, watch, eager, lake)
        degrees = edges_total = None
        store = _Overflow(q, schedule) if schedule.open_buckets else None
        seen: set[int] = set()
        while not q.done() and m.rounds < max_rounds:
            if stop and stop(RoundView(q.cur, _least(q), view["watched"], m)):
                break
            m.rounds += 1
            m.order.append(q.cur)
            m.revisits += q.cur in seen
            seen.add(q.cur)
            bound = view["watched"] if prune else None
            if eager:
                blocks = sorted(view["blocks"] or [])
                new, counts = eager_round(q, edges, blocks, graph.P, lake)
                tally = {r["kind"]: r for r in counts.collect()}
                m.jobs += 2
                m.shuffles += 2
                m.relaxations += tally[2]["n"]
                m.inserts += tally[3]["n"]
                m.visited += tally[4]["n"]
                m.inner_rounds += max(0, tally[5]["most"] - 1)
                m.violations += tally[6]["n"]
                q.state = new
            else:
                pull = schedule.direction == "pull"
                if schedule.direction == "auto":
                    if degrees is None:
                        degrees = cut(graph.edges.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("d")).repartition(graph.P, "id"))
                        edges_total = degrees.agg(F.sum("d")).first()[0] or 0
                    out = q.pop().join(degrees, "id").agg(F.sum("d")).first()[0] or 0
                    m.jobs += 1
                    pull = out > schedule.auto_ratio * edges_total
                pull = pull and view["n_active"] <= BROADCAST_ROWS
                m.pulls += pull
                m.shuffles += schedule.plan_hops if schedule.plan_hops > 1 else int(not pull) + (schedule.balance == "salted" and not pull and view["n_active"] > BROADCAST_ROWS // 50)
                if program.hooks:
                    q.state = hooked_round(q, m.rounds)
                elif store:
                    q.state = store.round(q, graph, view["n_active"], pull, bound)
                elif schedule.plan_hops > 1:
                    q.state = chained_hops(q, graph, schedule.plan_hops, bound)
                    m.inner_rounds += schedule.plan_hops - 1
                else:
                    q.state = lazy_round(q, graph, view["n_active"], pull, bound)
            view = _settle(q, m, watch, eager, lake)
            if store and view["next"] is None:
                view = store.reopen(q, m, watch)
                lake.pin()
        m.buckets, m.released = len(seen), lake.released
        m.seconds = time.monotonic() - began
        final = q.state if store is None else store.all_rows(q)
        return OrderedResult(final, m)


def _least(q: BucketQueue) -> int:
    return q.cur * q.schedule.delta


def _settle(q: BucketQueue, m: Metrics, watch: int | None, eager: bool, lake: Store | None = None) -> dict:
    """Writes the new state, reads the round's counters, moves the queue to the next bucket, and gives back what lies behind it."""
    write = lake.cut if lake else cut
    has = set(q.state.columns)
    cols = q.counters(watch)
    for c, name in (("__n", "sent"), ("__changed", "moved"), ("__popped", "popped"), ("__back", "back")):
        cols.append(F.expr(f"sum(cast({c if c in has else 0} AS long)) AS {name}"))
    if eager:
        cols.append(F.collect_set(F.when(F.col("active"), F.col("block"))).alias("blocks"))
    if q.schedule.callback:  # a Python function can't stand in an Observation
        state = write(q.state)
        view = state.agg(*cols).first().asDict()
        m.jobs += 2
    else:
        seen = Observation()
        state = write(q.state.observe(seen, *cols))
        view = seen.get
        m.jobs += 1
    if lake:
        lake.keep(state)
    q.state = state.drop("__n", "__changed", "__popped", "__back")
    q.cur = view["next"]
    if eager and m.rounds and q.cur is not None:
        # only blocks with a vertex in the bucket in hand take part
        rows = q.state.where(q.ready()).select("block").distinct().collect()
        view["blocks"] = [r["block"] for r in rows]
        m.jobs += 1
    if eager:
        m.inserts += view["moved"] or 0
    else:
        m.relaxations += view["sent"] or 0
        m.inserts += view["moved"] or 0
        m.visited += view["popped"] or 0
        m.violations += view["back"] or 0
    return view


class _Overflow:
    """Only ``open_buckets`` buckets at hand: the rest of the state lies still in ``far``, later offers wait in a log.

    ``q.state`` holds the rows whose bucket is below the window's end. An offer below the end to a far row moves that row
    in; other offers are logged and reduced when the window moves on. Rows that were popped in earlier windows are final.
    """

    def __init__(self, q: BucketQueue, schedule: Schedule):
        self.n, self.end = schedule.open_buckets, None
        self.far: DataFrame | None = None
        self.log: list[DataFrame] = []
        self.done: list[DataFrame] = []
        self._open(q, q.state)

    def _sign(self, q: BucketQueue) -> bool:
        return q.program.spec.order == "low"

    def _inside(self, q: BucketQueue, bucket: Column) -> Column:
        return F.coalesce(bucket < self.end if self._sign(q) else bucket > self.end, F.lit(False))

    def _open(self, q: BucketQueue, rows: DataFrame) -> None:
        if q.cur is None:
            self.end, self.far = 0, rows.limit(0)
            return
        self.end = q.cur + self.n if self._sign(q) else q.cur - self.n
        inside = self._inside(q, q.bucket())
        self.far = cut(rows.where(~inside))
        q.state = cut(rows.where(inside))

    def round(self, q: BucketQueue, graph: Graph, size: int, pull: bool, bound: int | None) -> DataFrame:
        kind = q.program.rule.kind
        msgs = cut(messages(q.pop(), graph, q.program, q.schedule, size, pull))
        hit = self.far.select("id", F.col("value").alias("__old"), "h").join(msgs, F.col("id") == F.col("dst"))
        hit = hit.join(q.state.select("id"), "id", "left_anti").where(better(kind, F.col("new"), F.col("__old")))
        if bound is not None:
            hit = hit.where(F.col("new") + F.col("h") < bound)
        prio = _div(F.col("new") + F.col("h"), q.schedule.delta)
        self.log.append(saved(hit.where(~self._inside(q, prio)).select("id", "new")))
        near = merge(q, msgs, bound)
        moved = hit.where(self._inside(q, prio)).select("id", F.col("new").alias("value"), "h", F.lit(True).alias("active"), F.lit(None).cast("long").alias("settled_at"), F.col("n").alias("__n"), F.lit(True).alias("__changed"), F.lit(False).alias("__popped"), F.lit(False).alias("__back"))
        return near.unionByName(moved).repartition(graph.P, "id")

    def reopen(self, q: BucketQueue, m: Metrics, watch: int | None) -> dict:
        """The window is empty: settle it, reduce the log into the far rows, and open the next one."""
        best = F.min if q.program.rule.kind == "lower" else F.max
        self.done.append(q.state)
        far = self.far.join(q.state.select("id"), "id", "left_anti")
        if self.log:
            log = self.log[0]
            for x in self.log[1:]:
                log = log.unionByName(x)
            log = log.groupBy("id").agg(best("new").alias("new"))
            far = far.join(log, "id", "left")
            ch = better(q.program.rule.kind, F.col("new"), F.col("value"))
            far = far.select("id", F.when(ch, F.col("new")).otherwise(F.col("value")).alias("value"), "h", (F.col("active") | ch).alias("active"), "settled_at")
        self.log = []
        q.state = far
        view = _settle(q, m, watch, False)
        self._open(q, q.state)
        return view

    def all_rows(self, q: BucketQueue) -> DataFrame:
        out = q.state.select("id", "value", "h", "active", "settled_at")
        far = self.far.join(q.state.select("id"), "id", "left_anti") if self.far is not None else None
        for x in [*self.done, *([far] if far is not None else [])]:
            out = out.unionByName(x.select("id", "value", "h", "active", "settled_at"))
        return out
