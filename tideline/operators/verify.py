"""Certificates: one-row comparisons whose expected outcome is known whatever the data."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tideline.operators import kcore as K
from tideline.operators import paths as P
from tideline.operators import setcover as C
from tideline.plans.schedule import UNBOUNDED, Schedule
from tideline.sources.graphs import Graph


def mismatches(a: DataFrame, b: DataFrame, value: str) -> int:
    """Ids whose values differ or that only one side has."""
    x = a.select("id", F.col(value).alias("__a")).join(b.select("id", F.col(value).alias("__b")), "id", "full_outer")
    return x.where(~F.col("__a").eqNullSafe(F.col("__b"))).count()


def slack(graph: Graph, dist: DataFrame) -> int:
    """Edges over which a distance could still be lowered."""
    d = dist.select("id", "dist")
    return graph.edges.join(d.toDF("src", "ds"), "src").join(d.toDF("dst", "dd"), "dst", "left").where("dd is null or ds + weight < dd").count()


def _far(dist: DataFrame) -> tuple[int, int]:
    row = dist.agg(F.count(F.lit(1)), F.max("dist")).first()
    return row[0], row[1]


def fusion(graph: Graph, source: int, delta: int) -> DataFrame:
    """Distances with and without fusion agree, and fusion takes no more rounds."""
    plain = P.sssp(graph, source, Schedule(update="eager", delta=delta, fuse_limit=0))
    fused = P.sssp(graph, source, Schedule(update="eager_fused", delta=delta))
    bad = mismatches(plain.values("dist"), fused.values("dist"), "dist")
    return graph.spark.createDataFrame([(*_far(fused.values("dist")), bad, fused.metrics.rounds <= plain.metrics.rounds)], "reached long, farthest long, mismatches long, fewer_rounds boolean")


def update_modes(graph: Graph) -> DataFrame:
    """Counted, lazy and eager coreness agree; eager inserts at least as often as counted updates."""
    count, lazy, eager = (K.kcore(graph, Schedule(update=u, fuse_limit=0)) for u in ("lazy_count", "lazy", "eager"))
    bad = mismatches(K.coreness(count), K.coreness(lazy), "coreness") + mismatches(K.coreness(count), K.coreness(eager), "coreness")
    row = K.coreness(count).agg(F.count(F.lit(1)), F.max("coreness")).first()
    return graph.spark.createDataFrame([(*row, bad, count.metrics.inserts <= eager.metrics.inserts)], "vertices long, degeneracy long, mismatches long, counts_fewer_inserts boolean")


def update_modes_paths(graph: Graph, source: int, delta: int) -> DataFrame:
    """Lazy and eager distances agree; a lazy round moves a vertex once at the most, so it never moves more than it sends."""
    lazy, eager = P.sssp(graph, source, Schedule(delta=delta)), P.sssp(graph, source, Schedule(update="eager", delta=delta, fuse_limit=0))
    bad = mismatches(lazy.values("dist"), eager.values("dist"), "dist")
    return graph.spark.createDataFrame([(*_far(lazy.values("dist")), bad, lazy.metrics.inserts <= lazy.metrics.relaxations)], "reached long, farthest long, mismatches long, moves_within_sent boolean")


def delta_sweep(graph: Graph, source: int, deltas: list[int]) -> DataFrame:
    """A row for each width: distances agree with those of the widest, and wider buckets are no more buckets."""
    runs = {x: P.sssp(graph, source, Schedule(delta=x)) for x in deltas}
    last = runs[max(deltas)]
    rows, before = [], None
    for x, r in sorted(runs.items()):
        rows.append((x, *_far(r.values("dist")), mismatches(last.values("dist"), r.values("dist"), "dist"), before is None or r.metrics.buckets <= before))
        before = r.metrics.buckets
    return graph.spark.createDataFrame(rows, "delta long, reached long, farthest long, mismatches long, buckets_fall boolean")


def work(graph: Graph, source: int) -> DataFrame:
    """Relaxations with small buckets against one bucket, both worked off within one block."""
    a = P.sssp(graph, source, Schedule(update="eager_fused", delta=1024, blocks=1))
    b = P.sssp(graph, source, Schedule(update="eager_fused", delta=UNBOUNDED, blocks=1))
    return graph.spark.createDataFrame([(*_far(a.values("dist")), a.metrics.relaxations <= b.metrics.relaxations)], "reached long, farthest long, ordered_relaxes_less boolean")


def bucket_order(graph: Graph, source: int) -> DataFrame:
    res = P.sssp(graph, source, Schedule(delta=32))
    m = res.metrics
    rising = all(a <= b for a, b in zip(m.order, m.order[1:]))
    return graph.spark.createDataFrame([(*_far(res.values("dist")), rising, m.rounds >= m.buckets, m.violations)], "reached long, farthest long, monotone boolean, rounds_at_least_buckets boolean, violations long")


def cover_quality(system: DataFrame, eps: float, accept: float) -> DataFrame:
    """The cover against sequential greedy: the size bound with the harmonic number of the largest set, and slack for the buckets."""
    # Read once for the cover, the greedy steps and the verdict.
    held = C.System.of(system)
    system = held.all_pairs
    got = C.set_cover(held, eps, accept).chosen
    best = C.greedy(held).count()
    v = C.verdict(system, got).first()
    largest = system.groupBy("set_id").count().agg(F.max("count")).first()[0] or 1
    harmonic = sum(1 / i for i in range(1, largest + 1))
    ok = got.count() <= (1 + eps) / (1 - accept) * harmonic * best
    return system.sparkSession.createDataFrame([(v["n_elements"], v["uncovered"], best, bool(ok))], "n_elements long, uncovered long, greedy_sets long, within_bound boolean")


def cover_ratio(system: DataFrame, chosen: DataFrame) -> float:
    """Chosen sets over those of sequential greedy."""
    return chosen.count() / max(1, C.greedy(system).count())
