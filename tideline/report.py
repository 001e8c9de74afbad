"""Tables of measures: schedules side by side, fusion on and off, eager and lazy, line counts, speedups."""

from __future__ import annotations

import time
from collections.abc import Callable
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tideline.operators.engine import OrderedResult
from tideline.plans.schedule import Schedule
from tideline.sources.graphs import Graph

FIELDS = "run string, rounds long, inner_rounds long, buckets long, revisits long, relaxations long, inserts long, visited long, violations long, jobs long, shuffles long, pulls long, released long, work long, seconds double"


def table_of(spark: SparkSession, runs: dict[str, OrderedResult]) -> DataFrame:
    """A row of metrics for each named run."""
    cols = [c.split()[0] for c in FIELDS.split(", ")][1:]
    return spark.createDataFrame([(n, *[r.metrics.row()[c] for c in cols]) for n, r in runs.items()], FIELDS)


def compare(spark: SparkSession, run: Callable[[Schedule], OrderedResult], schedules: dict[str, Schedule]) -> DataFrame:
    return table_of(spark, {n: run(s) for n, s in schedules.items()})


def fusion_table(spark: SparkSession, run: Callable[[Schedule], OrderedResult], delta: int) -> DataFrame:
    """Rounds and seconds with and without fusion of rounds of one bucket."""
    return compare(spark, run, {"with fusion": Schedule(update="eager_fused", delta=delta), "without": Schedule(update="eager", delta=delta, fuse_limit=0)})


def update_table(spark: SparkSession, run: Callable[[Schedule], OrderedResult], modes: list[str], delta: int = 1) -> DataFrame:
    return compare(spark, run, {m: Schedule(update=m, delta=delta) for m in modes})


def seconds(run: Callable[[], object]) -> float:
    """Wall clock of a call."""
    began = time.monotonic()
    run()
    return time.monotonic() - began


def redundant(graph: Graph, result: OrderedResult) -> float:
    """The share of relaxations beyond one for each edge out of a vertex that was reached."""
    once = graph.edges.join(result.values().select(F.col("id").alias("src")), "src", "left_semi").count()
    return max(0.0, 1 - once / max(1, result.metrics.relaxations))


def mean_over(run: Callable[[int], OrderedResult], starts: list[int]) -> float:
    """Mean seconds over starts."""
    return sum(run(s).metrics.seconds for s in starts) / len(starts)


def speedup(table: DataFrame, base: str) -> DataFrame:
    """``[run, seconds, times_base]``: seconds of ``base`` over those of each run."""
    b = table.where(F.col("run") == base).select(F.col("seconds").alias("b"))
    return table.join(F.broadcast(b)).select("run", "seconds", (F.col("b") / F.col("seconds")).alias("times_base"))


def loc() -> dict[str, int]:
    """Lines of code (no blanks, comments, docstring edges) of each algorithm's own module."""
    here, out = Path(__file__).parent / "operators", {}
    for name in ("paths", "kcore", "setcover", "components", "engine"):
        out[name] = sum(1 for x in (here / f"{name}.py").read_text().splitlines() if x.strip() and not x.strip().startswith(("#", '"""')))
    return out
