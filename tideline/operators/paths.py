"""Shortest-path methods on the ordered engine, their unordered baselines, and paths."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tideline.operators import reach
from tideline.operators.engine import OrderedResult, RoundView, run_ordered
from tideline.plans.rules import EdgeRule, OrderedProgram, PrioritySpec
from tideline.plans.schedule import UNBOUNDED, Schedule
from tideline.sources.graphs import Graph, tiles
from tideline.sources.tables import cut, saved

SSSP = OrderedProgram("sssp", PrioritySpec("low", True), EdgeRule.lower(lambda v, w: v + w), "sssp")
WBFS = OrderedProgram("wbfs", PrioritySpec("low", False), EdgeRule.lower(lambda v, w: v + w), "sssp")
ASTAR = OrderedProgram("astar", PrioritySpec("low", True), EdgeRule.lower(lambda v, w: v + w), "sssp")
WIDEST = OrderedProgram("widest", PrioritySpec("high", True), EdgeRule.raise_(lambda v, w: F.least(v, w)), "widest")


def sssp(graph: Graph, source: int, schedule: Schedule | None = None) -> OrderedResult:
    """Distances from ``source``; weights are integers of at least 0."""
    return run_ordered(SSSP, graph.checked(), schedule or Schedule(), {source: 0})


def wbfs(graph: Graph, source: int, schedule: Schedule | None = None) -> OrderedResult:
    """The same for positive weights, with one distance a bucket."""
    return run_ordered(WBFS, graph.checked(True), schedule or Schedule(), {source: 0})


def widest(graph: Graph, source: int, top: int, schedule: Schedule | None = None) -> OrderedResult:
    """The best bottleneck from ``source``, which itself has ``top``."""
    return run_ordered(WIDEST, graph.checked(), schedule or Schedule(), {source: top})


def _reached(target: int):
    def stop(v: RoundView) -> bool:
        return v.watched is not None and v.least >= v.watched

    return stop


def ppsp(graph: Graph, source: int, target: int, schedule: Schedule | None = None, prune: bool = True) -> OrderedResult:
    """Stops when the next bucket can't improve the target any more. Offers above its distance are dropped with ``prune``."""
    return run_ordered(SSSP, graph.checked(), schedule or Schedule(), {source: 0}, stop=_reached(target), watch=target, prune=prune)


def astar(graph: Graph, source: int, target: int, estimate: DataFrame, schedule: Schedule | None = None) -> OrderedResult:
    """Like :func:`ppsp` with priorities that add ``estimate`` ([id, h], never above the true distance to the target)."""
    return run_ordered(ASTAR, graph.checked(), schedule or Schedule(), {source: 0}, extra=estimate, stop=_reached(target), watch=target)


def distance_to(result: OrderedResult, source: int, target: int) -> DataFrame:
    """``[source, target, dist]``, one row; dist is null if the target can't be reached."""
    spark = result.state.sparkSession
    one = spark.createDataFrame([(source, target)], "source long, target long")
    found = result.state.where(F.col("id") == target).select(F.col("id").alias("target"), F.col("value").alias("dist"))
    return one.join(found, "target", "left").select("source", "target", "dist")


def bellman_ford(graph: Graph, source: int, direction: str = "push") -> OrderedResult:
    """Unordered: every changed vertex sends in every round."""
    return run_ordered(SSSP, graph.checked(), Schedule(delta=UNBOUNDED, direction=direction), {source: 0})


def relaxed_order(graph: Graph, source: int, width: int = 4, delta: int = 1) -> OrderedResult:
    """Approximate order: a round takes ``width`` buckets at once."""
    return run_ordered(SSSP, graph.checked(), Schedule(width=width, delta=delta), {source: 0})


def many(graph: Graph, sources: list[int], delta: int = 1, targets: dict[int, int] | None = None) -> DataFrame:
    """``[source, id, dist]`` for several sources in one loop: rounds are shared, state is keyed by (source, id).

    With ``targets`` (source to target) an entry stops growing once it can't improve its target; rows are exact up to the
    target's distance.
    """
    spark = graph.spark
    files = graph.checked().numbered()
    if files is not None and (files.count + len(sources)) * len(sources) <= reach.ENTRIES:
        return saved(spark.range(0, 1, 1, 1).mapInArrow(reach.many(files, sources, delta, targets), "source long, id long, dist long"))
    edges = graph.adjacent()
    state = cut(spark.createDataFrame([(s, s, 0, True) for s in sources], "source long, id long, dist long, active boolean"))
    goal = spark.createDataFrame(list(targets.items()), "source long, target long") if targets else None
    while True:
        low = state.where("active").agg(F.min(F.call_function("div", F.col("dist"), F.lit(delta).cast("long")))).first()[0]
        if low is None:
            return state.select("source", "id", "dist")
        ready = F.col("active") & (F.col("dist") < (low + 1) * delta)
        sent = state.where(ready).select("source", F.col("id").alias("src"), "dist").hint("shuffle_hash").join(edges, "src").selectExpr("source", "dist", "inline(arrays_zip(to, by)) AS (id, weight)").groupBy("source", "id").agg(F.min(F.col("dist") + F.col("weight")).alias("new"))
        rows = state.select("source", "id", "dist", (F.col("active") & ~ready).alias("active"), F.lit(None).cast("long").alias("new")).unionByName(sent.select("source", "id", F.lit(None).cast("long").alias("dist"), F.lit(None).cast("boolean").alias("active"), "new"))
        g = rows.groupBy("source", "id").agg(F.max("dist").alias("old"), F.max("active").alias("act"), F.min("new").alias("new"))
        ch = F.col("new").isNotNull() & (F.col("old").isNull() | (F.col("new") < F.col("old")))
        state = g.select("source", "id", F.when(ch, F.col("new")).otherwise(F.col("old")).alias("dist"), (F.coalesce("act", F.lit(False)) | ch).alias("active"))
        if goal is not None:
            # As a table: the planner's guess of the state's size would be squared in every round, to a number that fills the driver.
            state = saved(state)
            best = state.join(F.broadcast(goal), "source").where("id = target").select("source", F.col("dist").alias("best"))
            state = state.join(F.broadcast(best), "source", "left").withColumn("active", F.col("active") & (F.col("best").isNull() | (F.col("dist") < F.col("best")))).drop("best")
        state = saved(state)


def parents(graph: Graph, result: OrderedResult, source: int) -> DataFrame:
    """``[id, dist, parent]``: for each reached vertex a neighbour on a shortest path; null for the source.

    Over edges of positive weight the smallest such neighbour, which lies nearer to the source. A vertex that only edges of weight zero reach
    takes the smallest neighbour among those that the source reaches with one such edge less, so that parents never form a cycle.
    """
    d = result.values("dist")
    tight = cut(d.toDF("src", "ds").join(graph.edges, "src").join(d.toDF("dst", "dd"), "dst").where("ds + weight = dd").where(F.col("dst") != source).select("src", "dst", "weight"))
    up = cut(tight.where("weight > 0").groupBy(F.col("dst").alias("id")).agg(F.min("src").alias("parent")))
    level = tight.where("weight = 0").join(up.select(F.col("id").alias("dst")), "dst", "left_anti").select("src", "dst")
    if level.isEmpty():
        return d.join(up, "id", "left")
    level = cut(level)
    found, front = up, up.select("id").unionByName(d.where(F.col("id") == source).select("id"))
    while True:
        new = level.join(front.select(F.col("id").alias("src")), "src").join(found.select(F.col("id").alias("dst")), "dst", "left_anti")
        new = cut(new.groupBy(F.col("dst").alias("id")).agg(F.min("src").alias("parent")))
        if new.isEmpty():
            return d.join(found, "id", "left")
        found, front = cut(found.unionByName(new)), new.select("id")


def extract_path(tree: DataFrame, source: int, target: int, max_hops: int = 100_000) -> list[int]:
    """Vertices from source to target along parents; one small lookup a hop, empty if there is no path."""
    path, at, seen = [target], target, {target}
    while at != source and len(path) <= max_hops:
        row = tree.where(F.col("id") == at).select("parent").first()
        if row is None or row["parent"] is None or row["parent"] in seen:
            return []
        at = row["parent"]
        seen.add(at)
        path.append(at)
    return path[::-1]


def k_hop(graph: Graph, source: int, k: int) -> DataFrame:
    """``[id, hops]`` of the vertices within ``k`` edges."""
    e = graph.pushed()
    found = cut(graph.spark.createDataFrame([(source, 0)], "id long, hops int"))
    for i in range(1, k + 1):
        new = found.where(F.col("hops") == i - 1).join(e, F.col("id") == F.col("src")).select(F.col("dst").alias("id")).distinct()
        found = cut(found.unionByName(new.join(found.select("id"), "id", "left_anti").withColumn("hops", F.lit(i))))
    return found


def pairs_by_distance(graph: Graph, source: int, n: int = 10, schedule: Schedule | None = None) -> list[int]:
    """One target for each of ``n`` equal parts of the distances from ``source``: the first vertex of the part."""
    d = sssp(graph, source, schedule or Schedule(delta=UNBOUNDED)).values("dist")
    part = tiles(d, n, ["dist", "id"])
    return [r["t"] for r in part.groupBy("part").agg(F.min_by("id", F.struct("dist", "id")).alias("t")).orderBy("part").collect()]


def check_estimate(graph: Graph, estimate: DataFrame) -> DataFrame:
    """One row, ``violations``: edges whose ends' estimates differ by more than the weight."""
    e = graph.edges.join(estimate.toDF("src", "hs"), "src").join(estimate.toDF("dst", "hd"), "dst")
    return e.agg(F.count(F.when(F.col("hs") > F.col("weight") + F.col("hd"), 1)).alias("violations"))
