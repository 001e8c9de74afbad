"""Distances that follow a stream of new edges, and edges made from a stream of events."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from tideline.operators.engine import run_ordered
from tideline.operators.paths import SSSP
from tideline.plans.schedule import Schedule
from tideline.sources.graphs import Graph


class LiveDistances:
    """Distances from a source under edge insertions. New edges only lower distances, so the ordered loop goes on from
    where it stood: the ends of new edges whose offer improves their target are the next frontier. Removals aren't possible.

    State and edges lie in numbered folders below ``path``; a batch that is replayed writes its number anew.
    """

    def __init__(self, spark: SparkSession, path: str, source: int, schedule: Schedule | None = None):
        self.spark, self.path, self.source, self.schedule = spark, path, source, schedule or Schedule(delta=64)
        self.version = -1

    def state(self) -> DataFrame:
        return self.spark.read.parquet(f"{self.path}/state-{self.version}")

    def edges(self) -> DataFrame:
        return self.spark.read.parquet(f"{self.path}/edges-*")

    def batch(self, new: DataFrame, number: int) -> None:
        """For ``foreachBatch``: ``new`` holds ``[src, dst, weight]``."""
        if not new.where("weight < 0").isEmpty():
            raise ValueError("weights must be at least 0")
        new.select("src", "dst", "weight").write.mode("overwrite").parquet(f"{self.path}/edges-{number}")
        edges = self.edges().groupBy("src", "dst").agg(F.min("weight").alias("weight"))
        if self.version < 0:
            res = run_ordered(SSSP, Graph(edges), self.schedule, {self.source: 0}).state
        else:
            old = self.state().where("value is not null").select("id", "value")
            offer = new.join(old.toDF("src", "v"), "src").groupBy(F.col("dst").alias("id")).agg(F.min(F.col("v") + F.col("weight")).alias("o"))
            both = old.join(offer, "id", "full_outer")
            better = F.col("o").isNotNull() & (F.col("value").isNull() | (F.col("o") < F.col("value")))
            first = both.select("id", F.least("value", "o").alias("value"), better.alias("go"))
            res = _resume(Graph(edges), first, self.schedule)
        res.write.mode("overwrite").parquet(f"{self.path}/state-{number}")
        self.version = number

    def follow(self, stream: DataFrame, checkpoint: str):
        return stream.writeStream.foreachBatch(self.batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def _resume(graph: Graph, first: DataFrame, schedule: Schedule) -> DataFrame:
    """The ordered loop from given values, active only where an edge has just lowered them."""
    from tideline.operators import engine as E
    from tideline.plans.schedule import validate

    validate(SSSP, schedule)
    with E.steady(graph.spark, graph.P):
        verts = graph.all_vertices().select("id").join(first, "id", "left")
        state = verts.select("id", "value", F.lit(0).cast("long").alias("h"), F.coalesce("go", F.lit(False)).alias("active"), F.lit(None).cast("long").alias("settled_at"))
        q, m = E.BucketQueue(SSSP, schedule, state.repartition(graph.P, "id")), E.Metrics()
        view = E._settle(q, m, None, False)
        while not q.done():
            q.state = E.lazy_round(q, graph, view["n_active"], False, None)
            view = E._settle(q, m, None, False)
        return q.state


_EDGE = "src long, dst long, weight long"
_LAST = "event_id long, micros long"


def edges_of_events(events: DataFrame, late: str = "2 hours") -> DataFrame:
    """A stream of edges from each event to the next one of its user, with the last event of each user as state."""

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
        ids, at = rows["event_id"].tolist(), (rows["ts"].astype("int64") // (1 if rows["ts"].dtype == "datetime64[us]" else 1000)).tolist()
        if state.exists:
            last = state.get
            ids, at = [last[0], *ids], [last[1], *at]
        state.update((ids[-1], at[-1]))
        yield pd.DataFrame({"src": ids[:-1], "dst": ids[1:], "weight": [max(0, (b - a) // 1_000_000) + 1 for a, b in zip(at, at[1:])]})

    return events.withWatermark("ts", late).groupBy("user_id").applyInPandasWithState(step, _EDGE, _LAST, "append", GroupStateTimeout.NoTimeout)


def deduplicated(events: DataFrame, late: str = "2 hours") -> DataFrame:
    """Events once each, as long as repeats come within the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])
