"""Small column functions, and the choice of a bucket width."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def bucket_of(priority: Column, delta: int) -> Column:
    """Exact integer division; null stays null."""
    return F.call_function("div", priority, F.lit(delta).cast("long"))


def long_words(text: Column) -> Column:
    """Lower-case ASCII words of four letters and more."""
    return F.regexp_extract_all(F.lower(text), F.lit("[a-z]{4,}"), 0)


def suggest_delta(edges: DataFrame) -> int:
    """A power of two near the median weight for sparse graphs, and near weight per degree for dense ones, 1..2^17."""
    w = edges.agg(F.percentile_approx("weight", 0.5).alias("w"), F.count(F.lit(1)).alias("e"), F.approx_count_distinct("src").alias("v")).first()
    if not w["e"]:
        return 1
    degree = w["e"] / max(1, w["v"])
    goal = w["w"] * 16 if degree <= 8 else max(1, w["w"] * 4 / degree)
    return min(1 << 17, 1 << max(0, int(goal).bit_length() - 1))


def register_sql(spark: SparkSession) -> None:
    """The table functions for SQL: steps of a path, and entries of a packed adjacency."""

    @F.udtf(returnType="step int, id long")
    class PathSteps:
        def eval(self, path: list[int]):
            for i, v in enumerate(path or []):
                yield i, v

    @F.udtf(returnType="dst long, weight long")
    class Neighbours:
        def eval(self, adj: list):
            for e in adj or []:
                yield e["dst"], e["weight"]

    spark.udtf.register("path_steps", PathSteps)
    spark.udtf.register("neighbours", Neighbours)


def edge_schema() -> T.StructType:
    return T.StructType([T.StructField(c, T.LongType(), False) for c in ("src", "dst", "weight")])
