"""Edge lists in text files, and writers of results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tideline.sources.graphs import EDGE


def edge_list(spark: SparkSession, path: str, sep: str = " ", weighted: bool = True) -> DataFrame:
    """``src dst [weight]`` lines; lines that begin with # are comments, a missing weight is 1."""
    schema = "src long, dst long" + (", weight long" if weighted else "")
    rows = spark.read.schema(schema).csv(path, sep=sep, comment="#").where("src is not null and dst is not null")
    return rows.select(*EDGE) if weighted else rows.withColumn("weight", F.lit(1).cast("long"))


def dimacs(spark: SparkSession, path: str) -> DataFrame:
    """The ``a u v w`` lines of a road file, ids counted from 1."""
    f = F.split("value", r"\s+")
    return spark.read.text(path).where(F.col("value").startswith("a ")).select(f[1].cast("long").alias("src"), f[2].cast("long").alias("dst"), f[3].cast("long").alias("weight"))


def write(df: DataFrame, path: str, fmt: str = "parquet", partition_by: list[str] | None = None, mode: str = "error") -> None:
    """A folder of ``fmt`` (parquet, orc, json, csv), partitioned by columns if asked."""
    w = df.write.mode(mode).format(fmt)
    (w.partitionBy(*partition_by) if partition_by else w).save(path)


def write_table(df: DataFrame, name: str, bucket_by: str | None = None, buckets: int = 8, mode: str = "overwrite") -> None:
    """A table of the session's catalog; with ``bucket_by`` later joins on that column need no exchange."""
    w = df.write.mode(mode).format("parquet")
    (w.bucketBy(buckets, bucket_by).sortBy(bucket_by) if bucket_by else w).saveAsTable(name)
