"""Estimates of remaining distance as columns over vertices with coordinates: ``[id, h]``."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

EARTH_KM = 6371.0088


def _at(vertices: DataFrame, target: int):
    row = vertices.where(F.col("id") == target).first()
    if row is None:
        raise ValueError(f"no vertex {target}")
    return row


def zero(vertices: DataFrame) -> DataFrame:
    return vertices.select("id", F.lit(0).cast("long").alias("h"))


def manhattan(vertices: DataFrame, target: int, least_weight: int) -> DataFrame:
    """Lattice steps to the target, each at the smallest weight."""
    t = _at(vertices, target)
    return vertices.select("id", ((F.abs(F.col("x") - t["x"]) + F.abs(F.col("y") - t["y"])) * least_weight).cast("long").alias("h"))


def euclidean(vertices: DataFrame, target: int, scale: float) -> DataFrame:
    """Straight distance on x and y, times ``scale``, rounded down."""
    t = _at(vertices, target)
    return vertices.select("id", F.floor(F.sqrt(F.pow(F.col("x") - t["x"], 2) + F.pow(F.col("y") - t["y"], 2)) * scale).cast("long").alias("h"))


def vector(vertices: DataFrame, target: int, scale: float) -> DataFrame:
    """Straight distance of vectors (``v``), times ``scale``, rounded down."""
    t = _at(vertices, target)
    goal = F.array(*map(F.lit, map(float, t["v"])))
    d = F.sqrt(F.aggregate(F.zip_with("v", goal, lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, x: s + x))
    return vertices.select("id", F.floor(F.round(d * scale, 6)).cast("long").alias("h"))


def great_circle_km(lon1, lat1, lon2, lat2):
    """Haversine distance of degrees as a column."""
    la1, la2, dlo = F.radians(lat1), F.radians(lat2), F.radians(lon2) - F.radians(lon1)
    a = F.pow(F.sin((la2 - la1) / 2), 2) + F.cos(la1) * F.cos(la2) * F.pow(F.sin(dlo / 2), 2)
    return F.lit(2 * EARTH_KM) * F.asin(F.sqrt(F.least(a, F.lit(1.0))))


def great_circle(vertices: DataFrame, target: int, scale: float) -> DataFrame:
    """Distance on the sphere between x (longitude) and y (latitude) in degrees, in km times ``scale``, rounded down."""
    t = _at(vertices, target)
    return vertices.select("id", F.floor(great_circle_km(F.col("x"), F.col("y"), F.lit(float(t["x"])), F.lit(float(t["y"]))) * scale).cast("long").alias("h"))
