"""Leaders, then density: one leader for each grid cell is clustered, and the other points follow theirs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from densereps.functions.expr import cell
from densereps.operators.exact import exact_density


def leaders(points: DataFrame, radius: int) -> DataFrame:
    """(cx, cy, id, x, y, followers): the point of least id of each cell of that side, and how many the cell holds."""
    celled = points.withColumn("cx", cell("x", radius)).withColumn("cy", cell("y", radius))
    return celled.groupBy("cx", "cy").agg(
        F.min("id").alias("id"), F.min_by("x", "id").alias("x"), F.min_by("y", "id").alias("y"), F.count(F.lit(1)).alias("followers")
    )


def leaders_then_density(points: DataFrame, radius: int, eps: float, min_pts: int) -> DataFrame:
    """(id, leader, cluster): the density cluster of each point's leader."""
    found = leaders(points, radius)
    named = exact_density(found.select("id", "x", "y"), eps, min_pts).select(F.col("id").alias("leader"), "cluster")
    own = points.withColumn("cx", cell("x", radius)).withColumn("cy", cell("y", radius)).select("id", "cx", "cy")
    met = own.join(found.select("cx", "cy", F.col("id").alias("leader")), ["cx", "cy"]).join(named, "leader")
    return met.select("id", "leader", "cluster")
