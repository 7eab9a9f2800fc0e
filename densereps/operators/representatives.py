"""Representatives: cores of the rim and of the centre of each cluster."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def density_ratio(states: DataFrame) -> DataFrame:
    """The cores with ratio: neighbours over the most that a core of the cluster has, from an aggregate joined back."""
    cores = states.filter("state = 'core'")
    top = cores.groupBy("cluster").agg(F.max("n_eps").alias("top"))
    return cores.join(top, "cluster").withColumn("ratio", F.col("n_eps") / F.col("top"))


def representatives(states: DataFrame, tau: float = 0.3, selector: str = "rim_and_center") -> DataFrame:
    """(id, cluster, n_eps, ratio, is_center): cores of ratio at most tau, and the densest."""
    rated = density_ratio(states).withColumn("is_center", F.col("n_eps") == F.col("top"))
    keep = {
        "rim_and_center": F.col("is_center") | (F.col("ratio") <= tau), "rim_only": F.col("ratio") <= tau,
        "center_only": F.col("is_center"), "all_core": F.lit(True),
    }[selector]
    return rated.filter(keep).select("id", "cluster", "n_eps", "ratio", "is_center")


def reps_by_tau(states: DataFrame, taus: list[float]) -> DataFrame:
    """(tau, n_reps, n_clusters) for many thresholds in one pass over the cores."""
    rated = density_ratio(states).withColumn("tau", F.explode(F.array(*map(F.lit, taus))))
    kept = rated.filter((F.col("ratio") <= F.col("tau")) | (F.col("n_eps") == F.col("top")))
    return kept.groupBy("tau").agg(F.count(F.lit(1)).alias("n_reps"), F.countDistinct("cluster").alias("n_clusters"))


def one_center(states: DataFrame) -> DataFrame:
    """The densest core of each cluster, the least id among equals."""
    ranked = density_ratio(states).withColumn("at", F.row_number().over(W.partitionBy("cluster").orderBy(F.desc("n_eps"), "id")))
    return ranked.filter("at = 1").select("id", "cluster", "n_eps")
