"""The relaxed core threshold of a sample."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def next_threshold(mean: float, eta: int, min_pts: int, rule: str = "monotone") -> int:
    """eta after one step, given the mean neighbour count of a part of the sample."""
    guess = math.floor(mean + 0.5)
    if rule == "fixed":
        return min_pts
    if rule == "plus_one":
        return min(min_pts, eta + 1)
    if rule == "printed":
        return guess if mean <= min_pts else eta + 1
    return min(min_pts, max(eta + 1, guess)) if mean <= min_pts else min(min_pts, eta + 1)


def thresholds(mean: Column, eta: Column, min_pts: int) -> dict[str, Column]:
    """next_threshold() of columns, by rule."""
    guess, up = F.floor(mean + 0.5), F.least(F.lit(min_pts), eta + 1)
    return {
        "fixed": F.lit(min_pts),
        "plus_one": up,
        "printed": F.when(mean <= min_pts, guess).otherwise(eta + 1),
        "monotone": F.when(mean <= min_pts, F.least(F.lit(min_pts), F.greatest(eta + 1, guess))).otherwise(up),
    }


def estimate_eta(counts: DataFrame, min_pts: int, eta: int = 1, fraction: float = 0.10, rule: str = "monotone") -> DataFrame:
    """One row (n_used, mean_n_eps, eta): the mean over a share of the sample, the first in the order of md5 of "eta:id"."""
    total = counts.count()
    used = max(1, math.ceil(fraction * total))
    part = counts.withColumn("k", F.md5(F.concat(F.lit("eta:"), F.col("id").cast("string")).cast("binary"))).orderBy("k").limit(used)
    row = part.agg(F.avg("n_eps").alias("mean_n_eps"), F.count(F.lit(1)).alias("n_used"))
    value = thresholds(F.col("mean_n_eps"), F.lit(eta), min_pts)[rule]
    return row.select("n_used", F.round("mean_n_eps", 6).alias("mean_n_eps"), value.cast("long").alias("eta"))
