"""Disagreement of two labellings of one sample, and when to stop."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from densereps.functions.expr import choose2


def contingency(df: DataFrame, a: str, b: str) -> DataFrame:
    """(a, b, level, n): counts of each pair of labels, of each label alone, and of all, in one grouping."""
    return df.groupingSets([[F.col(a), F.col(b)], [F.col(a)], [F.col(b)], []], F.col(a), F.col(b)).agg(
        F.grouping_id().alias("level"), F.count(F.lit(1)).alias("n")
    )


def instability(df: DataFrame, a: str = "prev_cluster", b: str = "cur_cluster") -> DataFrame:
    """One row (m, delta): the share of pairs joined by one labelling only, from counts instead of pairs."""
    sums = contingency(df, a, b).groupBy("level").agg(F.sum(choose2("n")).alias("pairs"), F.sum("n").alias("m"))
    of = lambda level: F.coalesce(F.max(F.when(F.col("level") == level, F.col("pairs"))), F.lit(0))
    row = sums.agg(of(0).alias("ab"), of(1).alias("a"), of(2).alias("b"), of(3).alias("every"), F.coalesce(F.max("m"), F.lit(0)).alias("m"))
    delta = F.when(F.col("every") > 0, (F.col("a") + F.col("b") - 2 * F.col("ab")) / F.col("every")).otherwise(0.0)
    return row.select("m", F.round(delta, 9).alias("delta"))


def instability_pairs(df: DataFrame, a: str = "prev_cluster", b: str = "cur_cluster") -> DataFrame:
    """The same from every pair; for tests and small samples."""
    left = df.select(F.col("id").alias("i"), F.col(a).alias("a1"), F.col(b).alias("b1"))
    right = df.select(F.col("id").alias("j"), F.col(a).alias("a2"), F.col(b).alias("b2"))
    pairs = left.join(right, F.col("i") < F.col("j"))
    differ = (F.col("a1") == F.col("a2")) != (F.col("b1") == F.col("b2"))
    return pairs.agg(F.count(F.lit(1)).alias("pairs"), F.round(F.avg(differ.cast("double")), 9).alias("delta"))


@dataclass
class StopPolicy:
    """Stops after patience rounds with at most delta_tol; first raises eta to min_pts if it is not there yet."""

    min_pts: int
    delta_tol: float = 0.0
    patience: int = 1
    force_full_minpts: bool = True
    max_iterations: int = 1000
    calm: int = 0

    def after(self, iteration: int, delta: float, eta: int, left: int) -> tuple[str | None, int]:
        """(reason to stop or None, eta for the next round)."""
        self.calm = self.calm + 1 if delta <= self.delta_tol else 0
        if self.calm >= self.patience:
            if eta >= self.min_pts or not self.force_full_minpts:
                return "stable", eta
            self.calm, eta = 0, self.min_pts
        if left <= 0:
            return "exhausted", eta
        return ("max_iterations", eta) if iteration >= self.max_iterations else (None, eta)
