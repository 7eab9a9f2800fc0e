"""Size of the test sample, and the chance that it holds two points of every cluster."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def share(n: int, k: int, prob: float = 1.0, p: list[float] | None = None, exact: bool = True) -> float:
    """The fraction t to draw. k clusters of equal size, or of shares p; prob: of two points of each."""
    weight = k * prob ** (1 / (2 * k)) if p is None else prob ** (1 / (2 * k)) / math.exp(sum(map(math.log, p)) / len(p))
    if not exact:
        return 1 / (2 * n) + math.sqrt(weight / n)
    return (1 + math.sqrt(1 + 4 * n * weight)) / (2 * n)


def test_size(
    n: int, k: int, prob: float = 1.0, p: list[float] | None = None, exact: bool = True, rectify_n: int | None = None, rectify_k: int | None = None
) -> int:
    """Points of the test sample. rectify_n, rectify_k: what stands for n and k on more than rectify_n points."""
    large = rectify_n is not None and n > rectify_n
    n_used = rectify_n if large else n
    k_used = rectify_k if large and rectify_k else max(1, k)
    return min(n, math.ceil(n_used * share(n_used, k_used, prob, p, exact)))


test_size.__test__ = False


def coverage(m: int, p: float, t: float | None = None) -> tuple[float, float]:
    """(first-order estimate, exact chance) that m test points hold two of a cluster of share p.

    t: drawn fraction; the estimate multiplies it in, as it is stated for a point of the cluster and of the sample.
    """
    return ((m - 1) * p * (1 if t is None else t)) ** 2, 1 - (1 - p) ** m - m * p * (1 - p) ** (m - 1)


def test_size_table(cases: DataFrame) -> DataFrame:
    """cases(n, k) with alpha and alpha_approx, as one projection."""
    root = (1 + F.sqrt(1 + 4.0 * F.col("n") * F.col("k"))) / (2.0 * F.col("n"))
    near = 1 / (2.0 * F.col("n")) + F.sqrt(F.col("k") / F.col("n"))
    return cases.select(
        "*", F.ceil(F.round(F.col("n") * root, 9)).cast("long").alias("alpha"),
        F.ceil(F.round(F.col("n") * near, 9)).cast("long").alias("alpha_approx"),
    )


test_size_table.__test__ = False


def test_size_shares(counts: DataFrame, by: str, probs: list[float]) -> DataFrame:
    """(by, n, prob, k, alpha): test_size() for the shares that counts(by, c) gives, and each chance."""
    size = counts.groupBy(by).agg(F.sum("c").alias("n"), F.count(F.lit(1)).alias("k"), F.avg(F.log("c")).alias("mean_log"))
    rows = size.withColumn("prob", F.explode(F.array(*[F.lit(p) for p in probs])))
    n, k = F.col("n"), F.col("k")
    weight = F.pow("prob", 1 / (2.0 * k)) / F.exp(F.col("mean_log") - F.log("n"))
    alpha = F.least(n, F.ceil(F.round((1 + F.sqrt(1 + 4.0 * n * weight)) / 2.0, 6)).cast("long"))
    return rows.select(by, "n", "prob", "k", alpha.alias("alpha"))


test_size_shares.__test__ = False
