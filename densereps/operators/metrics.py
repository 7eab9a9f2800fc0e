"""Measures of accuracy and cost, from contingency counts and traces."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from densereps.functions.expr import choose2
from densereps.operators.stability import contingency
from densereps.params import SsdcParams


def nmi(df: DataFrame, a: str, b: str, average: str = "geometric", exclude_noise: bool = False) -> DataFrame:
    """One row (n, nmi): normalised mutual information of two label columns; noise (-1) is one class, or left out.

    Rows with a null label count for neither n nor nmi; without any row, or any label, nmi is null.
    """
    rows = df.select(F.col(a).cast("string").alias("a"), F.col(b).cast("string").alias("b"))
    if exclude_noise:
        rows = rows.filter("a <> '-1' AND b <> '-1'")
    counts = contingency(rows.na.drop(), "a", "b").groupBy("level").agg(
        F.sum("n").alias("n"), F.sum(F.col("n") * F.log("n")).alias("s")
    )
    of = lambda level: F.max(F.when(F.col("level") == level, F.col("s")))
    row = counts.agg(F.max("n").alias("n"), of(0).alias("sab"), of(1).alias("sa"), of(2).alias("sb"))
    n = F.col("n")
    h = lambda s: F.greatest(F.log(n) - F.col(s) / n, F.lit(0.0))
    scale = {
        "geometric": F.sqrt(h("sa") * h("sb")), "arithmetic": (h("sa") + h("sb")) / 2, "max": F.greatest(h("sa"), h("sb")), "min": F.least(h("sa"), h("sb")),
    }[average]
    value = F.when(scale > 1e-12, (h("sa") + h("sb") - h("sab")) / scale).otherwise(
        F.when((h("sa") < 1e-12) & (h("sb") < 1e-12), 1.0).otherwise(0.0)
    )
    return row.select(F.coalesce("n", F.lit(0)).alias("n"), F.when(n > 0, F.round(value, 6)).alias("nmi"))


def pair_metrics(df: DataFrame, a: str, b: str) -> DataFrame:
    """(n, rand, adjusted_rand, precision, recall, purity) of labelling a against b."""
    counts = contingency(df, a, b)
    sums = counts.groupBy("level").agg(F.sum(choose2("n")).alias("p"), F.sum("n").alias("n"))
    of = lambda level: F.max(F.when(F.col("level") == level, F.col("p"))).cast("double")
    row = sums.agg(F.max("n").alias("n"), of(0).alias("ab"), of(1).alias("pa"), of(2).alias("pb"), of(3).alias("every"))
    best = counts.filter("level = 0").groupBy(a).agg(F.max("n").alias("top")).agg(F.sum("top").alias("hits"))
    c = F.col
    chance = c("pa") * c("pb") / c("every")
    return row.join(F.broadcast(best), F.lit(True)).select(
        "n", F.round(1 - (c("pa") + c("pb") - 2 * c("ab")) / c("every"), 6).alias("rand"),
        F.round((c("ab") - chance) / ((c("pa") + c("pb")) / 2 - chance), 6).alias("adjusted_rand"),
        F.round(c("ab") / c("pa"), 6).alias("precision"), F.round(c("ab") / c("pb"), 6).alias("recall"),
        F.round(c("hits") / c("n"), 6).alias("purity"),
    )


def n_clusters(df: DataFrame, cluster: str = "cluster") -> DataFrame:
    return df.agg(
        F.countDistinct(F.when(F.col(cluster) >= 0, F.col(cluster))).alias("k"), F.sum((F.col(cluster) < 0).cast("long")).alias("n_noise")
    )


def k_frequency(runs: DataFrame, by: list[str] | None = None) -> DataFrame:
    """(by..., k, n, share): how often each number of clusters was found."""
    by = by or []
    counts = runs.groupBy(*by, "k").agg(F.count(F.lit(1)).alias("n"))
    return counts.withColumn("share", F.round(F.col("n") / F.sum("n").over(W.partitionBy(*by)), 6))


def mean_and_deviation(runs: DataFrame, by: list[str], columns: list[str]) -> DataFrame:
    return runs.groupBy(*by).agg(
        F.count(F.lit(1)).alias("runs"), *[F.round(F.avg(c), 6).alias(f"mean_{c}") for c in columns], *[F.round(F.stddev_samp(c), 6).alias(f"sd_{c}") for c in columns]
    )


def predicted_cost(trace: DataFrame, p: SsdcParams) -> DataFrame:
    """(iteration, predicted): operations of each round, as sample, increment and test sizes give them."""
    first = F.lit(float(p.gamma) ** 2)
    probe = F.lit(float(p.beta)) * F.col("n_sample")
    each = probe + F.col("n_sample") + F.col("n_test").cast("double") ** 2 + F.col("n_test") * F.col("k")
    return trace.select("iteration", F.when(F.col("iteration") == 0, first).otherwise(each).alias("predicted"))
