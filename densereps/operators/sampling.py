"""Drawing without repetition: one permutation of the ids, cut into consecutive slices."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from densereps.functions.expr import md5_key
from densereps.plans.lineage import stored


#: Rows that are ranked together, about.
ROWS_A_PART = 500_000


def permute(df: DataFrame, seed: int = 0, id_col: str = "id") -> DataFrame:
    """df with rank, from 0, in the order of md5 of "seed:id"; stored, so that a slice is read by its ranks alone.

    Keys are spread evenly, so the key's first digits deal the rows into parts of about ROWS_A_PART; one shuffle ranks
    them, and each part adds the rows before it, of which the driver gets one number for each part.
    """
    keyed = df.withColumn("rank_key", md5_key(id_col, seed))
    digits = max(1, math.ceil(math.log(max(1, df.count() / ROWS_A_PART), 16)))
    part = F.substring("rank_key", 1, digits)
    sizes = {r["part"]: r["count"] for r in keyed.groupBy(part.alias("part")).count().collect()}
    before, total = [], 0
    for name in sorted(sizes):
        before.append((name, total))
        total += sizes[name]
    offsets = df.sparkSession.createDataFrame(before, "part string, before long")
    ranked = keyed.withColumn("part", part).withColumn("at", F.row_number().over(W.partitionBy("part").orderBy("rank_key", id_col)))
    return stored(ranked.join(F.broadcast(offsets), "part").withColumn("rank", F.col("before") + F.col("at") - 1).drop("part", "before", "at"))


def key_head(id_col: str = "id", seed: int = 0) -> Column:
    """The first 32 bits of the permutation's key, evenly spread."""
    return F.conv(F.substring(md5_key(id_col, seed), 1, 8), 16, 10).cast("long")


def key_range(df: DataFrame, low: int, high: int, seed: int = 0, id_col: str = "id") -> DataFrame:
    """The rows whose key's head is from low to high - 1: a filter in the scan's stage, no shuffle."""
    return df.filter((key_head(id_col, seed) >= F.lit(low)) & (key_head(id_col, seed) < F.lit(high)))


def take(df: DataFrame, n: int, seed: int = 0, id_col: str = "id") -> DataFrame:
    """The first n rows of the permutation: a top-n, without a sort of all rows."""
    return df.withColumn("rank_key", md5_key(id_col, seed)).orderBy("rank_key", id_col).limit(n)


def threshold_sample(df: DataFrame, share: float, seed: int = 0, id_col: str = "id") -> DataFrame:
    """About a share of the rows by a threshold on the key's first 32 bits: a filter in the scan's stage, no shuffle."""
    return key_range(df, 0, int(share * (1 << 32)), seed, id_col)


def stratified(df: DataFrame, strata: str, n: int, seed: int = 0, id_col: str = "id") -> DataFrame:
    """At most n rows of each stratum, the first in the permutation; ranked in each task before the shuffle."""
    ranked = df.withColumn("rank_key", md5_key(id_col, seed)).withColumn(
        "rank", F.row_number().over(W.partitionBy(strata).orderBy("rank_key", id_col))
    )
    return ranked.filter(F.col("rank") <= n).drop("rank_key", "rank")


class SamplePlan:
    """Slices of one permutation: the first sample, the test sample, then increments."""

    def __init__(self, points: DataFrame, gamma: int, beta: int, alpha: int, seed: int = 0):
        self.ranked, self.gamma, self.beta, self.alpha = permute(points, seed), gamma, beta, alpha

    def slice(self, first: int, last: int) -> DataFrame:
        return self.ranked.filter((F.col("rank") >= first) & (F.col("rank") < last)).drop("rank_key")

    def prototype(self) -> DataFrame:
        return self.slice(0, self.gamma)

    def test(self) -> DataFrame:
        return self.slice(self.gamma, self.gamma + self.alpha)

    def batch(self, i: int) -> DataFrame:
        """Increment i, from 1."""
        start = self.gamma + self.alpha + (i - 1) * self.beta
        return self.slice(start, start + self.beta)

    def labelled(self) -> DataFrame:
        """Every point with what it is drawn for: prototype, test, or inc1, inc2, ..."""
        rank = F.col("rank")
        part = F.floor((rank - self.gamma - self.alpha) / self.beta).cast("long") + 1
        return self.ranked.select(
            "id", "rank",
            F.when(rank < self.gamma, "prototype").when(rank < self.gamma + self.alpha, "test").otherwise(F.concat(F.lit("inc"), part.cast("string"))).alias("slice"),
        )

    def write(self, path: str) -> None:
        """The plan as a table partitioned by slice, so that an iteration reads one folder."""
        self.labelled().join(self.ranked.drop("rank", "rank_key"), "id").repartition("slice").write.partitionBy("slice").mode("overwrite").parquet(path)
