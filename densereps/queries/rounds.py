"""Rounds and runs on the given tables, for the queries of closed forms and of tables of runs; with their DuckDB SQL.

A round is a month of `orders`, its points those of shapes9_large. Two labels of a point are its shape and the column of
shapes it lies in; delta is the share of a round's pairs that one label joins and the other parts. A run is a customer:
k is the number of shapes among the points of its orders, agreement the share of the largest.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from densereps.functions.expr import cell, choose2
from densereps.plans.lineage import cut
from densereps.queries import sql as S
from densereps.sources.points import load_points

PLACED = f"{S.points('shapes9_large')}, o AS (SELECT CAST(12 * (year(o_orderdate) - 1992) + month(o_orderdate) AS INT) AS iteration, o_custkey AS run, truth AS a, x // 2000 AS b FROM p JOIN orders ON o_orderkey = id)"
_TWO = "SELECT iteration, sum(c * (c - 1) // 2) AS w FROM (SELECT iteration, count(*) AS c FROM o GROUP BY iteration, {}) GROUP BY iteration"
#: CTEs up to t(iteration, added, k, delta), a row for each round.
ROUNDS = (
    PLACED + f", ja AS ({_TWO.format('a')}), jb AS ({_TWO.format('b')}), jab AS ({_TWO.format('a, b')}), "
    "t AS (SELECT iteration, added, k, CASE WHEN added > 1 THEN CAST(ja.w + jb.w - 2 * jab.w AS DOUBLE) / (added * (added - 1) // 2) ELSE 0.0 END AS delta FROM "
    "(SELECT iteration, count(*) AS added, count(DISTINCT a) AS k FROM o GROUP BY iteration) JOIN ja USING (iteration) JOIN jb USING (iteration) JOIN jab USING (iteration))"
)
#: CTEs up to r(k, agreement), a row for each run.
RUNS = PLACED + ", r AS (SELECT count(*) AS k, max(c) / CAST(sum(c) AS DOUBLE) AS agreement FROM (SELECT run, a, count(*) AS c FROM o GROUP BY run, a) GROUP BY run)"


def placed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(iteration, run, a, b) of each order's point."""
    orders = spark.read.parquet(f"{sf_dir}/orders.parquet")
    month = (12 * (F.year("o_orderdate") - 1992) + F.month("o_orderdate")).cast("int").alias("iteration")
    points = load_points(spark, sf_dir, "shapes9_large").select(F.col("id").alias("o_orderkey"), F.col("truth").alias("a"), cell("x", 2000).alias("b"))
    return orders.select("o_orderkey", F.col("o_custkey").alias("run"), month).join(points, "o_orderkey").drop("o_orderkey")


def rounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(iteration, added, k, delta), a row for each round; kept, since windows over all of them follow."""
    counts = placed(spark, sf_dir).groupBy("iteration", "a", "b").agg(F.count(F.lit(1)).alias("n"))
    counts = cut(counts)  # a row for each pair of labels in a round
    two = lambda *by: counts.groupBy("iteration", *by).agg(F.sum("n").alias("n")).groupBy("iteration").agg(F.sum(choose2("n")).alias("w" + "".join(by)))
    size = counts.groupBy("iteration").agg(F.sum("n").alias("added"), F.countDistinct("a").alias("k"))
    met = size.join(two("a"), "iteration").join(two("b"), "iteration").join(two("a", "b"), "iteration")
    delta = F.when(F.col("added") > 1, (F.col("wa") + F.col("wb") - 2 * F.col("wab")).cast("double") / choose2("added")).otherwise(0.0)
    return met.select("iteration", "added", "k", delta.alias("delta"))


def runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(k, agreement), a row for each run."""
    counts = placed(spark, sf_dir).groupBy("run", "a").agg(F.count(F.lit(1)).alias("c"))
    return counts.groupBy("run").agg(F.count(F.lit(1)).alias("k"), (F.max("c") / F.sum("c")).alias("agreement")).drop("run")


def in_order():
    """A window over all rounds: a row for each month."""
    return W.orderBy("iteration")
