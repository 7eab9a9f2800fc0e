"""Anytime density clustering by blocks of range queries; it ends with the clusters of exact density clustering.

A first block of range queries gives primitive groups: a queried core with its neighbours. Groups whose cores are near
each other are known to be one cluster. Each next block queries points that may still change a cluster, those that most
clusters wait for first:

- points in no group, which may start one;
- points within 2 eps of known cores of several clusters, which may link them, or be a border of several;
- neighbours of a queried point that is neither core nor known border, one of which may be a core;
- points whose id is less than that of every known core of their cluster, which may name it.

Any other point lies in groups of one cluster only, and no core of another cluster can be near it; it is not queried,
and is told as inner: a core or a border of its cluster. The trace tells after each block how many clusters are known.
"""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from densereps.functions.expr import md5_key
from densereps.operators import exact
from densereps.operators.neighbors import range_probe
from densereps.plans.lineage import cut

TRACE = "block int, queries long, known_pairs long, groups long, unknown long, clusters long, seconds double"


def anytime_blocks(
    points: DataFrame, eps: float, min_pts: int, block0: int = 256, block: int = 256, snapshot: int = 1, max_blocks: int = 10_000, seed: int = 0
) -> tuple[DataFrame, DataFrame]:
    """(id, n_eps, state, cluster), clusters equal to those of exact density clustering, and a trace.

    n_eps is null and state is inner where a point was not queried. The trace has a row every snapshot blocks and one at
    the end. max_blocks stops earlier, with the clusters known by then.
    """
    spark, began = points.sparkSession, time.time()
    points = cut(points.select("id", "x", "y").withColumn("key", md5_key("id", seed)))
    new = asked = cut(points.orderBy("key", "id").limit(block0).select("id"))
    pairs, rows, number = None, [], 0
    while True:
        found = cut(range_probe(points.join(new, "id", "left_semi"), points, eps))
        pairs = found if pairs is None else pairs.unionByName(found)
        counts = cut(pairs.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("n_eps")))
        cores = counts.filter(F.col("n_eps") >= min_pts).select("id")
        groups = pairs.join(cores.withColumnRenamed("id", "src"), "src", "left_semi")
        links = groups.join(cores.withColumnRenamed("id", "dst"), "dst", "left_semi").select("src", "dst")
        clusters = cut(exact.density_components(links, ids=cores).withColumnRenamed("component", "cluster"))
        member = cut(groups.join(clusters.withColumnRenamed("id", "src"), "src").groupBy(F.col("dst").alias("id")).agg(F.min("cluster").alias("cluster")))
        open_ = points.join(asked, "id", "left_anti").join(member, "id", "left")
        near = range_probe(open_, points.join(cores, "id", "left_semi"), 2 * eps).join(clusters.withColumnRenamed("id", "dst"), "dst")
        several = near.groupBy(F.col("src").alias("id")).agg(F.count_distinct("cluster").alias("k"))
        bare = counts.filter(F.col("n_eps") < min_pts).join(member, "id", "left_anti").select(F.col("id").alias("src"))
        beside = pairs.join(bare, "src", "left_semi").select(F.col("dst").alias("id")).distinct().withColumn("beside", F.lit(1))
        weight = F.when(F.col("k") > 1, F.col("k")).when(F.col("cluster").isNull() | F.col("beside").isNotNull() | (F.col("id") < F.col("cluster")), 1)
        useful = cut(open_.join(several, "id", "left").join(beside, "id", "left").withColumn("weight", weight).filter("weight IS NOT NULL").select("id", "key", "weight"))
        waiting = useful.count()
        last = not waiting or number >= max_blocks
        if number % snapshot == 0 or last:
            k = clusters.select("cluster").distinct().count()
            rows.append((number, asked.count(), pairs.count(), cores.count(), waiting, k, time.time() - began))
        if last:
            break
        number += 1
        new = cut(useful.orderBy(F.desc("weight"), "key", "id").limit(block).select("id"))
        asked = asked.unionByName(new)
    known = counts.join(clusters, "id", "left").withColumnRenamed("cluster", "own").join(member, "id", "left")
    state = F.when(F.col("n_eps") >= min_pts, "core").when(F.col("cluster").isNotNull(), "border").otherwise("noise")
    told = known.select("id", "n_eps", state.alias("state"), F.coalesce("own", "cluster", F.lit(-1)).alias("cluster"))
    rest = open_.select("id", F.lit(None).cast("long").alias("n_eps"), F.lit("inner").alias("state"), F.coalesce("cluster", F.lit(-1)).alias("cluster"))
    return told.unionByName(rest), spark.createDataFrame(rows, TRACE)
