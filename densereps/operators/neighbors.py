"""Range queries as joins: all pairs of points at most eps apart, in 2-D grids and in high dimension."""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from densereps.functions.expr import cell, l2_squared, squared_2d
from densereps.operators import kernel
from densereps.plans.lineage import cut


STRATEGIES = ("auto", "grid", "brute", "pivot", "lsh")
#: Vectors that meet one another in one block.
BLOCK_ROWS = 1 << 13


def coordinates(points: DataFrame) -> list[str]:
    """The columns that hold a point's place."""
    return ["vec"] if "vec" in points.columns else ["x", "y"]


def choose_strategy(points: DataFrame) -> str:
    """grid for points in the plane; pivots for vectors."""
    return "pivot" if coordinates(points) == ["vec"] else "grid"


def _around(df: DataFrame, eps: float) -> DataFrame:
    """Rows copied to the 3 x 3 cells around their own."""
    step = F.array(*[F.lit(i) for i in (-1, 0, 1)])
    return (
        df.withColumn("cx", cell("x", eps)).withColumn("cy", cell("y", eps))
        .withColumn("dx", F.explode(step)).withColumn("dy", F.explode(step))
        .withColumn("cx", F.col("cx") + F.col("dx")).withColumn("cy", F.col("cy") + F.col("dy")).drop("dx", "dy")
    )


def range_probe(probe: DataFrame, reference: DataFrame, eps: float, strategy: str = "auto") -> DataFrame:
    """(src, dst, d2): probe points with the reference points at most eps away.

    Points are (id, x, y) or (id, vec). grid: an equi-join on cells of side eps, which AQE may split where a cell is hot.
    brute: each pair, the probe broadcast in pieces, for tests. pivot: blocks of vectors by their distance to a pivot. lsh:
    approximate, for vectors; opt-in. auto: grid in the plane, pivot for vectors.
    """
    if strategy not in STRATEGIES:
        raise ValueError(f"strategy is one of {STRATEGIES}")
    strategy = choose_strategy(probe) if strategy == "auto" else strategy
    if (coordinates(probe) == ["vec"]) != (strategy in ("pivot", "lsh")):
        raise ValueError(f"{strategy} is not for points by {coordinates(probe)}")
    if strategy == "pivot":
        return pivot_probe(probe, reference, eps)
    if strategy == "lsh":
        return lsh_pairs(reference, eps).join(probe.select(F.col("id").alias("src")), "src", "left_semi").select("src", "dst", "d2")
    a = probe.select(F.col("id").alias("src"), F.col("x").alias("ax"), F.col("y").alias("ay"))
    b = reference.select(F.col("id").alias("dst"), F.col("x").alias("bx"), F.col("y").alias("by"))
    d2 = squared_2d(F.col("ax"), F.col("ay"), F.col("bx"), F.col("by"))
    if strategy == "brute":
        pieces = max(1, -(-a.count() // 10_000))  # each small enough to be broadcast
        part = lambda k: a.filter(F.pmod(F.xxhash64("src"), F.lit(pieces)) == k) if pieces > 1 else a
        met = reduce(DataFrame.unionByName, [b.join(F.broadcast(part(k)), d2 <= F.lit(eps * eps)) for k in range(pieces)])
    else:
        near = _around(a.withColumnRenamed("ax", "x").withColumnRenamed("ay", "y"), eps)
        near = near.withColumnRenamed("x", "ax").withColumnRenamed("y", "ay")
        homes = b.withColumn("cx", cell("bx", eps)).withColumn("cy", cell("by", eps))
        met = near.join(homes, ["cx", "cy"]).filter(d2 <= F.lit(eps * eps))
    return met.select("src", "dst", d2.alias("d2"))


def range_pairs(points: DataFrame, eps: float, strategy: str = "auto", include_self: bool = True) -> DataFrame:
    """All ordered pairs of points at most eps apart."""
    pairs = range_probe(points, points, eps, strategy)
    return pairs if include_self else pairs.filter("src <> dst")


def neighbor_counts(pairs: DataFrame) -> DataFrame:
    return pairs.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("n_eps"))


def pivot_probe(probe: DataFrame, reference: DataFrame, eps: float, rows: int = BLOCK_ROWS) -> DataFrame:
    """(src, dst, d2) for points (id, vec) of any dimension, exact.

    The distance to a pivot parts the reference into blocks of about that many rows. A probe point meets only the blocks
    whose distances come within eps of its own, as the triangle inequality allows, in pieces of about as many rows;
    a block and a piece meet as matrices.
    """
    spark = probe.sparkSession
    pivot = [r["vec"] for r in reference.orderBy(F.md5(F.col("id").cast("string").cast("binary"))).limit(1).collect()]
    if not pivot:
        return spark.createDataFrame([], "src long, dst long, d2 double")
    n, m = reference.count(), max(1, -(-probe.count() // rows))
    far = F.sqrt(l2_squared(F.col("vec"), F.array(*[F.lit(float(v)) for v in pivot[0]])))
    b = cut(reference.select("id", "vec", far.alias("far")))
    k = max(1, -(-n // rows))
    cuts = sorted(set(b.agg(F.percentile_approx("far", [i / k for i in range(1, k)], 10_000)).first()[0])) if k > 1 else []
    low, high = [-math.inf, *cuts], [*cuts, math.inf]
    b = b.withColumn("block", F.size(F.filter(F.array(*map(F.lit, cuts)), lambda c: c <= F.col("far"))) if cuts else F.lit(0))
    bounds = F.array(*[F.struct(F.lit(i).alias("block"), F.lit(x).alias("low"), F.lit(y).alias("high")) for i, (x, y) in enumerate(zip(low, high, strict=True))])
    slack = eps * (1 + 1e-9)
    near = F.filter(bounds, lambda z: (z["low"] - F.lit(slack) <= F.col("far")) & (F.col("far") <= z["high"] + F.lit(slack)))
    a = probe.select("id", "vec", far.alias("far"), F.pmod(F.xxhash64("id"), F.lit(m)).cast("long").alias("piece"))
    a = a.select("id", "vec", "piece", F.explode(near["block"]).alias("block"))
    b = b.select(F.col("id").alias("to"), F.col("vec").alias("at"), "block", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(m - 1).cast("long"))).alias("piece"))

    def meet(left: pa.Table, right: pa.Table) -> pa.Table:
        found = {"src": pa.array([], pa.int64()), "dst": pa.array([], pa.int64()), "d2": pa.array([], pa.float64())}
        if len(left) and len(right):
            xs, ys = (np.stack(c.combine_chunks().to_numpy(zero_copy_only=False)).astype(float) for c in (left.column("vec"), right.column("at")))
            i, j = kernel.all_near(xs, ys, eps)
            found = {"src": left.column("id").to_numpy()[i], "dst": right.column("to").to_numpy()[j], "d2": kernel.squares(xs, ys, i, j)}
        return pa.table(found, pa.schema([("src", pa.int64()), ("dst", pa.int64()), ("d2", pa.float64())]))

    return a.groupBy("block", "piece").cogroup(b.groupBy("block", "piece")).applyInArrow(meet, "src long, dst long, d2 double")


def pivot_pairs(points: DataFrame, eps: float, rows: int = BLOCK_ROWS) -> DataFrame:
    """All ordered pairs of points (id, vec) at most eps apart."""
    return pivot_probe(points, points, eps, rows)


def lsh_pairs(points: DataFrame, eps: float, n_tables: int = 8, n_bits: int = 6, seed: int = 0) -> DataFrame:
    """Approximate pairs for points (id, vec): those that share a bucket of shifted random projections in steps of 4 eps; opt-in."""
    width = points.selectExpr("max(size(vec)) AS d").first()["d"] or 0
    rng = np.random.default_rng(seed)
    planes, offsets = rng.normal(size=(n_tables * n_bits, width)), rng.random(n_tables * n_bits)

    def keys(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            vec = np.stack(pdf["vec"].to_numpy()) if len(pdf) else np.zeros((0, width))
            cells = np.floor(vec @ planes.T / (4 * eps) + offsets).astype(np.int64).reshape(len(pdf), n_tables, n_bits)
            for t in range(n_tables):
                yield pd.DataFrame({"id": pdf["id"], "key": [f"{t}:{','.join(map(str, c))}" for c in cells[:, t].tolist()]})

    buckets = points.select("id", "vec").mapInPandas(keys, "id long, key string")
    met = buckets.withColumnRenamed("id", "src").join(buckets.withColumnRenamed("id", "dst"), "key").select("src", "dst").distinct()
    a, b = points.select(F.col("id").alias("src"), F.col("vec").alias("va")), points.select(F.col("id").alias("dst"), F.col("vec").alias("vb"))
    return met.join(a, "src").join(b, "dst").withColumn("d2", l2_squared("va", "vb")).filter(F.col("d2") <= eps * eps).select("src", "dst", "d2")


def k_nearest(points: DataFrame, k: int, side: float) -> DataFrame:
    """(id, rank, neighbor, d2): the k nearest others of each point, or all others where there are fewer.

    Cells of that side serve the points that have k neighbours within it; for the others the side is doubled until
    all have them.
    """
    points = points.select("id", "x", "y")
    need = min(k, points.count() - 1)
    open_, parts = points, []
    while True:
        pairs = range_probe(open_, points, side).filter("src <> dst")
        ranked = pairs.withColumn("rank", F.row_number().over(W.partitionBy("src").orderBy("d2", "dst"))).filter(F.col("rank") <= k)
        found = cut(ranked.withColumn("n", F.count(F.lit(1)).over(W.partitionBy("src"))).filter(F.col("n") >= need))
        parts.append(found.select(F.col("src").alias("id"), "rank", F.col("dst").alias("neighbor"), "d2"))
        open_ = cut(open_.join(found.select(F.col("src").alias("id")).distinct(), "id", "left_anti")) if need > 0 else open_.limit(0)
        if open_.isEmpty():
            return reduce(DataFrame.unionByName, parts)
        side *= 2


def k_distance(points: DataFrame, k: int, side: float) -> DataFrame:
    """(id, d2) of the k-th nearest other point, for choosing eps; cells start with that side."""
    return k_nearest(points, k, side).filter(F.col("rank") == k).select("id", "d2")


def cell_candidates(points: DataFrame, eps: float) -> DataFrame:
    """(src, dst, d2): what the cell join meets, before the distance is checked."""
    a = _around(points.select("id", "x", "y"), eps).withColumnRenamed("id", "src")
    b = points.select(F.col("id").alias("dst"), F.col("x").alias("bx"), F.col("y").alias("by")).withColumn("cx", cell("bx", eps)).withColumn("cy", cell("by", eps))
    return a.join(b, ["cx", "cy"]).select("src", "dst", squared_2d(F.col("x"), F.col("y"), F.col("bx"), F.col("by")).alias("d2"))


def candidate_ratio(points: DataFrame, eps: float) -> DataFrame:
    """(candidates, pairs): what the cell join meets and what passes the distance."""
    near = F.col("d2") <= F.lit(eps * eps)
    return cell_candidates(points, eps).agg(F.count(F.lit(1)).alias("candidates"), F.sum(near.cast("long")).alias("pairs"))
