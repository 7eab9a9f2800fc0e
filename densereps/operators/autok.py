"""K-means that chooses K on samples: the K whose centroids agree best between two samples.

For each K up to k_max, pairs of samples are clustered and their centroids matched greedily, nearest first. The mean
squared distance of matched centroids, over the mean squared distance of points to their centroids, is the K's
instability; the least one from 2 on wins, the larger K among equals, if it is below UNSTABLE; else K is 1, which
always scores low, as only the mean moves. Each clustering is the best of a few restarts.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from densereps.operators.kmeans import local_kmeans
from densereps.operators.labeling import label_nearest
from densereps.operators.sampling import take

#: Points of the pooled sample that all draws are taken from.
MAX_POOL = 20_000
#: Instability from which no K beyond 1 is taken.
UNSTABLE = 0.5
RESTARTS = 5


def best_kmeans(xs: np.ndarray, k: int, rng: np.random.Generator) -> tuple[np.ndarray, np.ndarray]:
    """The clustering of least squared distance among RESTARTS."""
    runs = [local_kmeans(xs, k, rng) for _ in range(RESTARTS)]
    return min(runs, key=lambda r: ((xs - r[0][r[1]]) ** 2).sum())


def matched_cost(a: np.ndarray, b: np.ndarray) -> float:
    """Mean squared distance of centroids matched greedily, nearest pair first."""
    d2 = ((a[:, None] - b[None]) ** 2).sum(axis=2)
    total = 0.0
    for _ in range(len(a)):
        i, j = divmod(int(d2.argmin()), d2.shape[1])
        total += d2[i, j]
        d2[i, :], d2[:, j] = np.inf, np.inf
    return total / len(a)


def autok_scores(points: DataFrame, k_max: int, sample: int = 500, n_pairs: int = 8, seed: int = 0) -> DataFrame:
    """(k, instability) for every K: one task per K and pair of samples, on a broadcast pool of bounded size."""
    spark = points.sparkSession
    pool = take(points, MAX_POOL, seed).select("x", "y").toPandas().to_numpy(np.float64)
    held = spark.sparkContext.broadcast(pool)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        xs = held.value
        for pdf in batches:
            out = []
            for k, pair in zip(pdf["k"].tolist(), pdf["pair"].tolist(), strict=True):
                rng = np.random.default_rng([seed, k, pair])
                size = min(sample, max(1, len(xs) // 2))
                if len(xs) < 2 * k:
                    continue
                order = rng.permutation(len(xs))
                parts = [xs[order[:size]], xs[order[size : 2 * size]]]
                if min(map(len, parts)) < k:
                    continue
                (ca, la), (cb, lb) = (best_kmeans(x, k, rng) for x in parts)
                spread = np.mean([((x - c[label]) ** 2).sum(axis=1).mean() for x, c, label in zip(parts, (ca, cb), (la, lb), strict=True)])
                out.append((k, matched_cost(ca, cb) / max(spread, 1e-12)))
            yield pd.DataFrame(out, columns=["k", "score"])

    work = spark.range(k_max * n_pairs).select((F.col("id") % k_max + 1).cast("int").alias("k"), F.floor(F.col("id") / k_max).cast("int").alias("pair"))
    scores = work.repartition(max(1, min(k_max * n_pairs, 64)), "k", "pair").mapInPandas(run, "k int, score double")
    return scores.groupBy("k").agg(F.round(F.avg("score"), 9).alias("instability"))


def autok(points: DataFrame, k_max: int, seed: int = 0, **options) -> tuple[int, DataFrame]:
    """(K, points with cluster) for the K with the least instability."""
    scores = autok_scores(points, k_max, seed=seed, **options)
    row = scores.filter("k > 1").agg(F.min(F.struct("instability", (-F.col("k")).alias("minus_k"))).alias("best")).first()["best"]
    k = -row["minus_k"] if row is not None and row["instability"] < UNSTABLE else 1
    pool = take(points, MAX_POOL, seed).select("x", "y").toPandas().to_numpy(np.float64)
    centers, _ = best_kmeans(pool, k, np.random.default_rng(seed))
    reps = points.sparkSession.createDataFrame([(i, i, float(x), float(y)) for i, (x, y) in enumerate(centers)], "id long, cluster long, x double, y double")
    return k, label_nearest(points, reps)
