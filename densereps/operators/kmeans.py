"""K-means by Lloyd's steps on DataFrames, and as many runs at once on arrays."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from densereps.operators.labeling import label_nearest


def farthest_first(points: DataFrame, k: int) -> list[tuple[int, float, float]]:
    """(cluster, x, y) of k seeds: the least id, then each time the point farthest from those chosen (least id on ties)."""
    seeds: list[tuple[float, float]] = []
    for _ in range(k):
        if not seeds:
            row = points.orderBy("id").select("x", "y").first()
        else:
            apart = [((F.col("x") - x) ** 2 + (F.col("y") - y) ** 2) for x, y in seeds]
            far = F.least(*apart) if len(apart) > 1 else apart[0]
            row = points.agg(F.max_by(F.struct("x", "y"), F.struct(far, -F.col("id"))).alias("p")).first()["p"]
        if row is None:
            break
        seeds.append((float(row[0]), float(row[1])))
    return [(i, x, y) for i, (x, y) in enumerate(seeds)]


def centers_frame(points: DataFrame, centers: list[tuple[int, float, float]]) -> DataFrame:
    return points.sparkSession.createDataFrame([(i, i, x, y) for i, x, y in centers], "id long, cluster long, x double, y double")


def lloyd_step(points: DataFrame, centers: DataFrame) -> DataFrame:
    """(cluster, n, x, y): means of the points nearest to each centre; sums are combined before the shuffle."""
    labelled = label_nearest(points, centers)
    return labelled.groupBy("cluster").agg(F.count(F.lit(1)).alias("n"), F.avg("x").alias("x"), F.avg("y").alias("y"))


def kmeans(points: DataFrame, k: int, iterations: int = 20, tolerance: float = 1e-6) -> tuple[DataFrame, list[tuple[int, float, float]]]:
    """points with cluster, and the centres (cluster, x, y); an empty cluster keeps its centre."""
    centers = farthest_first(points, k)
    for _ in range(iterations):
        moved = {r["cluster"]: (r["x"], r["y"]) for r in lloyd_step(points, centers_frame(points, centers)).collect()}  # k rows
        new = [(i, *moved.get(i, (x, y))) for i, x, y in centers]
        shift = max((abs(a[1] - b[1]) + abs(a[2] - b[2]) for a, b in zip(new, centers, strict=True)), default=0)
        centers = new
        if shift <= tolerance:
            break
    return label_nearest(points, centers_frame(points, centers)), centers


def spark_ml_kmeans(points: DataFrame, k: int, seed: int = 0) -> DataFrame:
    """The library's K-means on the same points, for comparison."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.feature import VectorAssembler

    rows = VectorAssembler(inputCols=["x", "y"], outputCol="features").transform(points)
    return KMeans(k=k, seed=seed).fit(rows).transform(rows).withColumn("cluster", F.col("prediction").cast("long")).drop("features", "prediction")


def local_kmeans(xs: np.ndarray, k: int, rng: np.random.Generator, iterations: int = 50) -> tuple[np.ndarray, np.ndarray]:
    """(centres, labels) of a small array, seeded by squared distance."""
    xs = xs.astype(np.float64)
    centers = [xs[rng.integers(len(xs))]]
    d2 = ((xs - centers[0]) ** 2).sum(axis=1)
    for _ in range(1, k):
        centers.append(xs[rng.choice(len(xs), p=d2 / d2.sum())] if d2.sum() > 0 else xs[rng.integers(len(xs))])
        d2 = np.minimum(d2, ((xs - centers[-1]) ** 2).sum(axis=1))
    c = np.array(centers)
    label = np.zeros(len(xs), np.int64)
    for _ in range(iterations):
        far = (xs * xs).sum(axis=1)[:, None] + (c * c).sum(axis=1)[None, :] - 2 * xs @ c.T
        new = far.argmin(axis=1)
        if (new == label).all() and _:
            break
        label = new
        for j in range(k):
            if (label == j).any():
                c[j] = xs[label == j].mean(axis=0)
    return c, label
