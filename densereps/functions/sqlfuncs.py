"""SQL names for the functions: a distance over Arrow batches, neighbour cells as a table function, an aggregate."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from densereps.operators.kernel import mutual_information, nearest


def distance_udf():
    """Euclidean distance of two vectors, a batch at a time."""

    def run(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([float(np.linalg.norm(np.asarray(x) - np.asarray(y))) for x, y in zip(a, b, strict=True)])

    return F.pandas_udf(run, "double")


def nmi_udaf():
    """Normalised mutual information of two label columns, for groups that fit a task."""

    def run(a: pd.Series, b: pd.Series) -> float:
        return round(mutual_information(a.to_numpy(), b.to_numpy()), 6)

    run.__annotations__ = {"a": pd.Series, "b": pd.Series, "return": float}
    return F.pandas_udf(run, "double")


class GridCells:
    """The 3 x 3 cells of side eps around a point."""

    def eval(self, x: int, y: int, eps: int):
        for i in (-1, 0, 1):
            for j in (-1, 0, 1):
                yield x // eps + i, y // eps + j


def register(spark: SparkSession, reps: list[tuple[int, int, float, float]] | None = None) -> None:
    """ds_distance(a, b), grid_cells(x, y, eps), and ds_label(x, y) for representatives (id, cluster, x, y)."""
    spark.udf.register("ds_distance", distance_udf())
    spark.udtf.register("grid_cells", F.udtf(GridCells, returnType="cx long, cy long"))
    if reps is not None:
        ids, clusters, xs = np.array([r[0] for r in reps]), np.array([r[1] for r in reps]), np.array([r[2:] for r in reps], float)

        def label(x: pd.Series, y: pd.Series) -> pd.Series:
            return pd.Series(nearest(np.stack([x, y], axis=1), xs, ids, clusters))

        spark.udf.register("ds_label", F.pandas_udf(label, "long"))
