"""Labels by the nearest representative."""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from densereps.functions.expr import cell, squared_2d
from densereps.operators import kernel
from densereps.plans.broadcasts import fits
from densereps.plans.lineage import cut, stored

#: Representatives that one constant, or one block table, may hold.
MAX_ARRAY, MAX_BLOCK = 50, 200_000


def label_nearest(points: DataFrame, reps: DataFrame, mode: str = "auto", max_distance: float | None = None, reach: float | None = None) -> DataFrame:
    """points (id, x, y, ...) or (id, vec, ...) with cluster: that of the nearest of reps (id, cluster, and x, y or vec).

    Ties go to the smaller representative's id; without representatives, or beyond max_distance, -1. array: a pure
    projection against one constant; arrow: blocks of a broadcast table; grid: growing cells, for any number of
    representatives; join: all pairs, for small inputs and tests. auto picks by size. reach: a distance at which most
    points have a representative, where cells begin.
    """
    if "vec" in points.columns:
        return _label_vectors(points, reps, max_distance)
    reps = reps.select(F.col("id").alias("rep_id"), F.col("cluster").alias("rep_cluster"), F.col("x").alias("rx"), F.col("y").alias("ry"))
    if mode == "auto":
        mode = "array" if fits(reps, MAX_ARRAY) else "arrow" if fits(reps, MAX_BLOCK) else "grid"
    limit = F.lit(True) if max_distance is None else F.col("nearest.d2") <= F.lit(max_distance**2)
    chosen = F.when(limit, F.coalesce("nearest.rep_cluster", F.lit(-1))).otherwise(F.lit(-1))
    d2 = lambda r: squared_2d(F.col("x"), F.col("y"), r["rx"], r["ry"]).cast("double")
    if mode == "array":
        rows = reps.orderBy("rep_id").limit(MAX_BLOCK).collect()
        if not rows:
            return points.withColumn("cluster", F.lit(-1).cast("long"))
        held = F.from_json(F.lit("[" + ",".join(f'{{"rep_id":{r[0]},"rep_cluster":{r[1]},"rx":{r[2]},"ry":{r[3]}}}' for r in rows) + "]"),
                           "array<struct<rep_id: long, rep_cluster: long, rx: double, ry: double>>")
        best = F.array_min(F.transform(held, lambda r: F.struct(d2(r).alias("d2"), r["rep_id"].alias("rep_id"), r["rep_cluster"].alias("rep_cluster"))))
        return points.withColumn("nearest", best).withColumn("cluster", chosen).drop("nearest")
    if mode == "arrow":
        if not fits(reps, MAX_BLOCK):
            raise ValueError("too many representatives for one table")
        table = reps.toPandas()
        held = points.sparkSession.sparkContext.broadcast(tuple(table[c].to_numpy() for c in ("rx", "ry", "rep_id", "rep_cluster")))

        @F.pandas_udf("long")
        def run(batches: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
            rx, ry, ids, clusters = held.value
            for x, y in batches:
                xs = np.stack([x.to_numpy(), y.to_numpy()], axis=1)
                yield pd.Series(kernel.nearest(xs, np.stack([rx, ry], axis=1), ids, clusters, max_distance, reach))

        return points.withColumn("cluster", run("x", "y"))
    if mode == "grid":
        found = _by_cells(points.select("id", "x", "y"), reps, max_distance, reach)
    else:
        met = points.select("id", "x", "y").join(F.broadcast(reps) if fits(reps, 2_000) else reps, F.lit(True))
        found = _best(met)
    return points.join(found, "id", "left").withColumn("cluster", F.when(F.col("nearest").isNull(), F.lit(-1)).otherwise(chosen)).drop("nearest")


def _best(met: DataFrame) -> DataFrame:
    near = met.withColumn("d2", squared_2d(F.col("x"), F.col("y"), F.col("rx"), F.col("ry")).cast("double"))
    return near.groupBy("id").agg(F.min(F.struct("d2", "rep_id", "rep_cluster")).alias("nearest"))


def _by_cells(points: DataFrame, reps: DataFrame, max_distance: float | None, reach: float | None) -> DataFrame:
    """(id, nearest): an equi-join on cells; points without a representative within the cells' side meet doubled cells."""
    box = reps.agg(F.count("rep_id").alias("n"), *[f(c).alias(f"{f.__name__}_{c}") for c in ("rx", "ry") for f in (F.min, F.max)]).first()
    if not box["n"]:
        return points.limit(0).select("id", F.lit(None).cast("struct<d2: double, rep_id: long, rep_cluster: long>").alias("nearest"))
    area = max(1.0, float(box["max_rx"] - box["min_rx"])) * max(1.0, float(box["max_ry"] - box["min_ry"]))
    side = max_distance or reach or max(1.0, math.sqrt(area / box["n"]))
    step, parts = F.array(*[F.lit(i) for i in (-1, 0, 1)]), []
    while True:
        spread = (
            reps.withColumn("dx", F.explode(step)).withColumn("dy", F.explode(step))
            .withColumn("cx", cell("rx", side) + F.col("dx")).withColumn("cy", cell("ry", side) + F.col("dy"))
        )
        met = points.withColumn("cx", cell("x", side)).withColumn("cy", cell("y", side)).join(spread, ["cx", "cy"])
        sure = stored(_best(met).filter(F.col("nearest.d2") <= F.lit(float(side) ** 2)))
        parts.append(sure)
        if max_distance is not None:
            break
        points = cut(points.join(sure.select("id"), "id", "left_anti"))
        if points.isEmpty():
            break
        side *= 2
    return reduce(DataFrame.unionByName, parts)


def _nearest_of(held):
    """A column function: vec to the nearest representative of a broadcast table."""

    @F.pandas_udf("d2 double, rep_id long, rep_cluster long")
    def run(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        ids, vecs, clusters = held.value
        place = np.arange(len(ids))
        for v in batches:
            xs = np.stack(v.to_numpy()).astype(float)
            at = kernel.nearest(xs, vecs, ids, place)
            yield pd.DataFrame({"d2": ((xs - vecs[at]) ** 2).sum(axis=1), "rep_id": ids[at], "rep_cluster": clusters[at]})

    return run


def _label_vectors(points: DataFrame, reps: DataFrame, max_distance: float | None) -> DataFrame:
    """points (id, vec, ...) with cluster, by blocks of a broadcast table; beyond MAX_BLOCK, table after table."""
    n = reps.count()
    tables = max(1, -(-n // MAX_BLOCK))
    context, out = points.sparkSession.sparkContext, points
    dealt = reps if tables == 1 else cut(reps.withColumn("table", F.pmod(F.xxhash64("id"), F.lit(tables))))
    best = []
    for t in range(tables):
        rows = (dealt if tables == 1 else dealt.filter(F.col("table") == t)).select("id", "cluster", "vec").toPandas()
        if not len(rows):
            continue
        held = context.broadcast((rows["id"].to_numpy(np.int64), np.stack(rows["vec"].to_numpy()).astype(float), rows["cluster"].to_numpy(np.int64)))

        name = f"__nearest_{t}"
        out = out.withColumn(name, _nearest_of(held)("vec"))
        best.append(F.col(name))
    if not best:
        return points.withColumn("cluster", F.lit(-1).cast("long"))
    near = F.least(*best) if len(best) > 1 else best[0]
    limit = F.lit(True) if max_distance is None else near["d2"] <= F.lit(float(max_distance) ** 2)
    return out.withColumn("cluster", F.when(limit, near["rep_cluster"]).otherwise(F.lit(-1))).select(*points.columns, "cluster")
