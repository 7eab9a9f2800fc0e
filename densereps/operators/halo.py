"""Exact density clustering of whole sets by tiles with a halo: near pairs never leave a task."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from densereps.functions.expr import cell
from densereps.operators import kernel
from densereps.operators.exact import density_components
from densereps.plans.lineage import cut, stored

#: Places that a tile should hold, about, and the least side of a tile in units of eps.
PLACES_A_TILE, LEAST_SIDE = 50_000, 4

ROWS = "id long, x {x}, y {y}, n_eps long, core boolean, owned boolean, node long"


def _tile(eps: float, min_pts: int, border_rule: str):
    def run(rows: pa.Table) -> pa.Table:
        get = lambda c: rows.column(c).to_numpy()
        ids, copies = get("id"), get("copies")
        xs = np.stack([get("x"), get("y")], axis=1)
        inner, owned = get("inner").astype(bool), get("owned").astype(bool)
        sure, n = np.flatnonzero(inner), np.zeros(len(ids), np.int64)  # beyond eps outside the tile, counts are not whole
        asked = sure[owned[sure] | (kernel.cell_weights(xs, eps, copies)[sure] < min_pts)]  # others' counts are not given, and they are cores
        n[asked] = kernel.near_counts(xs, eps, copies, asked)
        core = inner.copy()
        core[asked] = n[asked] >= min_pts
        kept, label = np.flatnonzero(core), np.full(len(ids), -1)
        label[kept] = kept[kernel.linked(xs[kept], eps)]
        node = kernel.canonical(ids, label, core)
        loose = np.flatnonzero(owned & ~core)  # fewer than min_pts neighbours each
        i, j = kernel.near_pairs(xs[loose], xs, eps)
        edge = core[j]
        i, j = loose[i[edge]], j[edge]
        if border_rule == "min_cluster":  # clusters have their names when tiles are linked
            met = np.unique(np.stack([i, node[j]], axis=1), axis=0)
        else:
            far = kernel.squares(xs, xs, i, j) if border_rule == "nearest_core" else np.zeros(len(i))
            by = np.lexsort((ids[j], far, i))
            one, first = np.unique(i[by], return_index=True)
            met = np.stack([one, node[j[by][first]]], axis=1)
        lone = np.setdiff1d(loose, met[:, 0])
        at = np.concatenate([kept, met[:, 0], lone])
        found = np.concatenate([node[kept], met[:, 1], np.full(len(lone), -1)])
        return pa.table({"id": ids[at], "x": xs[at, 0], "y": xs[at, 1], "n_eps": n[at], "core": core[at], "owned": owned[at], "node": found})

    return run


def exact_density_tiles(points: DataFrame, eps: float, min_pts: int, side: float | None = None, border_rule: str = "min_cluster") -> DataFrame:
    """(id, n_eps, state, cluster) for points (id, x, y), the least core id naming a cluster and -1 noise.

    Points on one place are folded. Each tile gets the places up to 2 eps around it: counts are whole up to eps around it,
    so its cores and those next to it are sure. A tile clusters its cores and names each part by its least core; parts
    of different tiles that hold one core are linked, and the linked parts' least core names the cluster. A border takes
    the least cluster next to it, or that of the core which the rule names. No pairs of cores are formed. What is shuffled is the places, with their copies at the tiles' edges.
    """
    places = cut(points.groupBy("x", "y").agg(F.min("id").alias("id"), F.count(F.lit(1)).alias("copies")))
    if side is None:
        cells = places.groupBy(cell("x", eps).alias("cx"), cell("y", eps).alias("cy")).count().agg((F.sum(F.col("count") * F.col("count")) / F.sum("count")).alias("mean")).first()["mean"] or 1.0
        side = eps * max(LEAST_SIDE, math.floor(math.sqrt(PLACES_A_TILE / cells)))
    wide = 2 * eps
    near = lambda c: F.sequence(cell(F.col(c) - F.lit(wide), side), cell(F.col(c) + F.lit(wide), side))
    dealt = places.withColumn("tx", F.explode(near("x"))).withColumn("ty", F.explode(near("y")))
    off = lambda c, t: F.greatest(F.col(t) * F.lit(side) - F.col(c), F.col(c) - (F.col(t) + 1) * F.lit(side), F.lit(0.0))
    dealt = dealt.withColumn("owned", (cell("x", side) == F.col("tx")) & (cell("y", side) == F.col("ty")))
    dealt = dealt.withColumn("inner", F.col("owned") | ((off("x", "tx") <= F.lit(eps)) & (off("y", "ty") <= F.lit(eps))))
    columns = ["id", "x", "y", "copies", "owned", "inner"]
    dealt = dealt.select("tx", "ty", *columns).repartition(int(points.sparkSession.conf.get("spark.sql.shuffle.partitions")), "tx", "ty")  # few bytes can be much work
    met = dealt.groupBy("tx", "ty").applyInArrow(lambda t: _tile(eps, min_pts, border_rule)(t.select(columns)), ROWS.format_map(dict(places.dtypes)))
    rows = stored(met)
    nodes = rows.filter("core").groupBy("id").agg(F.min("node").alias("dst"), F.collect_set("node").alias("all"))  # at most four tiles meet
    links = nodes.select(F.explode("all").alias("src"), "dst").distinct()
    names = density_components(links).select(F.col("id").alias("node"), F.col("component").alias("named"))
    labels = rows.filter("owned").join(names, "node", "left").groupBy("id").agg(
        F.min("x").alias("x"), F.min("y").alias("y"), F.max("n_eps").alias("n_eps"), F.max("core").alias("core"), F.min("named").alias("cluster")
    )
    state = F.when(F.col("core"), "core").when(F.col("cluster").isNotNull(), "border").otherwise("noise")
    named = labels.select("x", "y", "n_eps", state.alias("state"), F.coalesce("cluster", F.lit(-1)).alias("cluster"))
    return points.select("id", "x", "y").join(named, ["x", "y"]).select("id", "n_eps", "state", "cluster")
