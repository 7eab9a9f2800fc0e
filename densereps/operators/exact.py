"""Exact density clustering as set operations: counts, cores, components of cores, borders by a fixed rule."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from densereps.operators.components import connected_components
from densereps.operators.neighbors import coordinates, neighbor_counts, range_pairs, range_probe
from densereps.plans.lineage import cut

#: Links up to which components are found by union-find on the driver; beyond it by star contraction.
MAX_LOCAL_LINKS = 200_000


def density_components(links: DataFrame, method: str = "auto", ids: DataFrame | None = None) -> DataFrame:
    """(id, component): least id reached by links (src, dst). method: auto, local or star; ids: nodes to include."""
    if ids is not None:
        links = links.select("src", "dst").unionByName(ids.select(F.col("id").alias("src"), F.col("id").alias("dst")))
    once = links.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).distinct()
    if method == "star":
        return connected_components(once)
    once = cut(once)
    if once.count() > MAX_LOCAL_LINKS:
        if method == "local":
            raise ValueError("too many links for the driver")
        return connected_components(once)
    up: dict[int, int] = {}

    def root(i: int) -> int:
        while up.setdefault(i, i) != i:
            up[i] = i = up[up[i]]
        return i

    for a, b in once.collect():  # at most MAX_LOCAL_LINKS
        ra, rb = root(a), root(b)
        if ra != rb:
            up[max(ra, rb)] = min(ra, rb)
    return links.sparkSession.createDataFrame([(i, root(i)) for i in list(up)], "id long, component long")


def classify(pairs: DataFrame, min_pts: int, counts: DataFrame | None = None) -> DataFrame:
    """(id, n_eps, state): core with at least min_pts neighbours, itself among them; border next to a core; noise."""
    counts = neighbor_counts(pairs) if counts is None else counts
    cores = counts.filter(F.col("n_eps") >= min_pts).select("id")
    near = pairs.join(cores, pairs["dst"] == cores["id"], "left_semi").select(F.col("src").alias("id")).distinct()
    return counts.join(near.withColumn("touched", F.lit(True)), "id", "left").select(
        "id", "n_eps",
        F.when(F.col("n_eps") >= min_pts, "core").when(F.col("touched"), "border").otherwise("noise").alias("state"),
    )


def direct_reach(pairs: DataFrame, states: DataFrame) -> DataFrame:
    """(core, reached): what a core point reaches directly."""
    cores = states.filter("state = 'core'").select("id")
    return pairs.join(cores, pairs["src"] == cores["id"], "left_semi").select(F.col("src").alias("core"), F.col("dst").alias("reached"))


def edge_states(pairs: DataFrame, states: DataFrame) -> DataFrame:
    """(src, dst, state), src < dst: yes between cores, weak with one, no without."""
    core = states.select("id", (F.col("state") == "core").alias("core"))
    a, b = core.select(F.col("id").alias("src"), F.col("core").alias("ca")), core.select(F.col("id").alias("dst"), F.col("core").alias("cb"))
    met = pairs.filter("src < dst").select("src", "dst").join(a, "src").join(b, "dst")
    return met.select(
        "src", "dst", F.when(F.col("ca") & F.col("cb"), "yes").when(F.col("ca") | F.col("cb"), "weak").otherwise("no").alias("state")
    )


def _sides(points: DataFrame, states: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The points (id, x, y) that are cores, and the others."""
    placed = cut(points.select("id", "x", "y").join(states.select("id", (F.col("state") == "core").alias("core")), "id"))
    return placed.filter("core").drop("core"), placed.filter("NOT core").drop("core")


def reach_of(points: DataFrame, states: DataFrame, eps: float) -> DataFrame:
    """direct_reach() from points in the plane: pairs are met once, as they go out, and neither kept nor joined."""
    cores, _ = _sides(points, states)
    return range_probe(cores, points, eps).select(F.col("src").alias("core"), F.col("dst").alias("reached"))


def _loose_edges(cores: DataFrame, loose: DataFrame, eps: float) -> DataFrame:
    """edge_states() of the pairs with one core or none; a point that is no core has fewer than min_pts neighbours."""
    weak = range_probe(loose, cores, eps).select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), F.lit("weak").alias("state"))
    return weak.unionByName(range_probe(loose, loose, eps).filter("src < dst").select("src", "dst", F.lit("no").alias("state")))


def edges_of(points: DataFrame, states: DataFrame, eps: float) -> DataFrame:
    """edge_states() from points in the plane: pairs are met once, as they go out, and neither kept nor joined."""
    cores, loose = _sides(points, states)
    return range_probe(cores, cores, eps).filter("src < dst").select("src", "dst", F.lit("yes").alias("state")).unionByName(_loose_edges(cores, loose, eps))


def edge_state_counts(points: DataFrame, states: DataFrame, eps: float) -> DataFrame:
    """(state, n) of edge_states(), without pairs of cores: what the neighbour counts leave beside the others is yes."""
    met = _loose_edges(*_sides(points, states), eps).groupBy("state").agg(F.count(F.lit(1)).alias("n"))
    every = states.agg(F.coalesce(F.sum(F.col("n_eps") - 1), F.lit(0)).alias("ends")).withColumn("every", F.expr("ends div 2"))
    rest = met.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("known")).join(every, F.lit(True))  # a row each
    yes = rest.select(F.lit("yes").alias("state"), (F.col("every") - F.col("known")).alias("n")).filter("n > 0")
    return met.unionByName(yes)


def core_links(pairs: DataFrame, states: DataFrame) -> DataFrame:
    """(src, dst), src < dst, of pairs of cores."""
    return edge_states(pairs, states).filter("state = 'yes'").select("src", "dst")


def attach_borders(pairs: DataFrame, states: DataFrame, clusters: DataFrame, rule: str = "min_cluster") -> DataFrame:
    """(id, cluster) of border points. rule: the least cluster next to them, that of the nearest core, or of the least core id."""
    borders = states.filter("state = 'border'").select(F.col("id").alias("src"))
    met = pairs.join(borders, "src", "left_semi").join(clusters.select(F.col("id").alias("dst"), "cluster"), "dst")
    chosen = {
        "min_cluster": F.min("cluster"),
        "nearest_core": F.min_by("cluster", F.struct("d2", "dst")),
        "lowest_core_id": F.min_by("cluster", "dst"),
    }[rule]
    return met.groupBy(F.col("src").alias("id")).agg(chosen.alias("cluster"))


def core_clusters(pairs: DataFrame, states: DataFrame, method: str = "auto") -> DataFrame:
    """(id, cluster) of cores: the least core id of the component."""
    return density_components(core_links(pairs, states), method, states.filter("state = 'core'").select("id")).withColumnRenamed("component", "cluster")


def with_borders(pairs: DataFrame, states: DataFrame, clusters: DataFrame, border_rule: str = "min_cluster") -> DataFrame:
    """states with cluster from those of the cores; -1 for noise."""
    named = clusters.unionByName(attach_borders(pairs, states, clusters, border_rule))
    return states.join(named, "id", "left").withColumn("cluster", F.coalesce("cluster", F.lit(-1)))


def label_states(pairs: DataFrame, states: DataFrame, border_rule: str = "min_cluster", weak_edges: str = "attach", method: str = "auto") -> DataFrame:
    """states with cluster: the least core id of the component, -1 for noise."""
    if weak_edges == "attach":
        return with_borders(pairs, states, core_clusters(pairs, states, method), border_rule)
    cores = states.filter("state = 'core'").select("id")
    kept = edge_states(pairs, states).filter("state <> 'no'").select("src", "dst")
    found = density_components(kept, method, cores)
    least = found.join(cores, "id", "left_semi").groupBy("component").agg(F.min("id").alias("cluster"))
    named = found.join(least, "component").select("id", "cluster")
    return states.join(named, "id", "left").withColumn("cluster", F.coalesce("cluster", F.lit(-1)))


def exact_density(
    points: DataFrame, eps: float, min_pts: int, border_rule: str = "min_cluster", weak_edges: str = "attach", method: str = "auto",
    pairs: DataFrame | None = None, halo: bool = False,
) -> DataFrame:
    """(id, n_eps, state, cluster) of all points (id, x, y).

    In the plane, clusters by cores go by tiles, which form no pairs of cores (halo.py); halo asks for them, and for an error
    where they don't serve. Links over borders ("connect") take all pairs; pass pairs to cluster points of another kind.
    """
    tiles = pairs is None and weak_edges == "attach" and coordinates(points) == ["x", "y"]
    if halo and not tiles:
        raise ValueError("tiles cluster points in the plane by their cores")
    if tiles:
        from densereps.operators.halo import exact_density_tiles

        return exact_density_tiles(points, eps, min_pts, border_rule=border_rule)
    near = cut(range_pairs(points, eps)) if pairs is None else pairs
    return label_states(near, cut(classify(near, min_pts)), border_rule, weak_edges, method)


def visit_transitions(labels: DataFrame) -> DataFrame:
    """(step, n): the states that points pass when they are visited in the order of their ids, from (id, state, cluster).

    A cluster is expanded when its least core is visited, which gives it its id; a border visited before is noise till then.
    """
    early = F.col("id") < F.col("cluster")
    steps = (
        F.when(F.col("state") == "core", F.array(F.lit("unknown>core"))).when(F.col("state") == "noise", F.array(F.lit("unknown>noise")))
        .when(early, F.array(F.lit("unknown>noise"), F.lit("noise>border"))).otherwise(F.array(F.lit("unknown>border")))
    )
    return labels.select(F.explode(steps).alias("step")).groupBy("step").agg(F.count(F.lit(1)).alias("n"))


def density_graph(points: DataFrame, eps: float, min_pts: int) -> tuple[DataFrame, DataFrame]:
    """Vertices (id, n_eps, state) and edges (src, dst, state) of all points."""
    near = cut(range_pairs(points, eps))
    states = cut(classify(near, min_pts))
    return states, edge_states(near, states)
