"""The sample's graph on DataFrames: states, pairs kept across iterations, and what an increment changes."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from densereps.operators import exact
from densereps.operators.neighbors import coordinates, neighbor_counts, range_pairs, range_probe
from densereps.params import SsdcParams
from densereps.plans.lineage import cut


@dataclass
class GraphState:
    """sample (id, x, y), pairs (src, dst, d2) both ways, vertices (id, n_eps, state, cluster), eta."""

    sample: DataFrame
    pairs: DataFrame
    vertices: DataFrame
    eta: int
    params: SsdcParams

    @property
    def edges(self) -> DataFrame:
        return exact.edge_states(self.pairs, self.vertices)


def _vertices(pairs: DataFrame, eta: int, p: SsdcParams, counts: DataFrame | None = None, before: DataFrame | None = None) -> DataFrame:
    """States and clusters from all pairs; with before, no cluster of it parts."""
    states = cut(exact.classify(pairs, eta, counts))
    if before is None or not p.keeps_merges:
        return cut(exact.label_states(pairs, states, p.border_rule, p.weak_edges))
    cores = exact.core_clusters(pairs, states)
    merged = merge_map(before, states.join(cores, "id"))
    cores = cores.join(merged, "cluster", "left").select("id", F.coalesce("merged", "cluster").alias("cluster"))
    return cut(exact.with_borders(pairs, states, cores, p.border_rule))


def init_graph(sample: DataFrame, eta, p: SsdcParams) -> GraphState:
    """The first sample's graph; eta is a threshold, or gives one from (id, n_eps)."""
    sample = cut(sample.select("id", *coordinates(sample)))
    pairs = cut(range_pairs(sample, p.eps))
    counts = cut(neighbor_counts(pairs))
    eta = eta(counts) if callable(eta) else eta
    return GraphState(sample, pairs, _vertices(pairs, eta, p, counts), eta, p)


def demote(graph: GraphState, eta: int) -> GraphState:
    """The graph at a higher threshold. Counts are kept; all failing cores fall at once, then borders are derived."""
    counts = graph.vertices.select("id", "n_eps")
    return replace(graph, vertices=_vertices(graph.pairs, eta, graph.params, counts, graph.vertices), eta=eta)


def increment_pairs(graph: GraphState, batch: DataFrame) -> DataFrame:
    """Pairs that a batch adds: with the sample, both ways, and inside the batch. The sample is not met with itself."""
    batch = batch.select("id", *coordinates(batch))
    cross = range_probe(batch, graph.sample, graph.params.eps)
    back = cross.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "d2")
    return cross.unionByName(back).unionByName(range_pairs(batch, graph.params.eps))


def insert(graph: GraphState, batch: DataFrame) -> GraphState:
    """The graph with a batch. Pairs are appended; only counts of points that gain neighbours are added to."""
    p = graph.params
    batch = cut(batch.select("id", *coordinates(batch)))
    gained = cut(increment_pairs(graph, batch))
    old = graph.vertices.select("id", "n_eps")
    counts = cut(old.unionByName(neighbor_counts(gained)).groupBy("id").agg(F.sum("n_eps").alias("n_eps")))
    pairs = graph.pairs.unionByName(gained)
    if p.weak_edges == "connect":
        vertices = _vertices(pairs, graph.eta, p, counts)
    else:
        vertices = cut(merge_clusters(graph.vertices, cut(exact.classify(pairs, graph.eta, counts)), pairs, p))
    return replace(graph, sample=graph.sample.unionByName(batch), pairs=pairs, vertices=vertices)


def merge_clusters(before: DataFrame, states: DataFrame, pairs: DataFrame, p: SsdcParams) -> DataFrame:
    """states with cluster after points were added at the same threshold, from the clusters before.

    Cores stay cores, so only links of new cores can join clusters: components are sought on a small graph of the new
    cores and the clusters next to them, and the least id of each component renames its clusters.
    """
    known = before.filter("state = 'core'").select("id", F.col("cluster").alias("node"))
    cores = cut(
        states.filter("state = 'core'").select("id").join(known, "id", "left")
        .select("id", F.coalesce("node", "id").alias("node"), F.col("node").isNull().alias("fresh"))
    )
    fresh = cores.filter("fresh").select("id")
    near = pairs.join(fresh.withColumnRenamed("id", "src"), "src", "left_semi").select("src", "dst")
    links = near.join(cores.select(F.col("id").alias("dst"), "node"), "dst").select("src", F.col("node").alias("dst")).distinct()
    found = cut(exact.density_components(links, ids=fresh).select(F.col("id").alias("node"), "component"))
    clusters = cores.join(found, "node", "left").select("id", F.coalesce("component", "node").alias("cluster"))
    named = exact.with_borders(pairs, states, clusters, p.border_rule)
    if p.merge_on == "core":
        return named
    named = cut(named)
    side = lambda end, name, state: named.filter(state).select(F.col("id").alias(end), F.col("cluster").alias(name))
    met = near.join(side("src", "a", "state = 'core'"), "src").join(side("dst", "b", "state = 'border'"), "dst").filter("a <> b")
    one = exact.density_components(met.select(F.col("a").alias("src"), F.col("b").alias("dst")).distinct())
    return named.join(one.withColumnRenamed("id", "cluster"), "cluster", "left").select("id", "n_eps", "state", F.coalesce("component", "cluster").alias("cluster"))


def merge_map(before: DataFrame, after: DataFrame) -> DataFrame:
    """(cluster, merged): after's clusters that share an old cluster's surviving cores get the least of their ids."""
    kept = before.filter("cluster >= 0").select("id", F.col("cluster").alias("old"))
    now = after.filter("state = 'core' AND cluster >= 0").select("id", "cluster")
    both = kept.join(now, "id").select("old", "cluster").distinct()
    first = both.groupBy("old").agg(F.min("cluster").alias("first"))
    links = both.join(first, "old").select(F.col("cluster").alias("src"), F.col("first").alias("dst"))
    return exact.density_components(links).select(F.col("id").alias("cluster"), F.col("component").alias("merged"))


def transitions(before: DataFrame, after: DataFrame) -> DataFrame:
    """(old_state, new_state, n) of the points of either version; a point not there is unknown."""
    a, b = before.select("id", F.col("state").alias("o")), after.select("id", F.col("state").alias("w"))
    met = a.join(b, "id", "full_outer").select(F.coalesce("o", F.lit("unknown")).alias("old_state"), F.coalesce("w", F.lit("unknown")).alias("new_state"))
    return met.groupBy("old_state", "new_state").agg(F.count(F.lit(1)).alias("n"))


def promotions(before: DataFrame, after: DataFrame) -> DataFrame:
    """The transitions up: noise to border or core, border to core."""
    up = "(old_state = 'noise' AND new_state IN ('border', 'core')) OR (old_state = 'border' AND new_state = 'core')"
    return transitions(before, after).filter(up)


def cluster_events(before: DataFrame, after: DataFrame) -> DataFrame:
    """(event, n): clusters that are new, were carried on, came of a merge; old ones that split or vanished.

    Clusters meet through the points they share, whatever their ids.
    """
    a = before.filter("cluster >= 0").select("id", F.col("cluster").alias("old"))
    b = after.filter("cluster >= 0").select("id", F.col("cluster").alias("new"))
    met = a.join(b, "id").select("old", "new").distinct()
    into = b.select("new").distinct().join(met.groupBy("new").agg(F.count(F.lit(1)).alias("n_old")), "new", "left")
    from_ = a.select("old").distinct().join(met.groupBy("old").agg(F.count(F.lit(1)).alias("n_new")), "old", "left")
    kinds = into.select(F.when(F.col("n_old").isNull(), "new").when(F.col("n_old") > 1, "merge").otherwise("carried").alias("event")).unionByName(
        from_.select(F.when(F.col("n_new").isNull(), "vanished").when(F.col("n_new") > 1, "split").alias("event")).filter("event IS NOT NULL")
    )
    return kinds.groupBy("event").agg(F.count(F.lit(1)).alias("n"))


def state_transitions(versions: DataFrame) -> DataFrame:
    """(iteration, old_state, new_state, n) from rows (id, iteration, state)."""
    lagged = versions.withColumn("old_state", F.lag("state", 1, "unknown").over(W.partitionBy("id").orderBy("iteration")))
    return lagged.groupBy("iteration", "old_state", F.col("state").alias("new_state")).agg(F.count(F.lit(1)).alias("n"))
