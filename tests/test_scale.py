"""Queries where a neighbourhood holds many points: what they must not hold, on small tables."""

import duckdb
import numpy as np
import pytest

from pyspark.sql import functions as F

from densereps import workloads
from densereps.operators import exact, halo, kernel, neighbors
from densereps.params import SsdcParams
from densereps.queries import ORACLES, QUERIES
from densereps.streaming import streams

#: Queries that form no pairs of cores, or meet them only as they go out.
WITHOUT_PAIRS = [
    "anti_noise",
    "border_lowest_core",
    "border_nearest",
    "contingency_grouping_sets",
    "core_components",
    "density_quartiles",
    "direct_reach",
    "edge_states",
    "exact_density_blobs31",
    "exact_visit_transitions",
    "oracle_graph_edges",
    "pair_metrics",
    "point_states",
    "representatives",
    "reps_by_tau",
    "state_cluster_cube",
]


def same_as_sql(df, name, sf_dir):
    con = duckdb.connect()
    for t in ("customer", "part", "events"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf_dir}/{t}.parquet')")
    want = con.execute(ORACLES[name])
    columns = [c[0] for c in want.description]
    normal = lambda rows: sorted(tuple(round(v, 6) if isinstance(v, float) else str(v) for v in r) for r in rows)
    assert normal(df.select(columns).collect()) == normal(want.fetchall())


@pytest.mark.parametrize("name", WITHOUT_PAIRS)
def test_all_pairs_are_never_kept(spark, sf_dir, monkeypatch, name):
    def refuse(*_, **__):
        raise AssertionError("all pairs are asked for")

    for module in (exact, neighbors):
        monkeypatch.setattr(module, "range_pairs", refuse)
    same_as_sql(QUERIES[name](spark, sf_dir), name, sf_dir)


def test_similarity_join_expands_no_pairs(spark, sf_dir, monkeypatch):
    """A row for each point with its class and number of links; they agree with the pairs."""
    points = QUERIES["scan_shapes_small"](spark, sf_dir).toPandas()
    i, j = kernel.near_pairs(points[["x", "y"]].to_numpy(), points[["x", "y"]].to_numpy(), 150)
    label = kernel.components(np.arange(len(points)), i, j)
    ids = points["id"].to_numpy()
    want = {int(ids[k]): (int(ids[label == label[k]].min()), int((i == k).sum()) - 1) for k in range(len(ids))}
    for module in (exact, neighbors):
        monkeypatch.setattr(module, "range_pairs", None)
    assert {r.id: (r.component, r.n_links) for r in QUERIES["eps_pairs"](spark, sf_dir).collect()} == want


def test_stream_without_copies_is_not_collected(spark, sf_dir, monkeypatch):
    monkeypatch.setattr(streams, "drain", None)
    same_as_sql(QUERIES["stream_deduplicated"](spark, sf_dir), "stream_deduplicated", sf_dir)


def test_dense_points_without_their_pairs(monkeypatch):
    """Counts, components and the loop of a dense set in the plane, with pairs only where a point is no core."""
    xs = np.stack(np.meshgrid(np.arange(40), np.arange(40)), axis=-1).reshape(-1, 2)
    xs[800:] += 100
    i, j = kernel.near_pairs(xs, xs, 15)
    counts, label = np.bincount(i), kernel.components(np.arange(len(xs)), i, j)
    most, chunks = [0], kernel.near_chunks

    def counted(a, b, eps):
        for i, j in chunks(a, b, eps):
            most[0] += len(i)
            yield i, j

    monkeypatch.setattr(kernel, "near_chunks", counted)
    assert (kernel.near_counts(xs, 15) == counts).all() and (kernel.linked(xs, 15) == label).all()
    n, state, cluster = kernel.exact(np.arange(len(xs)), xs, SsdcParams(eps=15, min_pts=5, gamma=1, beta=1))
    assert (n == counts).all() and (state == "core").all() and (cluster == label).all() and most[0] == 0


def test_labels_by_cells_can_be_written(spark, sf_dir, tmp_path):
    QUERIES["nearest_rep_labels_cells"](spark, sf_dir.replace("0.001", "0.01")).write.parquet(str(tmp_path / "out"))
    assert spark.read.parquet(str(tmp_path / "out")).count() == 1500


def test_counts_of_rows_too_far_apart_for_a_table(monkeypatch):
    """Dense rows that span more than one table are counted by several, not by their pairs."""
    xs = np.random.default_rng(0).integers(0, (600, 80), (9000, 2))
    want = kernel.near_counts(xs, 12)
    far = xs + np.where(xs[:, :1] >= 300, 10_000_000, 0)
    at = np.flatnonzero(xs[:, 0] % 3 == 0)
    apart = np.where(xs[:, 0] >= 300, kernel.near_counts(xs, 12, (xs[:, 0] >= 300).astype(int)), kernel.near_counts(xs, 12, (xs[:, 0] < 300).astype(int)))
    monkeypatch.setattr(kernel, "near_chunks", None)
    assert (kernel.near_counts(far, 12) == apart).all() and (kernel.near_counts(far, 12, at=at) == apart[at]).all()
    monkeypatch.setattr(kernel, "MAX_TABLE", 20_000)
    assert (kernel.near_counts(xs, 12) == want).all()


def test_tiles_of_few_rows_are_dealt_to_all_cores(spark, sf_dir):
    """Many points on few places are little to shuffle and much to count: tiles keep their own partitions."""
    spark.conf.set("spark.sql.shuffle.partitions", "7")
    try:
        parts = []
        stored = halo.stored
        halo.stored = lambda df: parts.append(df.rdd.getNumPartitions()) or stored(df)
        QUERIES["exact_density_halo_events"](spark, sf_dir).collect()
        assert parts == [7]
    finally:
        halo.stored = stored
        spark.conf.set("spark.sql.shuffle.partitions", "4")


def test_many_representatives_meet_no_pairs(monkeypatch):
    """Labels by lines are those of the nearest, the least id of equals, and form no pairs of points and representatives."""
    rng = np.random.default_rng(0)
    xs, reps, ids = rng.integers(0, 90, (2000, 2)), rng.integers(0, 60, (300, 2)), rng.permutation(3000)[:300]
    by = np.argsort(ids)
    want = ids[by][((xs[:, None] - reps[by][None]) ** 2).sum(axis=2).argmin(axis=1)]
    monkeypatch.setattr(kernel, "near_pairs", None)
    assert (kernel.nearest(xs, reps, ids, ids, reach=20) == want).all()
    monkeypatch.setattr(kernel, "MAX_TABLE", 1)
    assert (kernel.nearest(xs, reps, ids, ids, reach=20) == want).all()


def test_runs_are_dealt_evenly(spark, sf_dir):
    """As many runs to each task."""
    jobs = [("shapes9_small", "seeds", s, workloads._options("shapes9_small")) for s in range(12)]
    parts = workloads.repeated(spark, sf_dir, jobs).groupBy(F.spark_partition_id().alias("part")).count().collect()
    assert [r["count"] for r in parts] == [1] * 12
