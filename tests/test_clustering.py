"""Worked examples, invariants and plan shapes of the clustering engine."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from densereps.operators import anytime, exact, graph, halo, kernel, labeling, metrics, neighbors, sampling, stability
from densereps.operators import representatives as reps_
from densereps.operators.components import connected_components
from densereps.operators.ssdc import Ssdc, SsdcModel
from densereps.operators.testsize import coverage, test_size
from densereps.params import SsdcParams
from densereps.sources.points import load_points

LINE = SsdcParams(eps=1, min_pts=3, gamma=6, beta=5, tau=0.5)


def on_line(spark, positions):
    return spark.createDataFrame([(int(i), int(i), 0) for i in positions], "id long, x long, y long")


def as_dict(df, value):
    return {r["id"]: r[value] for r in df.collect()}


# ---- worked examples


def test_micro_set_by_hand(spark):
    got = exact.exact_density(on_line(spark, [0, 1, 2, 3, 10, 11, 12, 20]), 1, 3)
    assert as_dict(got, "n_eps") == {0: 2, 1: 3, 2: 3, 3: 2, 10: 2, 11: 3, 12: 2, 20: 1}
    assert as_dict(got, "state") == {0: "border", 1: "core", 2: "core", 3: "border", 10: "border", 11: "core", 12: "border", 20: "noise"}
    assert as_dict(got, "cluster") == {0: 1, 1: 1, 2: 1, 3: 1, 10: 11, 11: 11, 12: 11, 20: -1}


def test_one_round_by_hand(spark):
    state = graph.init_graph(on_line(spark, [0, 1, 2, 10, 11, 12]), 2, LINE)
    assert as_dict(state.vertices, "cluster") == {0: 0, 1: 0, 2: 0, 10: 10, 11: 10, 12: 10}
    reps = reps_.representatives(state.vertices, 0.5).join(state.sample, "id")
    assert {r["id"] for r in reps.collect()} == {1, 11}
    test = on_line(spark, [3, 9, 20])
    first = labeling.label_nearest(test, reps)
    assert as_dict(first, "cluster") == {3: 0, 9: 10, 20: 10}
    lower = graph.demote(state, 3)
    assert {(r["old_state"], r["new_state"]): r["n"] for r in graph.transitions(state.vertices, lower.vertices).collect()} == {("core", "border"): 4, ("core", "core"): 2}
    grown = graph.insert(lower, on_line(spark, [4, 5, 6, 7, 8]))
    assert {k for k, v in as_dict(grown.vertices, "state").items() if v == "core"} == {1, 5, 6, 7, 11}
    assert as_dict(grown.vertices, "cluster") == {0: 1, 1: 1, 2: 1, 4: 5, 5: 5, 6: 5, 7: 5, 8: 5, 10: 11, 11: 11, 12: 11}
    reps = reps_.representatives(grown.vertices, 0.5).join(grown.sample, "id")
    second = labeling.label_nearest(test, reps)
    assert as_dict(second, "cluster") == {3: 1, 9: 5, 20: 11}
    both = first.select("id", F.col("cluster").alias("prev_cluster")).join(second.select("id", F.col("cluster").alias("cur_cluster")), "id")
    assert stability.instability(both).first()["delta"] == pytest.approx(1 / 3)


def test_disagreement_by_hand(spark):
    rows = spark.createDataFrame([(0, 1, 1), (1, 1, 1), (2, 2, 1), (3, 2, 2)], "id long, prev_cluster long, cur_cluster long")
    assert stability.instability(rows).first()["delta"] == 0.5
    assert stability.instability_pairs(rows).first()["delta"] == 0.5
    assert kernel.disagreement(np.array([1, 1, 2, 2]), np.array([1, 1, 1, 2])) == 0.5
    assert kernel.disagreement(np.array([1, 1, 2, 2]), np.array([7, 7, 3, 3])) == 0
    a, b = np.random.default_rng(0).integers(0, 4, (2, 60))
    assert kernel.disagreement(a, b) == kernel.disagreement(b, a)


def test_selection_by_hand(spark):
    states = spark.createDataFrame([(i, n, "core", 0) for i, n in enumerate((4, 6, 8, 10))], "id long, n_eps long, state string, cluster long")
    pick = lambda tau: {r["n_eps"] for r in reps_.representatives(states, tau).collect()}
    assert pick(0.5) == {4, 10} and pick(1.0) == {4, 6, 8, 10} and pick(0.0) == {10}
    assert {r["n_eps"] for r in reps_.representatives(states, 0.7, "rim_only").collect()} == {4, 6}


def test_test_size_by_hand():
    assert [test_size(n, k) for n, k in ((50_000, 50), (788, 7), (2_000, 10), (500, 10))] == [1582, 75, 142, 72]
    assert test_size(10**9, 3, rectify_n=50_000, rectify_k=50) == 1582
    assert coverage(10_000, 0.01)[1] > 0.999 and coverage(1, 0.5)[1] == 0


# ---- invariants


@pytest.fixture(scope="module")
def points(spark, sf_dir):
    return load_points(spark, sf_dir.replace("0.001", "0.01"), "shapes9_small").cache()


@pytest.fixture(scope="module")
def arrays(points):
    pdf = points.toPandas().sort_values("id")
    return pdf["id"].to_numpy(), pdf[["x", "y"]].to_numpy()


def test_exact_clustering_equals_the_kernel_and_has_the_known_result(points, arrays):
    got = exact.exact_density(points.repartition(7), 80, 5).toPandas().sort_values("id")
    n, state, cluster = kernel.exact(*arrays, SsdcParams(eps=80, min_pts=5, gamma=1, beta=1))
    assert (got["n_eps"].to_numpy() == n).all() and (got["state"].to_numpy() == state).all() and (got["cluster"].to_numpy() == cluster).all()
    assert len(set(cluster[cluster >= 0])) == 27 and (cluster < 0).sum() == 27


def test_copies_of_a_point_count(spark):
    rows = spark.createDataFrame([(i, 5, 5) for i in range(1000)] + [(2000, 6, 5), (3000, 50, 50)], "id long, x long, y long")
    got = exact.exact_density(rows, 2, 100)
    assert as_dict(got, "cluster") == {**dict.fromkeys(range(1000), 0), 2000: 0, 3000: -1}


def test_star_contraction(spark):
    rng = np.random.default_rng(5)
    edges = [(int(a), int(b)) for a, b in rng.integers(0, 300, (250, 2))] + [(500, 500), (None, 3)] + [(i, i + 1) for i in range(600, 660)]
    got = {r["id"]: r["component"] for r in connected_components(spark.createDataFrame(edges, "src long, dst long")).collect()}
    up = {}

    def root(i):
        while up.setdefault(i, i) != i:
            i = up[i]
        return i

    for a, b in edges:
        if a is not None:
            x, y = root(a), root(b)
            up[max(x, y)] = min(x, y)
    assert got == {i: root(i) for i in up}


def test_slices_are_disjoint_and_cover(points):
    rows = sampling.SamplePlan(points, 180, 180, 117).labelled().collect()
    assert len({r["id"] for r in rows}) == len(rows) == 1500 and sorted(r["rank"] for r in rows) == list(range(1500))


def test_both_engines_give_the_same_run(points):
    p = SsdcParams(eps=200, min_pts=5, gamma=180, beta=180, tau=0.5)
    a, b = Ssdc(p).fit(points), Ssdc(p, "frames").fit(points)
    columns = ["iteration", "eta", "n_sample", "n_test", "k", "n_reps", "n_core", "n_border", "n_noise", "n_pairs"]
    assert a.trace.select(columns).collect() == b.trace.select(columns).collect() and a.reason == b.reason
    assert as_dict(a.vertices, "cluster") == as_dict(b.vertices, "cluster")
    assert {r["id"] for r in a.reps.collect()} == {r["id"] for r in b.reps.collect()}


VARIANTS = [
    {"relabel": "lazy"}, {"merge_on": "any"}, {"relabel": "lazy", "merge_on": "any"}, {"weak_edges": "connect"}, {"eta_rule": "plus_one", "border_rule": "nearest_core"},
    {"eta_rule": "printed", "relabel": "lazy"}, {"eta_rule": "fixed", "border_rule": "lowest_core_id"},
]


@pytest.mark.parametrize("options", VARIANTS, ids=str)
def test_engines_agree_on_variants(points, options):
    p = SsdcParams(eps=130, min_pts=5, gamma=120, beta=60, tau=0.5, max_iterations=3, finalize_eta=True, **options)
    a, b = Ssdc(p).fit(points), Ssdc(p, "frames").fit(points)
    columns = ["iteration", "eta", "n_sample", "n_test", "k", "n_reps", "n_core", "n_border", "n_noise", "n_pairs", "delta"]
    rows = lambda m: [tuple(round(v, 9) if isinstance(v, float) else v for v in r) for r in m.trace.select(columns).collect()]
    assert rows(a) == rows(b) and as_dict(a.vertices, "cluster") == as_dict(b.vertices, "cluster")


@pytest.mark.parametrize("eps", [80, 110, 130])
def test_any_neighbour_merges_more(arrays, eps):
    ids, xs = arrays
    o = kernel.permutation(ids, 0)
    draw = lambda a, b: (ids[o[a:b]], xs[o[a:b]])
    base = {"eps": eps, "min_pts": 5, "gamma": 300, "beta": 300, "tau": 0.5, "eta_rule": "fixed", "max_iterations": 1}
    plain, wide = (kernel.run(draw, len(ids), SsdcParams(**base, merge_on=m), keep_history=True) for m in ("core", "any"))
    (_, state, cluster), (_, _, merged) = plain.history[1], wide.history[1]
    core = state == "core"
    assert all(len(set(merged[core & (cluster == c)])) == 1 for c in set(cluster[core]))
    assert wide.trace[1]["k"] < plain.trace[1]["k"]


def test_vectors_on_both_engines_and_after_load(spark, tmp_path):
    rng = np.random.default_rng(3)
    xs = np.concatenate([rng.normal(c, 0.3, (80, 5)) for c in (0, 4, 8)])
    df = spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(xs)], "id long, vec array<double>")
    p = SsdcParams(eps=1.2, min_pts=4, gamma=60, beta=30, tau=0.5)
    a, b = Ssdc(p).fit(df), Ssdc(p, "frames").fit(df)
    assert as_dict(a.vertices, "cluster") == as_dict(b.vertices, "cluster")
    want = as_dict(a.transform(df), "cluster")
    assert len({c for c in want.values() if c >= 0}) == 3 and want == as_dict(b.transform(df), "cluster")
    a.save(str(tmp_path / "model"))
    assert as_dict(SsdcModel.load(spark, str(tmp_path / "model")).transform(df), "cluster") == want


def test_pairs_beyond_the_bound_go_to_frames(points, monkeypatch):
    p = SsdcParams(eps=200, min_pts=5, gamma=100, beta=50, tau=0.5, max_iterations=1)
    want = Ssdc(p).fit(points)
    monkeypatch.setattr(kernel, "MAX_PAIRS", 300)
    got = Ssdc(p).fit(points)
    assert got.fit is None and want.fit is not None and as_dict(got.vertices, "cluster") == as_dict(want.vertices, "cluster")


@pytest.mark.parametrize(("eps", "min_pts", "side"), [(80, 5, 330), (150, 9, 610), (40, 2, 100)])
def test_tiles_equal_whole(points, eps, min_pts, side):
    rows = points.select("id", "x", "y").union(points.filter("id % 5 = 0").selectExpr("id + 10000", "x", "y"))
    got = halo.exact_density_tiles(rows, eps, min_pts, side)
    want = exact.exact_density(rows, eps, min_pts)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
    assert halo.exact_density_tiles(rows.limit(0), eps, min_pts).count() == 0


@pytest.mark.parametrize("seed", range(4))
def test_core_partition_is_exact_on_the_sample_each_round(arrays, seed):
    ids, xs = arrays
    p = SsdcParams(eps=200, min_pts=5, gamma=180, beta=180, tau=0.5, seed=seed)
    o = kernel.permutation(ids, seed)
    fit = kernel.run(lambda a, b: (ids[o[a:b]], xs[o[a:b]]), len(ids), p, keep_history=True)
    etas = [t["eta"] for t in fit.trace]
    assert etas == sorted(etas) and max(etas) <= 5
    assert fit.reason == "stable" and fit.trace[-1]["k"] == 9
    own, where = fit.history[-1][0], {int(i): k for k, i in enumerate(ids)}
    n, state, cluster = kernel.exact(own, xs[[where[int(i)] for i in own]], p)
    assert (state == fit.history[-1][1]).all() and (cluster == fit.history[-1][2]).all()


def test_whole_set_as_first_sample_equals_exact(arrays):
    ids, xs = arrays
    p = SsdcParams(eps=80, min_pts=5, gamma=1500, beta=10, tau=0.5, finalize_eta=True)
    fit = kernel.run(lambda a, b: (ids[a:b], xs[a:b]), len(ids), p)
    assert (fit.cluster == kernel.exact(ids, xs, p)[2]).all()


def test_huge_eps_stops_at_three_batches(arrays):
    ids, xs = arrays
    fit = kernel.run(lambda a, b: (ids[a:b], xs[a:b]), len(ids), SsdcParams(eps=10**5, min_pts=300, gamma=180, beta=180, tau=0.5))
    assert fit.trace[-1]["k"] == 1 and len(fit.ids) == 180 + 2 * 180


def test_unsettled_run_uses_all_points(arrays):
    ids, xs = arrays
    o = kernel.permutation(ids, 0)
    fit = kernel.run(lambda a, b: (ids[o[a:b]], xs[o[a:b]]), len(ids), SsdcParams(eps=70, min_pts=5, gamma=180, beta=180, tau=0.5))
    assert fit.reason == "exhausted" and len(fit.ids) + len(fit.test_ids) == len(ids)


def test_labelling_modes_agree(points):
    model = Ssdc(SsdcParams(eps=200, min_pts=5, gamma=180, beta=180, tau=0.5)).fit(points)
    want = as_dict(labeling.label_nearest(points, model.reps, "array", 400), "cluster")
    free = as_dict(labeling.label_nearest(points, model.reps, "join"), "cluster")
    assert free == as_dict(labeling.label_nearest(points, model.reps, "grid", reach=20), "cluster") == as_dict(labeling.label_nearest(points, model.reps, "arrow", reach=100), "cluster")
    for mode in ("arrow", "grid", "join"):
        assert as_dict(labeling.label_nearest(points, model.reps, mode, 400), "cluster") == want
    assert as_dict(labeling.label_nearest(points, model.reps.limit(0)), "cluster") == dict.fromkeys(want, -1)


def test_lazy_labels_are_coarser(arrays):
    ids, xs = arrays
    o = kernel.permutation(ids, 1)
    draw = lambda a, b: (ids[o[a:b]], xs[o[a:b]])
    p = SsdcParams(eps=150, min_pts=5, gamma=180, beta=180, tau=0.5)
    assert kernel.run(draw, len(ids), SsdcParams(**{**p.__dict__, "relabel": "lazy"})).trace[-1]["k"] <= kernel.run(draw, len(ids), p).trace[-1]["k"]


def test_anytime_equals_exact(spark, sf_dir):
    rows = load_points(spark, sf_dir, "shapes9_small")
    got, trace = anytime.anytime_blocks(rows, 500, 4, 20, 20)
    assert as_dict(got, "cluster") == as_dict(exact.exact_density(rows, 500, 4), "cluster")
    assert trace.agg(F.max("queries")).first()[0] <= 150


def test_anytime_leaves_settled_points_unasked(points):
    got, trace = anytime.anytime_blocks(points, 150, 5, 64, 64)
    want = as_dict(exact.exact_density(points, 150, 5), "cluster")
    last = trace.orderBy(F.desc("block")).first()
    assert as_dict(got, "cluster") == want and last["clusters"] == len(set(want.values()) - {-1}) and last["queries"] < 1500
    told = got.filter("state <> 'inner'").join(exact.exact_density(points, 150, 5).select("id", F.col("state").alias("s")), "id")
    assert told.filter("state <> s").count() == 0


def test_model_round_trip(spark, points, tmp_path):
    model = Ssdc(SsdcParams(eps=200, min_pts=5, gamma=180, beta=180, tau=0.5)).fit(points)
    model.save(str(tmp_path / "model"))
    held = SsdcModel.load(spark, str(tmp_path / "model"))
    assert held.params == model.params and held.reason == model.reason
    assert as_dict(held.transform(points), "cluster") == as_dict(model.transform(points), "cluster")


def test_nmi_averages(spark, points):
    labels = exact.exact_density(points, 80, 5).join(points.select("id", "truth"), "id").cache()
    pdf = labels.toPandas()
    for average in ("geometric", "arithmetic", "max", "min"):
        got = metrics.nmi(labels, "cluster", "truth", average).first()["nmi"]
        assert got == pytest.approx(kernel.mutual_information(pdf["cluster"].to_numpy(), pdf["truth"].to_numpy(), average), abs=1e-5)


def test_pivot_pairs_miss_none(spark):
    rng = np.random.default_rng(7)
    xs = rng.normal(size=(120, 12))
    df = spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(xs)], "id long, vec array<double>")
    i, j = kernel.near_pairs(xs, xs, 4.0)
    assert {(r["src"], r["dst"]) for r in neighbors.pivot_pairs(df, 4.0).collect()} == set(zip(i.tolist(), j.tolist(), strict=True))
    near = {(r["src"], r["dst"]) for r in neighbors.lsh_pairs(df, 4.0).collect()}
    assert near <= set(zip(i.tolist(), j.tolist(), strict=True)) and len(near) > 0.5 * len(i)


# ---- plans


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_plan_shapes(points):
    assert "NestedLoop" not in plan(neighbors.range_pairs(points, 150)) and "Cartesian" not in plan(neighbors.range_pairs(points, 150))
    assert "TakeOrderedAndProject" in plan(sampling.take(points, 100))
    assert "Exchange" not in plan(sampling.threshold_sample(points, 0.1))
    assert "Exchange" not in plan(sampling.key_range(points, 5, 1 << 20))
    part = plan(sampling.SamplePlan(points, 180, 180, 117).batch(1))
    assert "Exchange" not in part and "Window" not in part and "PushedFilters: [IsNotNull(rank)" in part
    reps = points.limit(5).select("id", F.col("id").alias("cluster"), "x", "y")
    assert "Exchange" not in plan(labeling.label_nearest(points, reps, "array"))


def test_parameters_are_checked():
    with pytest.raises(ValueError):
        SsdcParams(eps=1, min_pts=1, gamma=1, beta=1, eta_rule="other").validate()


def test_k_nearest_of_sparse_points(spark):
    rows = [(i, 3 * i, i) for i in range(20)] + [(100, 50_000, 7), (101, -900_000, 3)]
    df = spark.createDataFrame(rows, "id long, x long, y long")
    want = {}
    for i, x, y in rows:
        near = sorted(((x - a) ** 2 + (y - b) ** 2, j) for j, a, b in rows if j != i)[:5]
        want |= {(i, k + 1): (j, d) for k, (d, j) in enumerate(near)}
    got = {(r.id, r.rank): (r.neighbor, r.d2) for r in neighbors.k_nearest(df, 5, 10).collect()}
    assert got == want
    assert neighbors.k_nearest(df.limit(1), 5, 10).count() == 0 and neighbors.k_nearest(df.filter("id < 3"), 5, 10).count() == 6
