"""The experiment workloads on the given tables; one row for each dataset, setting, seed and round as fits.

Repeated runs are independent and each holds one small sample, so they are dealt over tasks: each task runs the
array kernel on a broadcast point set of checked size. Large sets go through the fit on DataFrames.
"""

from __future__ import annotations

import itertools
import time
from collections.abc import Iterator
from functools import partial

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from densereps.operators import anytime, autok, exact, kernel, kmeans, metrics, testsize
from densereps.operators.ssdc import Ssdc
from densereps.params import SsdcParams
from densereps.plans.lineage import cut
from densereps.sources.points import load_documents, load_points, load_vectors

#: Points of a set that a task may hold for repeated runs: three numbers each.
MAX_REPEATED = 4_000_000

#: Density of the comparison of methods.
EPS, MIN_PTS = 150, 5

RUNS = (
    "dataset string, setting string, seed int, iteration int, last boolean, eta int, k int, n_sample long, n_reps long, delta double, "
    "nmi_exact double, nmi_truth double, reason string, n_core long, n_border long, n_noise long"
)

#: eps, min_pts, gamma, beta, tau of the small sets.
SMALL = {
    "shapes9_small": (150, 5, 0.12, 0.12, 0.5), "blobs30": (120, 5, 0.15, 0.10, 0.5), "blobs31": (80, 5, 0.10, 0.10, 0.5), "part_grid": (220, 5, 0.15, 0.10, 0.5),
    "docs_lang": (40, 10, 0.15, 0.10, 0.5),
}


def _set(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A point set with its truth as numbers."""
    if name != "docs_lang":
        return load_points(spark, sf_dir, name)
    docs = load_documents(spark, sf_dir)
    return docs.withColumn("truth", F.pmod(F.xxhash64("truth"), F.lit(1 << 30)).cast("int")).na.drop(subset=["id", "x", "y"])


def repeated(spark: SparkSession, sf_dir: str, jobs: list[tuple[str, str, int, dict]], every_round: bool = False) -> DataFrame:
    """Rows of many runs: (dataset, setting, seed, parameters of SsdcParams with gamma and beta as shares)."""
    sets = {}
    for name in {j[0] for j in jobs}:
        points = _set(spark, sf_dir, name)
        if points.count() > MAX_REPEATED:
            raise ValueError(f"{name} is too large for repeated runs")
        held = points.select("id", "x", "y", "truth").toArrow()
        ids, x, y = (held.column(c).to_numpy().astype(np.int64) for c in ("id", "x", "y"))
        truth = held.column("truth")
        sets[name] = (ids, np.stack([x, y], axis=1), None if truth.null_count == len(truth) else truth.to_numpy().astype(np.int64))
    shared = spark.sparkContext.broadcast(sets)
    keys = sorted({(name, options["eps"], options["min_pts"]) for name, _, _, options in jobs})

    def whole(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for k in batch["id"].tolist():  # a set's labels at a time, by number
                name, eps, min_pts = keys[k]
                ids, xs, _ = shared.value[name]
                label = kernel.exact(ids, xs, SsdcParams(eps=eps, min_pts=min_pts, gamma=1, beta=1))[2]
                yield pd.DataFrame({"id": [k], "labels": [np.unique(label, return_inverse=True)[1].astype(np.int32).tobytes()]})

    known = spark.range(0, len(keys), 1, max(1, len(keys))).mapInPandas(whole, "id long, labels binary")
    exact_of = {keys[r["id"]]: np.frombuffer(r["labels"], np.int32) for r in known.toLocalIterator()}  # four bytes a point, a task at a time
    held = spark.sparkContext.broadcast((exact_of, jobs))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        sets, (exact_of, jobs) = shared.value, held.value
        for batch in batches:
            rows = []
            for job in batch["job"].tolist():
                name, setting, seed, options = jobs[job]
                ids, xs, truth = sets[name]
                p = SsdcParams.of_share(len(ids), seed=seed, **options)
                order = kernel.permutation(ids, seed)
                fit = kernel.run(lambda a, b, ids=ids, xs=xs, o=order: (ids[o[a:b]], xs[o[a:b]]), len(ids), p)
                label = kernel.nearest(xs, fit.xs[fit.reps], fit.ids[fit.reps], fit.cluster[fit.reps], None, p.eps)
                by = np.argsort(ids)
                label[by[np.searchsorted(ids, fit.ids, sorter=by)]] = fit.cluster
                vs_exact = kernel.mutual_information(label, exact_of[name, p.eps, p.min_pts])
                vs_truth = None if truth is None else kernel.mutual_information(label, truth)
                for t in fit.trace if every_round else fit.trace[-1:]:
                    last = t is fit.trace[-1]
                    rows.append((name, setting, seed, t["iteration"], last, t["eta"], t["k"], t["n_sample"], t["n_reps"], t["delta"],
                                 vs_exact if last else None, vs_truth if last else None, fit.reason if last else None, t["n_core"], t["n_border"], t["n_noise"]))
            yield pd.DataFrame(rows, columns=[c.split()[0] for c in RUNS.split(", ")])

    dealt = spark.range(0, len(jobs), 1, max(1, min(len(jobs), 256)))  # as many to each task; by hash some get several and others none
    return dealt.withColumnRenamed("id", "job").mapInPandas(run, RUNS)


def _options(name: str, **over) -> dict:
    eps, min_pts, gamma, beta, tau = SMALL[name]
    return {"eps": eps, "min_pts": min_pts, "gamma": gamma, "beta": beta, "tau": tau} | over


def w_walkthrough(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One run, round by round: its counters, and how many points came to each state from each other."""
    held = load_points(spark, sf_dir, "shapes9_small").select("id", "x", "y").toArrow()  # three numbers a point
    ids, xs = held.column("id").to_numpy(), np.stack([held.column("x").to_numpy(), held.column("y").to_numpy()], axis=1)
    order = kernel.permutation(ids, 0)
    p = SsdcParams.of_share(len(ids), **_options("shapes9_small"))
    fit = kernel.run(lambda a, b: (ids[order[a:b]], xs[order[a:b]]), len(ids), p, keep_history=True)
    rows, before = [], np.zeros(0, "U7")
    for t, (_, state, _) in zip(fit.trace, fit.history, strict=True):  # a sample keeps the order of drawing
        was = np.concatenate([before, np.full(len(state) - len(before), "unknown")])
        moves = {(str(a), str(b)): int(((was == a) & (state == b)).sum()) for a in np.unique(was) for b in np.unique(state)}
        rows += [(t["iteration"], t["eta"], t["k"], t["n_sample"], t["delta"], a, b, n) for (a, b), n in sorted(moves.items()) if n]
        before = state
    return spark.createDataFrame(rows, "iteration int, eta int, k int, n_sample long, delta double, old_state string, new_state string, n long")


def w_randomness(spark: SparkSession, sf_dir: str, n_seeds: int = 50) -> DataFrame:
    """How often each K is found over seeds."""
    runs = repeated(spark, sf_dir, [("shapes9_small", "seeds", s, _options("shapes9_small")) for s in range(n_seeds)])
    return metrics.k_frequency(runs, ["dataset"])


def run_catalogue(spark: SparkSession, sf_dir: str, n_seeds: int = 50) -> DataFrame:
    """K, how often, and the mean agreement with exact clustering, over seeds."""
    runs = repeated(spark, sf_dir, [("blobs31", "seeds", s, _options("blobs31")) for s in range(n_seeds)])
    return runs.groupBy("dataset", "k").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("nmi_exact"), 6).alias("mean_nmi_exact"))


def w_gamma_sweep(spark: SparkSession, sf_dir: str, n_seeds: int = 100, gammas=(0.05, 0.10, 0.15, 0.20, 0.30, 0.40)) -> DataFrame:
    """K by the size of the first sample."""
    jobs = [(d, f"gamma={g}", s, _options(d, gamma=g)) for d, g, s in itertools.product(("shapes9_small", "blobs30", "blobs31"), gammas, range(n_seeds))]
    return metrics.k_frequency(repeated(spark, sf_dir, jobs), ["dataset", "setting"])


def w_quality(spark: SparkSession, sf_dir: str, n_seeds: int = 50) -> DataFrame:
    """Agreement with exact clustering and with the truth: mean and deviation over seeds."""
    runs = repeated(spark, sf_dir, [(d, "quality", s, _options(d)) for d in SMALL for s in range(n_seeds)])
    return metrics.mean_and_deviation(runs, ["dataset"], ["k", "n_sample", "nmi_exact", "nmi_truth"])


#: eps, min_pts of the large sets, at the density of sf0.01; gamma and beta as counts.
LARGE = {
    "shapes9_large": [(60, 5), (100, 5), (150, 10)],
    "shapes41_noise": [(60, 10), (100, 10), (150, 10)],
    "events_xy": [(600, 10), (1200, 20)],
}
#: The same of the vectors: one where no point is a core, and one at which all are.
VECTORS = [(1.1, 5), (1.5, 10)]
#: Blocks of the anytime method after its first, in the comparisons.
BLOCKS = 1
COMPARED = "dataset string, eps double, min_pts int, method string, k int, processed long, n_reps long, reason string, seconds double, nmi_truth double"


def _sampled(points: DataFrame, eps: float, min_pts: int, truth: bool, gamma: int = 600, beta: int = 300) -> tuple:
    """What one run gives; seconds until the representatives are there."""
    began = time.time()
    model = Ssdc(SsdcParams(eps=eps, min_pts=min_pts, gamma=gamma, beta=beta, tau=0.3)).fit(points)
    seconds, last = time.time() - began, model.trace.orderBy(F.desc("iteration")).first()
    nmi = metrics.nmi(model.transform(points), "cluster", "truth").first()["nmi"] if truth else None
    return ("sampled", int(last["k"]), int(last["n_sample"]), int(last["n_reps"]), model.reason, seconds, nmi)


def _anytime(points: DataFrame, eps: float, min_pts: int, truth: bool) -> tuple:
    """The block-wise method, stopped after BLOCKS blocks; processed are its range queries."""
    began = time.time()
    labels, trace = anytime.anytime_blocks(points, eps, min_pts, 2048, 2048, snapshot=100, max_blocks=BLOCKS)
    last = trace.orderBy(F.desc("block")).first()
    seconds = time.time() - began
    nmi = metrics.nmi(labels.join(points.select("id", "truth"), "id"), "cluster", "truth").first()["nmi"] if truth else None
    return ("anytime", int(last["clusters"]), int(last["queries"]), 0, "settled" if not last["unknown"] else "stopped", seconds, nmi)


def _autok(points: DataFrame) -> tuple:
    began = time.time()
    k, _ = autok.autok(points, 20, n_pairs=4)
    return ("autok", int(k), None, int(k), None, time.time() - began, None)


def w_large(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Clusters, points processed and seconds on large sets: sampled, block-wise anytime, and K-means that chooses K."""
    rows = []
    for name, settings in LARGE.items():
        points = cut(load_points(spark, sf_dir, name))
        rows.append((name, None, None, *_autok(points)))
        truth = name != "events_xy"
        rows += [(name, float(eps), min_pts, *_sampled(points, eps, min_pts, truth)) for eps, min_pts in settings]
        eps, min_pts = settings[-1]
        rows.append((name, float(eps), min_pts, *_anytime(points, eps, min_pts, truth)))
    vectors = cut(load_vectors(spark, sf_dir))
    rows += [("embeddings", eps, min_pts, *_sampled(vectors, eps, min_pts, True, 240, 80)) for eps, min_pts in VECTORS]
    return spark.createDataFrame(rows, COMPARED)


def w_eps_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Clusters by eps on the set of 41 shapes with noise: sampled and block-wise anytime."""
    points = cut(load_points(spark, sf_dir, "shapes41_noise"))
    rows = [("shapes41_noise", float(eps), 10, *f(points, eps, 10, True)) for eps in (40, 60, 100, 200) for f in (_sampled, _anytime)]
    return spark.createDataFrame(rows, COMPARED)


def w_single_cluster(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A huge eps gives one cluster and stops at the floor of three batches."""
    return repeated(spark, sf_dir, [("shapes9_small", "huge eps", s, _options("shapes9_small", eps=10_000, min_pts=300)) for s in range(5)], every_round=True)


def w_exhaust(spark: SparkSession, sf_dir: str) -> DataFrame:
    """An eps at which the labels hardly settle."""
    return repeated(spark, sf_dir, [("shapes9_small", "small eps", s, _options("shapes9_small", eps=80)) for s in range(5)])


#: Point sets whose sizes give the test sizes.
ALPHA_SETS = ("shapes9_small", "shapes9_large", "blobs31", "events_xy")


def w_alpha(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Test sizes for the point sets as they are, with and without the constants for large data."""
    sizes = [(name, load_points(spark, sf_dir, name).agg(F.count("x")).first()[0]) for name in ALPHA_SETS]
    rows = [(name, n, k, testsize.test_size(n, k), testsize.test_size(n, k, rectify_n=50_000, rectify_k=50)) for name, n in sizes for k in (2, 10, 50)]
    return spark.createDataFrame(rows, "dataset string, n long, k int, alpha int, alpha_rectified int")


def w_convergence(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Disagreement and K by round."""
    jobs = [("shapes9_large", "seeds", s, {"eps": 100, "min_pts": 5, "gamma": 0.04, "beta": 0.02, "tau": 0.3}) for s in range(5)]
    jobs += [("shapes41_noise", "seeds", s, {"eps": 100, "min_pts": 10, "gamma": 0.04, "beta": 0.02, "tau": 0.3}) for s in range(2)]
    return repeated(spark, sf_dir, jobs, every_round=True)


def w_tau(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Representatives and agreement by the rim threshold."""
    base = {"eps": 100, "min_pts": 5, "gamma": 0.04, "beta": 0.02}
    jobs = [("shapes9_large", f"tau={t}", s, base | {"tau": t}) for t in (0.0, 0.1, 0.2, 0.3, 0.4, 0.5, 0.7) for s in range(3)]
    return metrics.mean_and_deviation(repeated(spark, sf_dir, jobs), ["dataset", "setting"], ["n_reps", "nmi_exact", "nmi_truth"])


def w_toy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two shapes of unlike extent, a solid block beside a long bar: K-means, one representative a cluster, and many."""
    shapes = load_points(spark, sf_dir, "shapes9_small").filter("truth IN (0, 4)")
    points = cut(shapes.withColumn("x", F.when(F.col("truth") == 4, F.floor((F.col("x") - 2000) / 4) + 1400).otherwise(F.col("x"))).withColumn(
        "y", F.when(F.col("truth") == 4, 4 * (F.col("y") - 2000)).otherwise(F.col("y"))
    ))
    rows = []
    for name, labels in (("library", kmeans.spark_ml_kmeans(points, 2)), ("kmeans", kmeans.kmeans(points, 2)[0])):
        rows.append((name, 2, 2, metrics.nmi(labels, "cluster", "truth").first()["nmi"]))
    for selector in ("center_only", "rim_and_center", "rim_only", "all_core"):
        p = SsdcParams(eps=400, min_pts=3, gamma=max(20, points.count() // 2), beta=20, tau=0.7, selector=selector)
        model = Ssdc(p).fit(points)
        last = model.trace.orderBy(F.desc("iteration")).first()
        near = model.transform(points.withColumn("id", F.col("id") + (1 << 40)))  # as new points, labelled by representatives alone
        rows.append((selector, last["k"], last["n_reps"], metrics.nmi(near, "cluster", "truth").first()["nmi"]))
    return spark.createDataFrame(rows, "method string, k int, n_reps long, nmi_truth double")


def w_serve(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Labels on demand: only the events of a slice are read and labelled, by a model fitted on a sample of all."""
    points = load_points(spark, sf_dir, "events_xy")
    model = Ssdc(SsdcParams(eps=1200, min_pts=10, gamma=500, beta=250, tau=0.3)).fit(points)
    return model.transform(points.filter("x BETWEEN 10000 AND 20000")).groupBy("cluster").agg(F.count(F.lit(1)).alias("n"))


def w_methods(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Range queries and seconds of exact, anytime and sampled clustering on one set at one density."""
    points = load_points(spark, sf_dir, "shapes9_small")
    rows = []
    for name, f in (("exact", exact.exact_density), ("exact by tiles", partial(exact.exact_density, halo=True))):
        began = time.time()
        k = metrics.n_clusters(f(points, EPS, MIN_PTS)).first()["k"]
        rows.append((name, k, points.count(), time.time() - began))
    began = time.time()
    labels, trace = anytime.anytime_blocks(points, EPS, MIN_PTS, 512, 256)
    rows.append(("anytime", metrics.n_clusters(labels).first()["k"], trace.agg(F.max("queries")).first()[0], time.time() - began))
    began = time.time()
    last = Ssdc(SsdcParams(eps=EPS, min_pts=MIN_PTS, gamma=180, beta=180, tau=0.5)).fit(points).trace.orderBy(F.desc("iteration")).first()
    rows.append(("sampled", last["k"], last["n_range_queries"], time.time() - began))
    return spark.createDataFrame([(m, int(k), int(q), round(s, 3)) for m, k, q, s in rows], "method string, k int, range_queries long, seconds double")


ALL = [
    w_walkthrough, w_randomness, run_catalogue, w_gamma_sweep, w_quality, w_large, w_eps_sweep, w_single_cluster, w_exhaust, w_alpha, w_convergence, w_tau, w_toy,
    w_serve, w_methods,
]
