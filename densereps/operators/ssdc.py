"""Stable-sample density clustering: fit on a growing sample, label any row by its nearest representative."""

from __future__ import annotations

import math
import time
from dataclasses import asdict, dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from densereps.functions.expr import md5_key
from densereps.operators import graph as g
from densereps.operators import kernel
from densereps.operators.eta import next_threshold
from densereps.operators.labeling import label_nearest
from densereps.operators.representatives import representatives
from densereps.operators.sampling import key_range, permute
from densereps.operators.stability import StopPolicy, instability
from densereps.operators.testsize import test_size
from densereps.params import SsdcParams
from densereps.plans.lineage import cut

#: Sampled points that the array kernel may hold; a larger sample is grown on DataFrames.
MAX_KERNEL = 400_000

TRACE = (
    "iteration int, eta int, n_sample long, n_test long, k int, n_reps long, delta double, n_core long, n_border long, n_noise long, "
    "n_range_queries long, n_pairs long, seconds double"
)


@dataclass
class SsdcModel:
    """reps (id, cluster, n_eps, x, y or vec), vertices (id, n_eps, state, cluster), trace, params, why it stopped."""

    reps: DataFrame
    vertices: DataFrame
    trace: DataFrame
    params: SsdcParams
    reason: str
    fit: kernel.Fit | None = None

    def transform(self, points: DataFrame, mode: str = "auto") -> DataFrame:
        """points with cluster: the sample keeps its graph's, any other row gets the nearest representative's.

        Lazy: nothing runs until asked, and filters on points go below it.
        """
        own = self.vertices.select("id", F.col("cluster").alias("graph_cluster"))
        near = label_nearest(points, self.reps, mode, self.params.max_distance, self.params.eps)
        return near.join(own, "id", "left").withColumn("cluster", F.coalesce("graph_cluster", "cluster")).drop("graph_cluster")

    def save(self, path: str) -> None:
        for name in ("reps", "vertices", "trace"):
            getattr(self, name).write.mode("overwrite").parquet(f"{path}/{name}")
        spark = self.reps.sparkSession
        rows = [(k, None if v is None else str(v)) for k, v in asdict(self.params).items()] + [("reason", self.reason)]
        spark.createDataFrame(rows, "key string, value string").write.mode("overwrite").parquet(f"{path}/params")

    @staticmethod
    def load(spark: SparkSession, path: str) -> SsdcModel:
        held = {r["key"]: r["value"] for r in spark.read.parquet(f"{path}/params").collect()}
        kinds = {"eps": float, "tau": float, "eim_fraction": float, "max_distance": float}
        kinds |= dict.fromkeys(("min_pts", "gamma", "beta", "rectify_n", "rectify_k", "seed", "max_iterations", "min_clusters"), int)
        kinds |= dict.fromkeys(("force_full_minpts", "finalize_eta"), lambda v: v == "True")
        params = SsdcParams(**{k: None if v is None else kinds.get(k, str)(v) for k, v in held.items() if k != "reason"})
        return SsdcModel(*[spark.read.parquet(f"{path}/{name}") for name in ("reps", "vertices", "trace")], params, held["reason"])


class _Drawer:
    """Slices of the permutation for the kernel, by ranges of its keys: scans with a filter, no shuffle of the points.

    Reads a stretch ahead, so that few jobs run.
    """

    def __init__(self, points: DataFrame, columns: list[str], seed: int, total: int, ahead: int):
        self.points, self.columns, self.seed, self.total, self.ahead = points, columns, seed, total, ahead
        self.ids, self.xs, self.high = np.zeros(0, np.int64), None, 0

    def __call__(self, a: int, b: int) -> tuple[np.ndarray, np.ndarray]:
        while len(self.ids) < min(b, self.total):
            stop = max(b, len(self.ids) + self.ahead)
            if stop > MAX_KERNEL + self.ahead:
                raise OverflowError("the sample outgrows the array kernel")
            # keys are spread evenly; some more than wanted come at once
            high = min(1 << 32, max(self.high + 1, int((stop + 4 * math.sqrt(stop)) / self.total * (1 << 32))))
            part = key_range(self.points.select("id", *self.columns), self.high, high, self.seed).withColumn("key", md5_key("id", self.seed))
            rows = part.toPandas().sort_values(["key", "id"])
            if self.columns == ["vec"]:
                xs = np.stack(rows["vec"].to_numpy()) if len(rows) else None
            else:
                xs = rows[self.columns].to_numpy()
            self.ids, self.high = np.concatenate([self.ids, rows["id"].to_numpy().astype(np.int64)]), high
            self.xs = xs if self.xs is None else self.xs if xs is None else np.concatenate([self.xs, xs])
        return self.ids[a:b], np.zeros((0, 1)) if self.xs is None else self.xs[a:b]


class Ssdc:
    """fit() draws, clusters, grows and tests the sample until its labels are stable."""

    def __init__(self, params: SsdcParams, engine: str = "auto"):
        self.params, self.engine = params.validate(), engine

    def fit(self, points: DataFrame) -> SsdcModel:
        """points: (id, x, y) or (id, vec).

        auto: the sample is grown by the array kernel on the driver while it has at most MAX_KERNEL points and their
        near pairs fit, beyond which it gets only where the labels never settle; then, or with engine="frames", it is
        grown on DataFrames.
        """
        if self.engine != "frames":
            try:
                return self._fit_arrays(points)
            except OverflowError:
                pass
        return self._fit_frames(permute(points, self.params.seed))

    def _fit_arrays(self, points: DataFrame) -> SsdcModel:
        p, spark, total = self.params, points.sparkSession, points.count()
        columns = ["vec"] if "vec" in points.columns else ["x", "y"]
        draw = _Drawer(points, columns, p.seed, total, p.gamma + 12 * p.beta + 2_000)
        fit = kernel.run(draw, total, p)
        vertices = spark.createDataFrame(
            [(int(a), int(b), str(c), int(d)) for a, b, c, d in zip(fit.ids, fit.n, fit.state, fit.cluster, strict=True)],
            "id long, n_eps long, state string, cluster long",
        )
        r = fit.reps
        where = [(v.tolist(),) for v in fit.xs[r].astype(float)] if columns == ["vec"] else [(int(x), int(y)) for x, y in fit.xs[r]]
        reps = spark.createDataFrame(
            [(int(fit.ids[i]), int(fit.cluster[i]), int(fit.n[i]), *w) for i, w in zip(r, where, strict=True)],
            "id long, cluster long, n_eps long, " + ("vec array<double>" if columns == ["vec"] else "x long, y long"),
        )
        names = [c.split()[0] for c in TRACE.split(", ")]
        trace = spark.createDataFrame([tuple(t[c] for c in names) for t in fit.trace], TRACE)
        return SsdcModel(reps, vertices, trace, p, fit.reason, fit)

    def _fit_frames(self, ranked: DataFrame) -> SsdcModel:
        """The same loop with the sample, its pairs and its states as checkpointed DataFrames; the driver sees counts."""
        p, spark, began = self.params, ranked.sparkSession, time.time()
        total = ranked.count()
        where = ["vec"] if "vec" in ranked.columns else ["x", "y"]
        part = lambda a, b: ranked.filter((F.col("rank") >= a) & (F.col("rank") < b)).select("id", *where)

        def reps(graph) -> DataFrame:
            return cut(representatives(graph.vertices, p.tau, p.selector).join(graph.sample, "id"))

        def label(points: DataFrame, held: DataFrame, name: str) -> DataFrame:
            return label_nearest(points, held, "auto", p.max_distance, p.eps).select("id", F.col("cluster").alias(name))

        def mean(counts: DataFrame) -> float:
            counts = counts.select("id", "n_eps")
            used = max(1, -(-int(counts.count() * p.eim_fraction * 1e9) // 10**9))
            key = F.md5(F.concat(F.lit("eta:"), F.col("id").cast("string")).cast("binary"))
            return counts.withColumn("k", key).orderBy("k").limit(used).agg(F.avg("n_eps")).first()[0]

        def clusters(graph) -> int:
            return graph.vertices.filter("cluster >= 0").select("cluster").distinct().count()

        gamma = min(p.gamma, total)
        graph = g.init_graph(part(0, gamma), lambda counts: next_threshold(mean(counts), 1, p.min_pts, p.eta_rule), p)
        eta = graph.eta
        k, held = clusters(graph), reps(graph)
        size = lambda k: test_size(total, max(1, k), rectify_n=p.rectify_n, rectify_k=p.rectify_k)
        n_test = min(size(k), total - gamma)
        used = gamma + n_test
        test = cut(part(gamma, used))
        before = cut(label(test, held, "prev_cluster"))
        rows, iteration, reason = [], 0, "exhausted"

        def log(delta: float | None) -> None:
            c = {r["state"]: r["count"] for r in graph.vertices.groupBy("state").count().collect()}
            n = sum(c.values())
            rows.append((iteration, eta, n, n_test, k, held.count(), delta, c.get("core", 0), c.get("border", 0), c.get("noise", 0), n, graph.pairs.count(), time.time() - began))

        log(None)
        policy = StopPolicy(p.min_pts, force_full_minpts=p.force_full_minpts, max_iterations=p.max_iterations)
        while used < total and iteration < p.max_iterations:
            iteration += 1
            stop = min(total, used + p.beta)
            if eta < p.min_pts:
                eta = next_threshold(mean(graph.vertices), eta, p.min_pts, p.eta_rule)
                graph = g.demote(graph, eta)
            graph = g.insert(graph, part(used, stop))
            used = stop
            k, held = clusters(graph), reps(graph)
            now = cut(before.join(label(test, held, "cur_cluster"), "id"))
            delta = float(instability(now).first()["delta"])
            before = now.select("id", F.col("cur_cluster").alias("prev_cluster"))
            more = size(k) - n_test
            if 0 < more <= total - used:
                grown = cut(part(used, used + more))
                before = cut(before.unionByName(label(grown, held, "prev_cluster")))
                test, n_test, used = cut(test.unionByName(grown)), n_test + more, used + more
            log(delta)
            why, raised = policy.after(iteration, delta if k >= p.min_clusters else 1.0, eta, total - used)
            if raised != eta:
                eta = raised
                graph = g.demote(graph, eta)
            if why:
                reason = "all_noise" if why == "stable" and not k else why
                break
        if p.finalize_eta and eta < p.min_pts:
            graph = g.demote(graph, p.min_pts)
        held = reps(graph).select("id", "cluster", "n_eps", *where)
        return SsdcModel(held, graph.vertices, spark.createDataFrame(rows, TRACE), p, reason)
