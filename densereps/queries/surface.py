"""Queries of the surrounding surface: scans, joins, aggregations, windows, functions, streams."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from densereps.functions import expr, sqlfuncs
from densereps.operators import exact, graph, neighbors, sampling, stability
from densereps.params import SsdcParams
from densereps.plans.lineage import cut, shared_dir
from densereps.queries import sql as S
from densereps.queries.methods import BASE, EPS, MIN_PTS, MINI, SNAPS, P
from densereps.queries.rounds import ROUNDS, in_order, rounds
from densereps.sources.points import load_documents, load_points, load_vectors, recipe, scale, validate_points
from densereps.streaming import streams

SURFACE: dict = {}
SURFACE_ORACLES: dict[str, str] = {}


def query(oracle: str | None = None):
    def register(f):
        SURFACE[f.__name__] = f
        if oracle is not None:
            SURFACE_ORACLES[f.__name__] = oracle
        return f

    return register


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def small(spark, sf_dir) -> DataFrame:
    return load_points(spark, sf_dir, "shapes9_small")


def labels(spark, sf_dir, name="shapes9_small", eps=EPS, min_pts=MIN_PTS) -> DataFrame:
    return exact.exact_density(load_points(spark, sf_dir, name), eps, min_pts)


LARGE = S.recursive(S.points("shapes9_large"), S.density("p", 30, 5))

# ---- scans and features

for _name, _key in {
    "shapes9_small": "scan_shapes_small", "shapes9_large": "scan_shapes_large", "shapes41_noise": "scan_shapes41", "blobs30": "scan_blobs30",
    "blobs31": "scan_blobs31", "events_xy": "scan_events_xy", "part_grid": "scan_part_grid",
}.items():
    SURFACE[_key] = lambda spark, sf_dir, n=_name: load_points(spark, sf_dir, n)
    SURFACE_ORACLES[_key] = recipe(_name, "duck")


@query(
    "SELECT doc_id AS id, CAST(floor(10000 * length(regexp_replace(text, '[ -~\n]', '', 'g')) / greatest(length(text), 1)) AS BIGINT) AS x, "
    "CAST(floor(100 * length(text) / len(regexp_split_to_array(text, '[ \t\n\r\f\v]+'))) AS BIGINT) AS y, lang AS truth FROM documents"
)
def docs_features(spark, sf_dir):
    return load_documents(spark, sf_dir)


@query("SELECT min(len(embedding)) AS min_width, max(len(embedding)) AS max_width, count(*) AS n FROM embeddings")
def embed_width_check(spark, sf_dir):
    return load_vectors(spark, sf_dir).agg(F.min(F.size("vec")).cast("long").alias("min_width"), F.max(F.size("vec")).cast("long").alias("max_width"), F.count(F.lit(1)).alias("n"))


@query("SELECT vec_id AS id, round(sqrt(list_sum(list_transform(embedding, lambda v: CAST(v AS DOUBLE) * CAST(v AS DOUBLE)))), 6) AS norm FROM embeddings")
def embed_norms(spark, sf_dir):
    return load_vectors(spark, sf_dir).select("id", F.round(F.sqrt(expr.dot("vec", "vec")), 6).alias("norm"))


@query("SELECT count(*) AS n, CAST(count(*) FILTER (WHERE value IS NULL) AS BIGINT) AS n_null, CAST(count(*) FILTER (WHERE isnan(value)) AS BIGINT) AS n_nan, CAST(count(*) FILTER (WHERE isinf(value)) AS BIGINT) AS n_infinite FROM events")
def validate_points_report(spark, sf_dir):
    return validate_points(table(spark, sf_dir, "events"), ["value"])


@query("SELECT p_partkey AS id, round((p_size - min(p_size) OVER ()) * 1.0 / (max(p_size) OVER () - min(p_size) OVER ()), 6) AS a, round((p_retailprice - min(p_retailprice) OVER ()) / (max(p_retailprice) OVER () - min(p_retailprice) OVER ()), 6) AS b FROM part")
def scale_minmax(spark, sf_dir):
    part = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), F.col("p_size").cast("double").alias("a"), F.col("p_retailprice").alias("b"))
    return scale(part, ["a", "b"]).select("id", F.round("a", 6).alias("a"), F.round("b", 6).alias("b"))


@query("SELECT p_partkey AS id, round((p_size - avg(p_size) OVER ()) / stddev_samp(p_size) OVER (), 5) AS a, round((p_retailprice - avg(p_retailprice) OVER ()) / stddev_samp(p_retailprice) OVER (), 5) AS b FROM part")
def scale_zscore(spark, sf_dir):
    part = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), F.col("p_size").cast("double").alias("a"), F.col("p_retailprice").alias("b"))
    return scale(part, ["a", "b"], "zscore").select("id", F.round("a", 5).alias("a"), F.round("b", 5).alias("b"))


@query(f"WITH {S.points('shapes9_large')} SELECT id, x, y FROM p WHERE x BETWEEN 2000 AND 3000 AND y < 2500")
def filter_bbox(spark, sf_dir):
    return load_points(spark, sf_dir, "shapes9_large").filter("x BETWEEN 2000 AND 3000 AND y < 2500").select("id", "x", "y")


@query(f"WITH {S.points('shapes9_large')} SELECT x // 100 AS cx, y // 100 AS cy, count(*) AS n FROM p GROUP BY 1, 2 HAVING count(*) >= 5")
def cell_histogram(spark, sf_dir):
    cells = load_points(spark, sf_dir, "shapes9_large").groupBy(expr.cell("x", 100).alias("cx"), expr.cell("y", 100).alias("cy"))
    return cells.agg(F.count(F.lit(1)).alias("n")).filter("n >= 5")


# ---- joins


@query("SELECT a.c_custkey AS a, b.c_custkey AS b FROM customer a JOIN customer b ON a.c_custkey < b.c_custkey AND abs(a.c_acctbal - b.c_acctbal) <= 1.0")
def band_join_1d(spark, sf_dir):
    """Pairs of accounts at most 1 apart: an equi-join on bands of that width and their neighbours."""
    held = table(spark, sf_dir, "customer").select("c_custkey", "c_acctbal", F.floor("c_acctbal").cast("long").alias("band"))
    left = held.select(F.col("c_custkey").alias("a"), F.col("c_acctbal").alias("va"), F.explode(F.array(*[F.col("band") + i for i in (-1, 0, 1)])).alias("band"))
    right = held.select(F.col("c_custkey").alias("b"), F.col("c_acctbal").alias("vb"), "band")
    return left.join(right, "band").filter("a < b AND abs(va - vb) <= 1.0").select("a", "b")


@query("SELECT CAST(0 AS BIGINT) AS only_grid, CAST(0 AS BIGINT) AS only_brute")
def brute_vs_grid_equal(spark, sf_dir):
    points = small(spark, sf_dir)
    a, b = cut(neighbors.range_probe(points, points, EPS)), cut(neighbors.range_probe(points, points, EPS, "brute"))
    return spark.createDataFrame([(a.exceptAll(b).count(), b.exceptAll(a).count())], "only_grid long, only_brute long")


KNN = (
    f"WITH {S.points('blobs30')}, {S.pairs('p', 'p', 600, 'pr')}, r AS (SELECT src AS id, CAST(row_number() OVER (PARTITION BY src ORDER BY d2, dst) AS INT) AS rank, dst AS neighbor, d2 FROM pr WHERE src <> dst) "
)


@query(KNN + "SELECT id, rank, neighbor, d2 FROM r WHERE rank <= 5")
def knn_k5(spark, sf_dir):
    """The nearest five, of those at most 600 away, as the SQL has it; knn_k5_all has no radius."""
    return neighbors.k_nearest(load_points(spark, sf_dir, "blobs30"), 5, 600).filter(F.col("d2") <= 600 * 600)


@query(KNN + ", k AS (SELECT d2 FROM r WHERE rank = 5) SELECT unnest([10, 50, 90]) AS pct, round(unnest([quantile_cont(d2, 0.1), quantile_cont(d2, 0.5), quantile_cont(d2, 0.9)]), 6) AS d2 FROM k")
def k_distance_curve(spark, sf_dir):
    """Of the points with five others at most 600 away, as the SQL has it; k_distance_curve_all has no radius."""
    return k_distance_quantiles(neighbors.k_distance(load_points(spark, sf_dir, "blobs30"), 5, 600).filter(F.col("d2") <= 600 * 600))


def k_distance_quantiles(far):
    row = far.agg(F.percentile("d2", F.array(F.lit(0.1), F.lit(0.5), F.lit(0.9))).alias("q"))
    return row.select(F.explode(F.arrays_zip(F.array(F.lit(10), F.lit(50), F.lit(90)).alias("pct"), "q")).alias("z")).select("z.pct", F.round("z.q", 6).alias("d2"))


KNN_ALL = (
    f"WITH {S.points('blobs30')}, r AS (SELECT a.id AS id, CAST(row_number() OVER (PARTITION BY a.id ORDER BY (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y), b.id) AS INT) AS rank, b.id AS neighbor, (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) AS d2 FROM p a JOIN p b ON a.id <> b.id) "
)


@query(KNN_ALL + "SELECT id, rank, neighbor, d2 FROM r WHERE rank <= 5")
def knn_k5_all(spark, sf_dir):
    """The nearest five of every point, at any distance."""
    return neighbors.k_nearest(load_points(spark, sf_dir, "blobs30"), 5, 600)


@query(KNN_ALL + ", k AS (SELECT d2 FROM r WHERE rank = 5) SELECT unnest([10, 50, 90]) AS pct, round(unnest([quantile_cont(d2, 0.1), quantile_cont(d2, 0.5), quantile_cont(d2, 0.9)]), 6) AS d2 FROM k")
def k_distance_curve_all(spark, sf_dir):
    """Over all points, the sparse ones too."""
    return k_distance_quantiles(neighbors.k_distance(load_points(spark, sf_dir, "blobs30"), 5, 600))


@query(S.recursive(P, S.density("p", 80, MIN_PTS)) + " SELECT id, state FROM st WHERE state <> 'core' AND EXISTS (SELECT 1 FROM pr JOIN st k ON k.id = dst AND k.state = 'core' WHERE src = st.id)")
def semi_core_neighbors(spark, sf_dir):
    pairs = cut(neighbors.range_pairs(small(spark, sf_dir), 80))
    states = cut(exact.classify(pairs, MIN_PTS))
    near = pairs.join(states.filter("state = 'core'").select(F.col("id").alias("dst")), "dst", "left_semi")
    return states.filter("state <> 'core'").join(near.select(F.col("src").alias("id")), "id", "left_semi").select("id", "state")


@query(S.recursive(P, S.density("p", 80, MIN_PTS)) + " SELECT id FROM st WHERE state = 'noise'")
def anti_noise(spark, sf_dir):
    touched = labels(spark, sf_dir, eps=80).filter("state <> 'noise'").select("id")
    return small(spark, sf_dir).select("id").join(touched, "id", "left_anti")


@query(
    S.recursive(P, S.density("p", 80, MIN_PTS, "0"), S.density("p", 100, MIN_PTS, "1"))
    + " SELECT coalesce(a.state, 'unknown') AS old_state, coalesce(b.state, 'unknown') AS new_state, count(*) AS n FROM lab0 a FULL JOIN lab1 b USING (id) GROUP BY 1, 2"
)
def full_outer_state_diff(spark, sf_dir):
    return graph.transitions(labels(spark, sf_dir, eps=80), labels(spark, sf_dir, eps=100))


@query(f"WITH {P} SELECT id FROM (SELECT id, row_number() OVER (ORDER BY md5('0:' || id)) AS r FROM p) WHERE r > 180")
def remainder_after_sample(spark, sf_dir):
    points = small(spark, sf_dir).select("id")
    return points.join(sampling.take(points, 180).select("id"), "id", "left_anti")


@query(f"WITH {P} SELECT 0 AS n_shared, CAST(count(*) - 180 - 117 AS BIGINT) AS n_left, count(*) AS n_union FROM p")
def sample_test_disjoint(spark, sf_dir):
    plan = sampling.SamplePlan(small(spark, sf_dir), 180, 180, 117)
    first, test, every = plan.prototype().select("id"), plan.test().select("id"), plan.ranked.select("id")
    left = every.exceptAll(first.unionByName(test))
    return spark.createDataFrame([(first.intersect(test).count(), left.count(), first.union(test).union(left).distinct().count())], "n_shared int, n_left long, n_union long")


@query("SELECT lang, count(*) AS n, min(doc_id) AS least FROM (SELECT *, row_number() OVER (PARTITION BY lang ORDER BY md5('0:' || doc_id), doc_id) AS r FROM documents) WHERE r <= 50 GROUP BY lang")
def stratified_sample_counts(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "lang")
    return sampling.stratified(docs, "lang", 50).groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.min("id").alias("least"))


# ---- aggregations


@query(BASE + ", j AS (SELECT cluster, truth FROM lab JOIN p USING (id)) SELECT cluster, truth, CAST(grouping(cluster, truth) AS BIGINT) AS level, count(*) AS n FROM j GROUP BY GROUPING SETS ((cluster, truth), (cluster), (truth), ())")
def contingency_grouping_sets(spark, sf_dir):
    return stability.contingency(labels(spark, sf_dir).join(small(spark, sf_dir).select("id", "truth"), "id"), "cluster", "truth")


@query(S.recursive(P, S.density("p", 80, MIN_PTS)) + " SELECT state, cluster, count(*) AS n FROM lab GROUP BY CUBE (state, cluster)")
def state_cluster_cube(spark, sf_dir):
    return labels(spark, sf_dir, eps=80).cube("state", "cluster").agg(F.count(F.lit(1)).alias("n"))


@query(BASE + " SELECT r_name, n_name, cluster, count(*) AS n FROM lab JOIN customer ON c_custkey = id JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY ROLLUP (r_name, n_name, cluster)")
def region_nation_cluster_rollup(spark, sf_dir):
    who = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("id"), "c_nationkey")
    places = table(spark, sf_dir, "nation").join(table(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    met = labels(spark, sf_dir).join(who, "id").join(F.broadcast(places), F.col("c_nationkey") == F.col("n_nationkey"))  # 25 nations
    return met.rollup("r_name", "n_name", "cluster").agg(F.count(F.lit(1)).alias("n"))


@query(LARGE + " SELECT cluster, count(*) AS n, min(x) AS x0, max(x) AS x1, min(y) AS y0, max(y) AS y1, round(avg(x), 6) AS mx, round(avg(y), 6) AS my, round(quantile_cont(x, 0.5), 6) AS median_x FROM lab JOIN p USING (id) GROUP BY cluster")
def cluster_profile(spark, sf_dir):
    met = labels(spark, sf_dir, "shapes9_large", 30, 5).join(load_points(spark, sf_dir, "shapes9_large"), "id")
    return met.groupBy("cluster").agg(
        F.count(F.lit(1)).alias("n"), F.min("x").alias("x0"), F.max("x").alias("x1"), F.min("y").alias("y0"), F.max("y").alias("y1"),
        F.round(F.avg("x"), 6).alias("mx"), F.round(F.avg("y"), 6).alias("my"), F.round(F.percentile("x", 0.5), 6).alias("median_x"),
    )


@query()
def approx_cluster_sizes(spark, sf_dir):
    return labels(spark, sf_dir, "shapes9_large", 30, 5).groupBy("cluster").agg(F.approx_count_distinct("id").alias("about"))


# ---- windows and top-k

SIZES = LARGE + ", z AS (SELECT cluster, count(*) AS n FROM lab WHERE cluster >= 0 GROUP BY cluster) "


@query(SIZES + "SELECT cluster, n, CAST(rank() OVER (ORDER BY n DESC) AS INT) AS place FROM z")
def cluster_size_rank(spark, sf_dir):
    sizes = labels(spark, sf_dir, "shapes9_large", 30, 5).filter("cluster >= 0").groupBy("cluster").agg(F.count(F.lit(1)).alias("n"))
    return sizes.withColumn("place", F.rank().over(W.orderBy(F.desc("n"))))  # a row for each cluster


@query(SIZES + "SELECT id, cluster, CAST(dense AS INT) AS dense FROM lab JOIN (SELECT cluster, dense_rank() OVER (ORDER BY cluster) AS dense FROM z) USING (cluster)")
def dense_cluster_ids(spark, sf_dir):
    found = cut(labels(spark, sf_dir, "shapes9_large", 30, 5).filter("cluster >= 0").select("id", "cluster"))
    ranked = found.select("cluster").distinct().withColumn("dense", F.dense_rank().over(W.orderBy("cluster")))  # a row for each cluster
    return found.join(ranked, "cluster").select("id", "cluster", "dense")


@query(BASE + " SELECT id, cluster, CAST(ntile(4) OVER (PARTITION BY cluster ORDER BY n_eps, id) AS INT) AS quartile FROM lab")
def density_quartiles(spark, sf_dir):
    return labels(spark, sf_dir).select("id", "cluster", F.ntile(4).over(W.partitionBy("cluster").orderBy("n_eps", "id")).alias("quartile"))


@query(f"WITH {ROUNDS} SELECT iteration, round(delta, 9) AS delta, round(delta - lag(delta) OVER (ORDER BY iteration), 9) AS step FROM t")
def delta_trend(spark, sf_dir):
    """Each round's disagreement of two labels, and its change from the round before."""
    return rounds(spark, sf_dir).select("iteration", F.round("delta", 9).alias("delta"), F.round(F.col("delta") - F.lag("delta").over(in_order()), 9).alias("step"))


@query(f"WITH {ROUNDS} SELECT iteration, CAST(sum(added) OVER (ORDER BY iteration ROWS UNBOUNDED PRECEDING) AS BIGINT) AS processed FROM t")
def processed_running_total(spark, sf_dir):
    return rounds(spark, sf_dir).select("iteration", F.sum("added").over(in_order().rowsBetween(W.unboundedPreceding, 0)).alias("processed"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n_hour FROM events")
def event_density_range_frame(spark, sf_dir):
    seconds = F.expr("timestampdiff(SECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', CAST(ts AS TIMESTAMP_NTZ))").cast("long")
    rows = table(spark, sf_dir, "events").select("event_id", "user_id", seconds.alias("s"))
    return rows.select("event_id", F.count(F.lit(1)).over(W.partitionBy("user_id").orderBy("s").rangeBetween(-3600, 0)).alias("n_hour"))


VERSIONS = [(1, "2024-01-01 00:00:00"), (2, "2024-01-08 12:00:00"), (3, "2024-01-20 06:30:00")]


@query("WITH m(version, since) AS (VALUES (1, TIMESTAMP '2024-01-01 00:00:00'), (2, TIMESTAMP '2024-01-08 12:00:00'), (3, TIMESTAMP '2024-01-20 06:30:00')) SELECT event_id, version FROM events ASOF LEFT JOIN m ON ts >= since")
def event_asof_model(spark, sf_dir):
    """The version in force at each event: a range join with a short table of versions and when each ends."""
    versions = spark.createDataFrame(VERSIONS, "version int, since string").withColumn("since", F.col("since").cast("timestamp_ntz"))
    spans = versions.withColumn("until", F.lead("since").over(W.orderBy("since")))  # a row for each version of the model
    events = table(spark, sf_dir, "events").withColumn("at", F.col("ts").cast("timestamp_ntz"))
    held = (F.col("at") >= F.col("since")) & (F.col("until").isNull() | (F.col("at") < F.col("until")))
    return events.join(F.broadcast(spans), held, "left").select("event_id", "version")


@query("SELECT CAST(json_extract(props, '$.k') AS INT) AS k, count(*) AS n, round(avg(value), 6) AS mean FROM events GROUP BY 1")
def props_json_feature(spark, sf_dir):
    rows = table(spark, sf_dir, "events").select(F.from_json("props", "k INT")["k"].alias("k"), "value")
    return rows.groupBy("k").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("value"), 6).alias("mean"))


EVENTS = S.recursive(S.points("events_xy"), S.density("p", 600, 10))


@query(EVENTS + " SELECT CAST(hour(ts) AS INT) AS hour, cluster >= 0 AS clustered, count(*) AS n FROM lab JOIN events ON event_id = id GROUP BY 1, 2")
def cluster_by_hour(spark, sf_dir):
    met = labels(spark, sf_dir, "events_xy", 600, 10).join(table(spark, sf_dir, "events").select(F.col("event_id").alias("id"), "ts"), "id")
    return met.groupBy(F.hour("ts").alias("hour"), (F.col("cluster") >= 0).alias("clustered")).agg(F.count(F.lit(1)).alias("n"))


@query(LARGE + " SELECT CAST(month(o_orderdate) AS INT) AS month, cluster, count(*) AS n FROM lab JOIN orders ON o_orderkey = id GROUP BY 1, 2")
def cluster_by_month(spark, sf_dir):
    met = labels(spark, sf_dir, "shapes9_large", 30, 5).join(table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("id"), "o_orderdate"), "id")
    return met.groupBy(F.month("o_orderdate").alias("month"), "cluster").agg(F.count(F.lit(1)).alias("n"))


# ---- functions

KERNELS = """
WITH v AS (SELECT vec_id AS id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS a FROM embeddings), w AS (SELECT id, a, list_reverse(a) AS b FROM v),
t AS (SELECT id, unnest(a) AS x, unnest(b) AS y FROM w)
SELECT id, round(sqrt(sum((x - y) * (x - y))), 6) AS l2, round(sum(abs(x - y)), 6) AS l1, round(max(abs(x - y)), 6) AS linf, round(sum(x * y) / sqrt(sum(x * x) * sum(y * y)), 6) AS cosine FROM t GROUP BY id
"""


@query(KERNELS)
def distance_kernels(spark, sf_dir):
    """Each vector against itself reversed."""
    rows = load_vectors(spark, sf_dir).select("id", F.col("vec").alias("a"), F.reverse("vec").alias("b"))
    return rows.select(
        "id", F.round(F.sqrt(expr.l2_squared("a", "b")), 6).alias("l2"), F.round(expr.l1("a", "b"), 6).alias("l1"),
        F.round(expr.l_infinity("a", "b"), 6).alias("linf"), F.round(expr.cosine("a", "b"), 6).alias("cosine"),
    )


@query("SELECT p_partkey AS id, round(sqrt(pow(p_size - 25, 2) + pow(p_retailprice - 950, 2)), 6) AS d FROM part")
def udf_distance(spark, sf_dir):
    part = table(spark, sf_dir, "part")
    a, b = F.array(F.col("p_size").cast("double"), "p_retailprice"), F.array(F.lit(25.0), F.lit(950.0))
    return part.select(F.col("p_partkey").alias("id"), F.round(sqlfuncs.distance_udf()(a, b), 6).alias("d"))


@query(f"WITH {S.points('blobs30')} SELECT id, x // 500 + i AS cx, y // 500 + j AS cy FROM p, (SELECT unnest([-1, 0, 1]) AS i), (SELECT unnest([-1, 0, 1]) AS j)")
def udtf_cells(spark, sf_dir):
    sqlfuncs.register(spark)
    return spark.sql("SELECT id, c.cx, c.cy FROM {p} p, LATERAL grid_cells(p.x, p.y, 500) c", p=load_points(spark, sf_dir, "blobs30"))


@query(BASE + ", j AS (SELECT cluster, truth FROM lab JOIN p USING (id)) SELECT nmi FROM (" + S.entropy_nmi("j", "cluster", "truth") + ")")
def udaf_nmi(spark, sf_dir):
    met = labels(spark, sf_dir).join(small(spark, sf_dir).select("id", "truth"), "id")
    return met.agg(sqlfuncs.nmi_udaf()("cluster", "truth").alias("nmi"))


# ---- streams


def _event_stream(spark, sf_dir) -> DataFrame:
    held = table(spark, sf_dir, "events")
    stream = spark.readStream.schema(held.schema).parquet(f"{sf_dir}/events*.parquet")
    return stream.withColumn("at", F.col("ts").cast("timestamp"))


def _name() -> str:
    return f"stream_{uuid.uuid4().hex}"


@query("SELECT time_bucket(INTERVAL '1 day', CAST(ts AS TIMESTAMP)) AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def stream_tumbling(spark, sf_dir):
    counted = streams.window_counts(_event_stream(spark, sf_dir), "at", ["event_type"], "1 day")
    return streams.drain(counted, _name(), "complete").select(F.col("start").cast("timestamp_ntz").alias("day"), "event_type", "n")


@query("SELECT time_bucket(INTERVAL '1 day', CAST(ts AS TIMESTAMP)) - k * INTERVAL '1 day' AS start, count(*) AS n FROM events, (SELECT unnest([0, 1]) AS k) GROUP BY 1")
def stream_sliding(spark, sf_dir):
    counted = streams.window_counts(_event_stream(spark, sf_dir), "at", [], "2 days", "1 day")
    return streams.drain(counted, _name(), "complete").select(F.col("start").cast("timestamp_ntz").alias("start"), "n")


@query("SELECT user_id, CAST(count(*) AS BIGINT) AS sessions FROM (SELECT user_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS before FROM events) WHERE before IS NULL OR ts - before >= INTERVAL '6 hours' GROUP BY user_id")
def stream_session(spark, sf_dir):
    found = streams.drain(streams.session_counts(_event_stream(spark, sf_dir), "at", "user_id", "6 hours"), _name(), "complete")
    return found.groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"))


@query("SELECT event_type AS key, count(*) AS n FROM events GROUP BY 1")
def stream_stateful_counts(spark, sf_dir):
    provider = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(provider)
    spark.conf.set(provider, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        rows = streams.drain(streams.running_counts(_event_stream(spark, sf_dir), "event_type"), _name(), "update")
    finally:
        spark.conf.set(provider, before)
    return rows.groupBy("key").agg(F.max("n").alias("n"))


SERVED = SsdcParams(eps=1200, min_pts=10, gamma=500, beta=250, tau=0.3)


@query("SELECT count(*) AS n, 0 AS n_different FROM events")
def stream_serve_labels(spark, sf_dir):
    """Labels served on the stream equal those of the batch."""
    from densereps.operators.ssdc import Ssdc

    points = load_points(spark, sf_dir, "events_xy")
    reps = cut(Ssdc(SERVED).fit(points).reps)
    minutes = F.expr("timestampdiff(MINUTE, TIMESTAMP_NTZ'2024-01-01 00:00:00', CAST(ts AS TIMESTAMP_NTZ))").cast("long")
    moving = _event_stream(spark, sf_dir).select(F.col("event_id").alias("id"), minutes.alias("x"), F.round(F.col("value") * 100).cast("long").alias("y"))
    served = streams.drain(streams.serve_labels(moving, reps), _name()).select("id", F.col("cluster").alias("live"))
    from densereps.operators.labeling import label_nearest

    both = label_nearest(points, reps, "arrow").join(served, "id")
    return both.agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("cluster") != F.col("live")).cast("int")).cast("int").alias("n_different"))


@query(S.recursive(P, S.sample("p", 0, 0, SNAPS[2], "s"), S.density("s", EPS, MIN_PTS)) + " SELECT id, n_eps, state, cluster FROM lab")
def stream_incremental_equals_batch(spark, sf_dir):
    """The graph after micro-batches of the permutation's slices, as SQL clusters them at once."""
    ranked = sampling.permute(small(spark, sf_dir), 0).select("id", "x", "y", "rank")
    at = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    for i, (a, b) in enumerate(((SNAPS[0], SNAPS[1]), (SNAPS[1], SNAPS[2]))):
        ranked.filter((F.col("rank") >= a) & (F.col("rank") < b)).drop("rank").coalesce(1).write.parquet(f"{at}/in/part={i}")
    first = graph.init_graph(ranked.filter(F.col("rank") < SNAPS[0]), MIN_PTS, MINI)
    stream = spark.readStream.schema("id long, x long, y long").option("maxFilesPerTrigger", 1).parquet(f"{at}/in/*")
    streams.incremental_stream(stream, first, f"{at}/out", f"{at}/checkpoint").awaitTermination()
    return spark.read.parquet(f"{at}/out/vertices/version=2").select("id", "n_eps", "state", "cluster")
