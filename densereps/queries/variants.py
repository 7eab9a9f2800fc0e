"""Queries of variants, fixed-sample snapshots of the loop, and further joins, scans and streams."""

from __future__ import annotations

import os
import time
import uuid

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from densereps.operators import exact, graph, halo, labeling, metrics, neighbors, testsize
from densereps.operators import representatives as reps_
from densereps.params import SsdcParams
from densereps.plans.lineage import shared_dir
from densereps.queries import sql as S
from densereps.queries.methods import BASE, EPS, MIN_PTS, SNAP_ETA, SNAPS, TAU, P, _snap, _summary, prefix, query, small
from densereps.queries.rounds import ROUNDS, RUNS, in_order, placed, rounds, runs
from densereps.queries.surface import table
from densereps.sources.points import load_points, read_points, recipe
from densereps.streaming import streams

# ---- exact clustering by tiles; in order of visits


@query(BASE + " SELECT id, n_eps, state, cluster FROM lab")
def exact_density_halo(spark, sf_dir):
    return halo.exact_density_tiles(small(spark, sf_dir), EPS, MIN_PTS, side=700)


@query(_summary("events_xy", 600, 10))
def exact_density_halo_events(spark, sf_dir):
    return metrics.n_clusters(halo.exact_density_tiles(load_points(spark, sf_dir, "events_xy"), 600, 10))


@query(
    S.recursive(S.points("blobs31"), S.density("p", 80, 5))
    + """, t AS (SELECT unnest(CASE WHEN state = 'core' THEN ['unknown>core'] WHEN state = 'noise' THEN ['unknown>noise']
WHEN id < cluster THEN ['unknown>noise', 'noise>border'] ELSE ['unknown>border'] END) AS step FROM lab) SELECT step, count(*) AS n FROM t GROUP BY step"""
)
def exact_visit_transitions(spark, sf_dir):
    return exact.visit_transitions(exact.exact_density(load_points(spark, sf_dir, "blobs31"), 80, 5))


# ---- merges, labels and representatives of fixed samples

ANY = SsdcParams(eps=EPS, min_pts=MIN_PTS, gamma=180, beta=180, tau=TAU, merge_on="any")
LAZY = SsdcParams(eps=EPS, min_pts=MIN_PTS, gamma=180, beta=180, tau=TAU, relabel="lazy")


@query(
    S.recursive(P, _snap(0, "0", 4), _snap(1, "1", 4))
    + """, j AS (SELECT DISTINCT u.cluster AS a, v.cluster AS b FROM pr1 JOIN lab1 u ON u.id = src AND u.state = 'core' JOIN lab1 v ON v.id = dst AND v.state = 'border'
      LEFT JOIN lab0 o ON o.id = src WHERE coalesce(o.state, '') <> 'core' AND u.cluster <> v.cluster),
j2 AS (SELECT a, b FROM j UNION SELECT b, a FROM j),
mk(id, low) USING KEY (id) AS (SELECT DISTINCT cluster, cluster FROM lab1 WHERE cluster >= 0 UNION
     SELECT j2.b, min(mk.low) FROM mk JOIN j2 ON mk.id = j2.a JOIN recurring.mk AS r ON r.id = j2.b WHERE mk.low < r.low GROUP BY j2.b)
SELECT lab1.id, n_eps, state, coalesce(low, -1) AS cluster FROM lab1 LEFT JOIN mk ON mk.id = lab1.cluster"""
)
def ssdc_merge_on_any(spark, sf_dir):
    first = graph.init_graph(prefix(spark, sf_dir, 0, SNAPS[0]), 4, ANY)
    return graph.insert(first, prefix(spark, sf_dir, SNAPS[0], SNAPS[1])).vertices


@query(
    S.recursive(P, _snap(0, "0", 2), _snap(0, "9", 5))
    + """, m AS (SELECT lab0.cluster AS old, min(cc9.cluster) AS low FROM cc9 JOIN lab0 USING (id) GROUP BY 1),
k AS (SELECT cc9.id, low AS cluster FROM cc9 JOIN lab0 USING (id) JOIN m ON m.old = lab0.cluster),
b AS (SELECT src AS id, min(k.cluster) AS cluster FROM pr9 JOIN st9 ON st9.id = src AND state = 'border' JOIN k ON k.id = dst GROUP BY src)
SELECT st9.id, n_eps, state, coalesce(k.cluster, b.cluster, -1) AS cluster FROM st9 LEFT JOIN k USING (id) LEFT JOIN b USING (id)"""
)
def ssdc_lazy_demotion(spark, sf_dir):
    return graph.demote(graph.init_graph(prefix(spark, sf_dir, 0, SNAPS[0]), 2, LAZY), 5).vertices


def _last(spark, sf_dir) -> graph.GraphState:
    return graph.init_graph(prefix(spark, sf_dir, 0, SNAPS[2]), SNAP_ETA[2], ANY)


LAST = S.recursive(P, _snap(2, "2"), S.reps("lab2", TAU, "r2"), "x2 AS (SELECT r2.*, x, y FROM r2 JOIN p USING (id))", S.nearest("p", "x2", "nn"))


@query(LAST + " SELECT id, cluster, n_eps FROM r2")
def snapshot_representatives(spark, sf_dir):
    return reps_.representatives(_last(spark, sf_dir).vertices, TAU).select("id", "cluster", "n_eps")


@query(LAST + " SELECT p.id, coalesce(lab2.cluster, nn.cluster, -1) AS cluster FROM p LEFT JOIN lab2 USING (id) LEFT JOIN nn USING (id)")
def snapshot_labels(spark, sf_dir):
    """Labels of all points: the sample's from its graph, the others' from the nearest representative."""
    state, points = _last(spark, sf_dir), small(spark, sf_dir)
    reps = reps_.representatives(state.vertices, TAU).join(state.sample, "id")
    near = labeling.label_nearest(points, reps, "arrow", reach=EPS)
    return near.join(state.vertices.select("id", F.col("cluster").alias("own")), "id", "left").select("id", F.coalesce("own", "cluster").alias("cluster"))


@query(LAST + " SELECT p.id, coalesce(nn.cluster, -1) AS cluster FROM p LEFT JOIN nn USING (id)")
def nearest_rep_labels_cells(spark, sf_dir):
    state = _last(spark, sf_dir)
    reps = reps_.representatives(state.vertices, TAU).join(state.sample, "id")
    return labeling.label_nearest(small(spark, sf_dir), reps, "grid", reach=60).select("id", "cluster")


# ---- closed forms and run tables

PROBS = [0.5, 0.9, 0.99]


@query(
    f"WITH {ROUNDS}, w AS (SELECT iteration, sum(c) AS n, count(*) AS k, avg(ln(c)) AS l FROM (SELECT iteration, a, count(*) AS c FROM o GROUP BY iteration, a) GROUP BY iteration), "
    f"v AS (SELECT *, pow(prob, 1.0 / (2 * k)) / exp(l - ln(n)) AS g FROM w, (SELECT CAST(unnest({PROBS}) AS DOUBLE) AS prob)) "
    "SELECT iteration, CAST(n AS BIGINT) AS n, prob, k, CAST(least(n, ceil(round((1 + sqrt(1 + 4.0 * n * g)) / 2.0, 6))) AS BIGINT) AS alpha FROM v"
)
def test_size_shares(spark, sf_dir):
    """Test sizes for the unequal shares of a round's shapes and a chance below one."""
    counts = placed(spark, sf_dir).groupBy("iteration", "a").agg(F.count(F.lit(1)).alias("c"))
    return testsize.test_size_shares(counts, "iteration", PROBS)


test_size_shares.__test__ = False


@query(
    f"WITH {ROUNDS}, s AS (SELECT iteration, k, sum(added) OVER (ORDER BY iteration ROWS UNBOUNDED PRECEDING) AS n, row_number() OVER (ORDER BY iteration) - 1 AS i FROM t), "
    "m AS (SELECT *, ceil(round((1 + sqrt(1 + 4.0 * n * k)) / 2.0, 9)) AS m FROM s) SELECT CAST(i AS INT) AS iteration, "
    "CAST(CASE WHEN i = 0 THEN 180.0 * 180 ELSE 180.0 * n + n + m * m + m * k END AS DOUBLE) AS predicted FROM m"
)
def predicted_cost_table(spark, sf_dir):
    """The cost of each round, whose sample is all points so far."""
    sample = F.sum("added").over(in_order().rowsBetween(W.unboundedPreceding, 0))
    grown = rounds(spark, sf_dir).select((F.row_number().over(in_order()) - 1).alias("iteration"), sample.alias("n"), "k")
    return metrics.predicted_cost(testsize.test_size_table(grown).withColumnsRenamed({"n": "n_sample", "alpha": "n_test"}), ANY)


@query(f"WITH {RUNS} SELECT k, count(*) AS n, round(count(*) * 1.0 / sum(count(*)) OVER (), 6) AS share FROM r GROUP BY k")
def k_frequency_table(spark, sf_dir):
    return metrics.k_frequency(runs(spark, sf_dir))


@query(
    f"WITH {RUNS} SELECT count(*) AS runs, round(avg(k), 6) AS mean_k, round(stddev_samp(k), 6) AS sd_k, "
    "round(avg(agreement), 6) AS mean_agreement, round(stddev_samp(agreement), 6) AS sd_agreement FROM r"
)
def run_summary_table(spark, sf_dir):
    return metrics.mean_and_deviation(runs(spark, sf_dir), [], ["k", "agreement"])


# ---- joins


@query(
    f"WITH {P} SELECT a.id AS src, b.id AS dst FROM p a JOIN p b ON abs(a.x // {EPS} - b.x // {EPS}) <= 1 AND abs(a.y // {EPS} - b.y // {EPS}) <= 1"
)
def cell_join_candidates(spark, sf_dir):
    return neighbors.cell_candidates(small(spark, sf_dir), EPS).select("src", "dst")


@query(
    f"WITH {P}, c AS (SELECT truth, avg(x) AS cx, avg(y) AS cy FROM p GROUP BY truth) SELECT id, t.truth AS shape FROM p, LATERAL "
    "(SELECT c.truth FROM c ORDER BY (p.x - cx) * (p.x - cx) + (p.y - cy) * (p.y - cy), c.truth LIMIT 2) t"
)
def nearest_shapes_lateral(spark, sf_dir):
    """The two nearest shapes of each point, by a lateral top-k over a short table."""
    points = small(spark, sf_dir)
    return spark.sql(
        "WITH c AS (SELECT truth, avg(x) AS cx, avg(y) AS cy FROM {points} GROUP BY truth) SELECT p.id, t.truth AS shape FROM {points} p, LATERAL "
        "(SELECT truth FROM (SELECT c.truth, (p.x - cx) * (p.x - cx) + (p.y - cy) * (p.y - cy) AS d FROM c) ORDER BY d, truth LIMIT 2) t",
        points=points,
    )


@query(
    "SELECT a.event_id AS first, b.event_id AS second FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 2 HOUR"
)
def event_interval_join(spark, sf_dir):
    """Events of a user within two hours after another: an equi-join on hour slots, then the interval."""
    events = table(spark, sf_dir, "events").select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts"))
    slot = F.floor(F.unix_seconds("ts") / 7200)
    a = events.select(F.col("event_id").alias("first"), "user_id", F.col("ts").alias("t0"), F.explode(F.array(slot, slot + 1)).alias("slot"))
    b = events.select(F.col("event_id").alias("second"), "user_id", F.col("ts").alias("t1"), slot.alias("slot"))
    return a.join(b, ["user_id", "slot"]).filter("t1 > t0 AND t1 <= t0 + INTERVAL 2 HOURS").select("first", "second")


# ---- sources and sinks


def _kept(spark, kind: str) -> str:
    return os.path.join(shared_dir(spark), f"densereps-{kind}-{uuid.uuid4().hex}")


@query(recipe("shapes9_small", "duck"))
def scan_points_csv(spark, sf_dir):
    small(spark, sf_dir).write.option("header", True).csv(path := _kept(spark, "csv"))
    return read_points(spark, path, "csv")


@query(recipe("shapes9_small", "duck"))
def scan_points_json(spark, sf_dir):
    small(spark, sf_dir).write.json(path := _kept(spark, "json"))
    return read_points(spark, path, "json")


@query(S.recursive(P, S.sample("p", 0, 297, 477, "s")) + " SELECT id, x, y FROM s")
def scan_pruned_batch(spark, sf_dir):
    """The first increment, read from a layout by slice."""
    from densereps.operators.sampling import SamplePlan

    SamplePlan(small(spark, sf_dir), 180, 180, 117).write(path := _kept(spark, "plan"))
    return spark.read.parquet(path).filter("slice = 'inc1'").select("id", "x", "y")


# ---- streams


@query(
    "WITH o AS (SELECT event_id, CAST(ts AS TIMESTAMP) AS ts, ts >= TIMESTAMP '2024-01-15' AS early FROM events), f AS (SELECT min(event_id) AS one FROM o WHERE early), "
    "m AS (SELECT max(ts) AS top FROM o, f WHERE early AND event_id <> one) "
    "SELECT time_bucket(INTERVAL 1 DAY, ts) AS day, count(*) AS n FROM o, m WHERE early OR time_bucket(INTERVAL 1 DAY, ts) + INTERVAL 1 DAY > top - INTERVAL 10 DAY GROUP BY 1"
)
def stream_late(spark, sf_dir):
    """Daily counts of a stream whose last file holds older events: days closed by the watermark take no more rows.

    A batch drops what was late when the batch before it began, so a file with one event comes between.
    """
    events = table(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("at"))
    early = F.col("at") >= F.lit("2024-01-15").cast("timestamp")
    one = F.col("event_id") == events.filter(early).agg(F.min("event_id")).first()[0]
    path = _kept(spark, "late")
    for name, rows in (("a", events.filter(early & ~one)), ("b", events.filter(one)), ("c", events.filter(~early))):
        rows.select("at").coalesce(1).write.parquet(f"{path}/{name}")
        time.sleep(1.1)  # files are taken in the order of their times
    stream = spark.readStream.schema("at timestamp").option("maxFilesPerTrigger", 1).parquet(f"{path}/*")
    seen = streams.drain(streams.window_counts(stream, "at", [], "1 day", late="10 days"), f"late_{uuid.uuid4().hex}", "update")
    return seen.groupBy(F.col("start").cast("timestamp_ntz").alias("day")).agg(F.max("n").alias("n"))


@query("SELECT event_type, count(DISTINCT event_id) AS n FROM events GROUP BY 1")
def stream_deduplicated(spark, sf_dir):
    """A stream that brings each event twice, once in each of two folders; what it lets through is written, not collected."""
    events = table(spark, sf_dir, "events").select("event_id", "event_type", F.col("ts").cast("timestamp").alias("at"))
    path = _kept(spark, "twice")
    for name in "ab":
        events.write.parquet(f"{path}/{name}")
    stream = spark.readStream.schema(events.schema).parquet(f"{path}/*")
    with streams.state_on_disk(spark):
        once = streams.drain_to_files(streams.deduplicated(stream, "at", "event_id", "365 days"), _kept(spark, "once"))
    return once.groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))

