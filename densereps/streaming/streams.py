"""Structured Streaming: growing the sample's graph by micro-batches, serving labels, counts by event time."""

from __future__ import annotations

import contextlib
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from densereps.operators import graph as g
from densereps.operators.labeling import label_nearest


def incremental_stream(batches: DataFrame, first: g.GraphState, out: str, checkpoint: str):
    """Inserts each micro-batch of points (id, x, y) into the graph.

    A version is written for each batch id, so that a batch that runs again after a restart overwrites its own
    version and starts from the one before it.
    """
    spark = batches.sparkSession
    sample, pairs, vertices = (f"{out}/{x}" for x in ("sample", "pairs", "vertices"))
    for name, frame in ((sample, first.sample), (pairs, first.pairs), (vertices, first.vertices)):
        frame.write.mode("overwrite").parquet(f"{name}/version=0")

    def insert(batch: DataFrame, batch_id: int) -> None:
        held = g.GraphState(*[spark.read.parquet(f"{x}/version={batch_id}") for x in (sample, pairs, vertices)], first.eta, first.params)
        new = batch.select("id", "x", "y").join(held.sample.select("id"), "id", "left_anti")
        after = g.insert(held, new)
        for name, frame in ((sample, after.sample), (pairs, after.pairs), (vertices, after.vertices)):
            frame.write.mode("overwrite").parquet(f"{name}/version={batch_id + 1}")

    return batches.writeStream.foreachBatch(insert).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def serve_labels(points: DataFrame, reps: DataFrame, max_distance: float | None = None) -> DataFrame:
    """A stream of points with cluster: a projection against the representatives, without state."""
    return label_nearest(points, reps, "array", max_distance)


def window_counts(events: DataFrame, time: str, keys: list[str], size: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Counts by event-time window; rows later than the watermark are dropped."""
    window = F.window(time, size, slide) if slide else F.window(time, size)
    counted = events.withWatermark(time, late).groupBy(window, *keys).agg(F.count(F.lit(1)).alias("n"))
    return counted.select(F.col("window.start").alias("start"), F.col("window.end").alias("end"), *keys, "n")


def session_counts(events: DataFrame, time: str, key: str, gap: str, late: str = "1 hour") -> DataFrame:
    counted = events.withWatermark(time, late).groupBy(F.session_window(time, gap), key).agg(F.count(F.lit(1)).alias("n"))
    return counted.select(F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), key, "n")


def deduplicated(events: DataFrame, time: str, key: str, late: str = "1 hour") -> DataFrame:
    return events.withWatermark(time, late).dropDuplicatesWithinWatermark([key])


class RunningCount(StatefulProcessor):
    """Rows seen of each key, kept across micro-batches."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.seen = handle.getValueState("seen", "n long")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timers) -> Iterator[pd.DataFrame]:
        total = (self.seen.get()[0] if self.seen.exists() else 0) + sum(len(pdf) for pdf in rows)
        self.seen.update((total,))
        yield pd.DataFrame({"key": [str(key[0])], "n": [total]})

    def close(self) -> None:
        pass


def running_counts(events: DataFrame, key: str) -> DataFrame:
    """(key, n) whenever a key grows; needs the RocksDB state store."""
    return events.groupBy(key).transformWithStateInPandas(RunningCount(), "key string, n long", "Update", "None")


def drain_to_files(stream: DataFrame, at: str) -> DataFrame:
    """All that a stream over files appends, as files under at, which all machines share; for outputs of any size."""
    query = stream.writeStream.format("parquet").option("path", f"{at}/out").option("checkpointLocation", f"{at}/checkpoint")
    query.outputMode("append").trigger(availableNow=True).start().awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(f"{at}/out")


@contextlib.contextmanager
def state_on_disk(spark: SparkSession):
    """Streams started within keep their state in RocksDB, not in the executors' heaps."""
    provider = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(provider)
    spark.conf.set(provider, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        yield
    finally:
        spark.conf.set(provider, before)


def drain(stream: DataFrame, name: str, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """All that a stream over files gives, as a table in memory; for tests and small outputs."""
    writer = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True)
    if checkpoint:
        writer = writer.option("checkpointLocation", checkpoint)
    query = writer.start()
    query.awaitTermination()
    return stream.sparkSession.table(name)
