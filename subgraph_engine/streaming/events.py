"""Structured Streaming over events: windows, late rows, duplicates, growing components, state per user."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subgraph_engine.functions.components import star_components
from subgraph_engine.storage import shared_path, written_table

EVENT = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"
#: Watermark delay that drops nothing of a table that is read at once.
GENEROUS = "3650 days"


def event_stream(spark: SparkSession, folder: str, schema: str = EVENT, files_per_trigger: int = 8) -> DataFrame:
    """Files that come into a folder; ``ts`` as a timestamp, which watermarks need."""
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def staged(spark: SparkSession, sf_dir: str, files: int = 2) -> str:
    """The events table as a folder of files, as a stream source wants it."""
    path = shared_path(spark, "stream-in")
    spark.read.parquet(f"{sf_dir}/events.parquet").repartitionByRange(files, "ts").write.parquet(path)
    return path


def run_to_end(spark: SparkSession, rows: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a bounded stream (all that is available now) into a written table."""
    out, state = shared_path(spark, "stream-out"), shared_path(spark, "stream-state")
    if mode == "append":
        rows.writeStream.outputMode(mode).option("checkpointLocation", state).trigger(availableNow=True).format("parquet").start(out).awaitTermination()
    else:

        def keep(batch: DataFrame, _: int) -> None:
            batch.write.mode("overwrite").parquet(out)

        rows.writeStream.outputMode(mode).option("checkpointLocation", state).trigger(availableNow=True).foreachBatch(keep).start().awaitTermination()
    return spark.read.parquet(out)


def tumbling(events: DataFrame, width: str = "1 day", delay: str = GENEROUS) -> DataFrame:
    return events.withWatermark("ts", delay).groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))


def sliding(events: DataFrame, width: str = "2 days", step: str = "1 day", delay: str = GENEROUS) -> DataFrame:
    return events.withWatermark("ts", delay).groupBy(F.window("ts", width, step).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))


def sessions(events: DataFrame, gap: str = "6 hours", delay: str = GENEROUS) -> DataFrame:
    return events.withWatermark("ts", delay).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))


def without_repeats(events: DataFrame, delay: str = GENEROUS) -> DataFrame:
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def with_customers(events: DataFrame, customers: DataFrame) -> DataFrame:
    """Stream with a static table."""
    return events.join(customers, events["user_id"] == customers["c_custkey"])


def click_then_purchase(events: DataFrame, within: str = "1 hour", delay: str = "2 hours") -> DataFrame:
    """Stream with stream: a purchase of the same user at most so long after a click."""
    clicks = events.filter("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("u"), F.col("ts").alias("t0"))
    buys = events.filter("event_type = 'purchase'").select(F.col("event_id").alias("buy"), "user_id", F.col("ts").alias("t1"))
    clicks, buys = clicks.withWatermark("t0", delay), buys.withWatermark("t1", delay)
    near = F.expr(f"u = user_id AND t1 >= t0 AND t1 <= t0 + interval {within}")
    return clicks.join(buys, near).select("click", "buy")


LAST = "user_id long, event_id long, n long"


def last_events(events: DataFrame) -> DataFrame:
    """user_id, event_id, n: each user's latest event so far and how many there were, as they change."""

    def step(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        at, event_id, n = state.get if state.exists else (0, -1, 0)
        for rows in batches:
            n += len(rows)
            best = max(zip(rows["at"].tolist(), rows["event_id"].tolist()))
            at, event_id = max((at, event_id), best)
        state.update((at, event_id, n))
        yield pd.DataFrame({"user_id": [key[0]], "event_id": [event_id], "n": [n]})

    timed = events.select("user_id", "event_id", F.unix_micros("ts").alias("at"))
    return timed.groupBy("user_id").applyInPandasWithState(step, LAST, "at long, event_id long, n long", "update", "NoTimeout")


class GrowingComponents:
    """Components of edges that come in batches.

    A batch is contracted to edges between the components its ends are in so far;
    only those small edges go through the star contraction, and the components
    they name are renamed. Edges only ever join components, none is taken away.
    """

    def __init__(self, spark: SparkSession):
        self.spark = spark
        self.labels = spark.createDataFrame([], "vid long, component long")

    def add(self, edges: DataFrame) -> None:
        ends = edges.select(F.col("src").alias("vid")).unionByName(edges.select(F.col("dst").alias("vid"))).distinct()
        known = self.labels.unionByName(ends.join(self.labels, "vid", "left_anti").select("vid", F.col("vid").alias("component")))
        known = written_table(self.spark, known, "grow-known")
        a = known.select(F.col("vid").alias("src"), F.col("component").alias("a"))
        b = known.select(F.col("vid").alias("dst"), F.col("component").alias("b"))
        contracted = edges.join(a, "src").join(b, "dst").filter("a <> b").select(F.col("a").alias("src"), F.col("b").alias("dst")).distinct()
        names = star_components(self.spark, contracted).select(F.col("vid").alias("component"), F.col("component").alias("_new"))
        renamed = known.join(names, "component", "left").select("vid", F.coalesce("_new", "component").alias("component"))
        self.labels = written_table(self.spark, renamed, "grow-labels")

    def follow(self, edges: DataFrame) -> DataFrame:
        """Runs a stream of src, dst to its present end; returns vid, component."""
        state = shared_path(self.spark, "stream-state")
        stream = edges.writeStream.option("checkpointLocation", state).trigger(availableNow=True)
        stream.foreachBatch(lambda batch, _: self.add(batch)).start().awaitTermination()
        return self.labels
