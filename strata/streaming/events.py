"""Streams of events around a model: scoring, windowed counts, sessions, running sums, refits."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from strata.functions.points import PointSet
from strata.operators import assign

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def stream(spark: SparkSession, path: str, files: str = "events.parquet", per_trigger: int = 1000) -> DataFrame:
    """The events table as a file stream. Watermarks need TIMESTAMP, so `ts` is taken in UTC."""
    raw = spark.readStream.schema(SCHEMA).option("pathGlobFilter", files).option("maxFilesPerTrigger", per_trigger).parquet(path)
    return raw.withColumn("ts", F.to_timestamp(F.concat(F.date_format("ts", "yyyy-MM-dd HH:mm:ss.SSSSSS"), F.lit("Z"))))


def points(events: DataFrame) -> PointSet:
    ts = F.timestamp_seconds(F.unix_micros("ts") / 1_000_000)
    seconds = F.pmod(F.floor(F.unix_micros("ts") / 1_000_000), F.lit(86_400))
    return PointSet(events.select(F.col("event_id").alias("point_id"), F.round(F.col("value") * 100).cast("long").alias("c0"), seconds.cast("long").alias("c1"), ts.alias("ts")), 2)


def score(events: DataFrame, c: np.ndarray) -> DataFrame:
    """Stateless, in any output mode: the centroids are literals."""
    return assign.by_literal(points(events), c)


def counts(scored: DataFrame, window: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    w = F.window("ts", window, slide) if slide else F.window("ts", window)
    return scored.withWatermark("ts", late).groupBy(w.alias("w"), "cluster_id").agg(F.count("*").alias("n")).select(F.unix_micros("w.start").alias("start_us"), "cluster_id", "n")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n"))
    return w.select("user_id", F.unix_micros("w.start").alias("start_us"), "n")


def deduplicated(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def running_sums(events: DataFrame, c: np.ndarray) -> DataFrame:
    """Counts and coordinate sums by cluster over all that has come: centroids are their quotients."""
    return score(events, c).groupBy("cluster_id").agg(F.count("*").alias("n"), F.sum("c0").alias("s_c0"), F.sum("c1").alias("s_c1"))


def late_rows(query) -> int:
    """Rows that a finished query's stateful operators left out because they came after the watermark."""
    return sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in p["stateOperators"])


def shared_folder(spark: SparkSession, name: str) -> str:
    """A folder that the driver and all executors reach: in the session's `spark.checkpoint.dir`, or, where a session names none (tests
    on one machine), one chosen here."""
    context = spark.sparkContext
    known = context._jsc.sc().getCheckpointDir()
    return f"{known.get() if known.isDefined() else context.getConf().get('spark.checkpoint.dir') or '/tmp/checkpoints'}/{name}"


def run_to_end(df: DataFrame, name: str, mode: str = "append", on_end: Callable | None = None) -> DataFrame:
    """Everything available. New rows (`append`) and whole results (`complete`, the last batch's) go from the executors to files in
    the shared folder, never through the driver; `update` uses a memory sink, for tests. `on_end` gets the finished query."""
    spark, folder = df.sparkSession, shared_folder(df.sparkSession, name)
    rows = f"{folder}/rows"
    writer = df.writeStream.queryName(name).outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{folder}/state")
    if mode == "append":
        query = writer.format("parquet").start(rows)
    elif mode == "complete":
        spark.createDataFrame([], df.schema).write.parquet(rows)  # where no batch comes
        query = writer.foreachBatch(lambda batch, number: batch.write.mode("overwrite").parquet(rows)).start()
    else:
        query = writer.format("memory").start()
    query.awaitTermination()
    if on_end:
        on_end(query)
    return spark.table(name) if mode == "update" else spark.read.schema(df.schema).parquet(rows)


def refit(events: DataFrame, fit: Callable[[DataFrame, int], None]) -> None:
    """Calls `fit` with each micro-batch and its number."""
    events.writeStream.foreachBatch(fit).trigger(availableNow=True).start().awaitTermination()
