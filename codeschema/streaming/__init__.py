"""Streams: operation logs in windows, sessions, source changes, changes of referenced objects."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..store import shared_folder


def event_stream(spark: SparkSession, path: str) -> DataFrame:
    """The events table as a stream; its time column becomes an instant, which watermarks need."""
    schema = spark.read.parquet(path).schema
    folder, _, name = path.rstrip("/").rpartition("/")
    return spark.readStream.schema(schema).option("pathGlobFilter", name).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def operations(events: DataFrame) -> DataFrame:
    """The operation each event stands for: container and kind."""
    k = F.get_json_object("props", "$.k").cast("int")
    deleted = k % 10 == 0
    container = F.when(deleted, "events").when(F.col("event_type").isin("view", "signup"), "customers").when(F.col("event_type") == "purchase", "orders").otherwise("events")
    kind = F.when(deleted, "D").when(F.col("event_type").isin("view", "click"), "R").when(F.col("event_type").isin("purchase", "signup"), "I").otherwise("U")
    return events.select("event_id", "ts", "user_id", container.alias("container"), kind.alias("kind"))


def tumbling(ops: DataFrame, width: str = "1 day", late: str = "1 hour") -> DataFrame:
    w = ops.withWatermark("ts", late).groupBy(F.window("ts", width), "container", "kind").agg(F.count("*").alias("n"))
    return w.select(F.col("window.start").alias("start"), "container", "kind", "n")


def sliding(ops: DataFrame, width: str = "1 day", step: str = "12 hours", late: str = "1 hour") -> DataFrame:
    w = ops.withWatermark("ts", late).groupBy(F.window("ts", width, step), "container").agg(F.count("*").alias("n"))
    return w.select(F.col("window.start").alias("start"), "container", "n")


def sessions(ops: DataFrame, gap: str = "12 hours", late: str = "1 hour") -> DataFrame:
    w = ops.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))
    return w.select(F.col("session_window.start").alias("start"), "user_id", "n")


def run_to_table(stream: DataFrame, name: str, mode: str = "complete") -> DataFrame:
    """Everything that is there now, processed as a stream into files in the shared folder, and read from them.

    ``complete``: each batch writes the whole result, the last one counts; ``append``: batches add up.
    """
    spark = stream.sparkSession
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex[:12]}"
    done: list[int] = []

    def put(df: DataFrame, batch: int) -> None:
        df.write.mode("overwrite").parquet(f"{path}/batch={batch}")
        done.append(batch)

    q = stream.writeStream.foreachBatch(put).option("checkpointLocation", f"{path}-state").outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    parts = sorted(set(done))[-1:] if mode == "complete" else sorted(set(done))
    if not parts:
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(*[f"{path}/batch={i}" for i in parts])


def first_last(ops: DataFrame, late: str = "1 hour") -> DataFrame:
    """The first and the last operation of each user and container so far, kept as state: (user_id, container, first_kind, last_kind, n)."""
    at = F.struct("ts", "event_id", "kind")
    g = ops.withWatermark("ts", late).groupBy("user_id", "container").agg(F.min(at).alias("a"), F.max(at).alias("z"), F.count("*").alias("n"))
    return g.select("user_id", "container", F.col("a.kind").alias("first_kind"), F.col("z.kind").alias("last_kind"), "n")


def enriched(changes: DataFrame, static: DataFrame, on: str) -> DataFrame:
    """A stream of changes with the duplicates of a stored side."""
    return changes.join(static, on, "left")


def matched_changes(hosts: DataFrame, referenced: DataFrame, within: str = "1 hour") -> DataFrame:
    """Host inserts with changes of what they refer to in the time before: (ref, ts) on both sides."""
    h = hosts.withWatermark("ts", within).select(F.col("ref").alias("h_ref"), F.col("ts").alias("h_ts"), *[c for c in hosts.columns if c not in ("ref", "ts")])
    r = referenced.withWatermark("ts", within).select(F.col("ref").alias("r_ref"), F.col("ts").alias("r_ts"), *[c for c in referenced.columns if c not in ("ref", "ts")])
    return h.join(r, F.expr(f"h_ref = r_ref AND r_ts <= h_ts AND r_ts >= h_ts - INTERVAL {within}"))


def once_each(stream: DataFrame, key: str = "event_id", late: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark([key])


def source_changes(files: DataFrame, handle: Callable[[DataFrame, int], None], label: str = "sources"):
    """New file versions as they come: each batch goes to ``handle`` (an incremental analysis)."""
    spark = files.sparkSession
    return files.writeStream.foreachBatch(handle).option("checkpointLocation", f"{shared_folder(spark)}/{label}-stream").trigger(availableNow=True).start()
