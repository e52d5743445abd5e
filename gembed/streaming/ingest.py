"""Edges as streams: windows, late data, running degrees, and appends to the bucket store."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import scratch


def event_stream(spark: SparkSession, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    """Files as a stream; event times without a zone are taken in the session's zone, as watermarks need one."""
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling(events: DataFrame, length: str = "1 day", late: str = "1 day") -> DataFrame:
    """(window_start, user_id, n); batch and stream alike."""
    rows = events.withWatermark("ts", late) if events.isStreaming else events
    return rows.groupBy(F.window("ts", length).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("window_start"), "user_id", "n")


def sliding(events: DataFrame, length: str = "1 day", step: str = "6 hours", late: str = "1 day") -> DataFrame:
    rows = events.withWatermark("ts", late) if events.isStreaming else events
    return rows.groupBy(F.window("ts", length, step).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("window_start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "12 hours", late: str = "1 day") -> DataFrame:
    rows = events.withWatermark("ts", late) if events.isStreaming else events
    return rows.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("session_start"), F.col("w.end").alias("session_end"), "user_id", "n")


def deduplicated(events: DataFrame, late: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def view_then_purchase(events: DataFrame, within: str = "1 hour", late: str = "1 day") -> DataFrame:
    """Pairs of a view and a later purchase of the same user: an interval join, of streams or tables."""
    mark = (lambda df: df.withWatermark("ts", late)) if events.isStreaming else (lambda df: df)
    views = mark(events.where("event_type = 'view'")).select(F.col("user_id").alias("v_user"), F.col("ts").alias("v_ts"), F.col("event_id").alias("view_id"))
    buys = mark(events.where("event_type = 'purchase'")).select(F.col("user_id").alias("b_user"), F.col("ts").alias("b_ts"), F.col("event_id").alias("purchase_id"))
    return views.join(buys, F.expr(f"v_user = b_user and b_ts > v_ts and b_ts <= v_ts + interval {within}")).select(F.col("v_user").alias("user_id"), "view_id", "purchase_id")


def with_static(events: DataFrame, side: DataFrame, key: str) -> DataFrame:
    """A stream joined with a table: every micro-batch looks its keys up, no state is kept."""
    return events.join(side, key)


def edges_of(events: DataFrame) -> DataFrame:
    return events.select(F.lit("did").alias("rel"), F.col("user_id").cast("string").alias("src"), F.col("event_type").alias("dst"), F.lit(1).cast("long").alias("weight"))


def running_degrees(events: DataFrame) -> DataFrame:
    """(key, degree, first_seen) per node, kept as state: transformWithState on a stream."""
    from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

    class Degree(StatefulProcessor):
        def init(self, handle: StatefulProcessorHandle) -> None:
            self.n = handle.getValueState("n", "degree long, first_seen timestamp")

        def handleInputRows(self, key, rows, timers):
            import pandas as pd

            now = self.n.get() if self.n.exists() else None
            degree, first = (now[0], now[1]) if now else (0, None)
            for batch in rows:
                degree += len(batch)
                least = batch["ts"].min().to_pydatetime()
                first = least if first is None or least < first else first
            self.n.update((int(degree), first))
            yield pd.DataFrame({"key": [key[0]], "degree": [int(degree)], "first_seen": [first]})

        def close(self) -> None:
            pass

    keyed = events.select(F.col("user_id").cast("string").alias("key"), "ts")
    return keyed.groupBy("key").transformWithStateInPandas(Degree(), outputStructType="key string, degree long, first_seen timestamp", outputMode="Update", timeMode="None")


def run_all(stream: DataFrame, sink: Callable[[DataFrame, int], None], mode: str = "append") -> None:
    """Runs a stream over all that is there now, batch by batch, and stops."""
    spark = stream.sparkSession
    q = stream.writeStream.outputMode(mode).foreachBatch(sink).option("checkpointLocation", scratch(spark, "stream-checkpoint")).trigger(availableNow=True).start()
    q.awaitTermination()


def append_buckets(stream: DataFrame, folder: str) -> None:
    """Appends each micro-batch's edges to the bucket store; a batch that is replayed replaces itself."""

    def sink(batch: DataFrame, number: int) -> None:
        edges_of(batch).groupBy("rel", "src", "dst").agg(F.sum("weight").alias("weight")).write.mode("overwrite").parquet(f"{folder}/batch={number}")

    run_all(stream, sink)
