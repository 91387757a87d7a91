"""Streaming forms of the usage features. Each takes a streaming (or batch) DataFrame of events or contacts, so the
batch twin is the same expression over the same rows. Watermarks bound the state; ids are dropped with it."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EVENTS = "event_id BIGINT, ts TIMESTAMP_NTZ, user_id BIGINT, event_type STRING, value DOUBLE, props STRING"


def event_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """Event files as a stream; times become zoned, as watermarks want them."""
    rows = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def zoned(events: DataFrame) -> DataFrame:
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def live_usage(events: DataFrame, length: str = "1 day", late: str = "1 hour") -> DataFrame:
    """(start, user_id, n, total) for each tumbling window."""
    rows = events.withWatermark("ts", late).groupBy(F.window("ts", length), "user_id").agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    return rows.select(F.col("window.start").alias("start"), "user_id", "n", "total")


def live_sliding(events: DataFrame, length: str = "9 days", slide: str = "3 days", late: str = "1 hour") -> DataFrame:
    """(start, event_type, n, total) for windows that overlap: the last N periods together, renewed each period."""
    rows = events.withWatermark("ts", late).groupBy(F.window("ts", length, slide), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    return rows.select(F.col("window.start").alias("start"), "event_type", "n", "total")


def live_sessions(events: DataFrame, gap: str = "12 hours", late: str = "1 hour") -> DataFrame:
    """(start, end, user_id, n) of runs of activity without a pause of the gap."""
    rows = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))
    return rows.select(F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "user_id", "n")


def live_once(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Events with repeated ids left out, while the watermark remembers them (all, in a batch)."""
    if events.isStreaming:
        return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])
    return events.dropDuplicates(["event_id"])


def live_enrich(events: DataFrame, subscribers: DataFrame) -> DataFrame:
    """Events with the operator and state of their subscriber; the static side is read anew with each batch."""
    return events.join(subscribers.select(F.col("sub_id").alias("user_id"), "operator", "state"), "user_id", "left")


def live_pairs(events: DataFrame, within: str = "1 hour", late: str = "2 hours") -> DataFrame:
    """(user_id, error_at, next_at, next_type): what a user did within some time after an error."""
    errors = events.where("event_type = 'error'").select(F.col("user_id").alias("u"), F.col("ts").alias("error_at")).withWatermark("error_at", late)
    others = events.where("event_type <> 'error'").select("user_id", F.col("ts").alias("next_at"), F.col("event_type").alias("next_type")).withWatermark("next_at", late)
    soon = F.expr(f"u = user_id AND next_at >= error_at AND next_at <= error_at + INTERVAL {within}")
    return errors.join(others, soon).select("user_id", "error_at", "next_at", "next_type")


def live_idle(events: DataFrame, days: int = 3, late: str = "1 hour") -> DataFrame:
    """(user_id, last_seen, alarm): the time a user was last seen, with each batch; and an alarm when event time has moved
    `days` beyond it without a sign. State is one time a user, dropped with the alarm."""
    import pandas as pd

    def step(key, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            (last,) = state.get
            state.remove()
            yield pd.DataFrame({"user_id": [key[0]], "last_seen": [pd.Timestamp(last, unit="us")], "alarm": [True]})
            return
        last = state.get[0] if state.exists else 0
        for batch in batches:
            last = max(last, int(batch["us"].max()))
        state.update((last,))
        state.setTimeoutTimestamp(max(last // 1000 + days * 86_400_000, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame({"user_id": [key[0]], "last_seen": [pd.Timestamp(last, unit="us")], "alarm": [False]})

    rows = events.withWatermark("ts", late).withColumn("us", F.unix_micros("ts"))
    return rows.groupBy("user_id").applyInPandasWithState(step, "user_id BIGINT, last_seen TIMESTAMP, alarm BOOLEAN", "last BIGINT", "append", "EventTimeTimeout")


def live_arcs(contacts: DataFrame, path: str, checkpoint: str):
    """Keeps (src, dst, n_events, talk) partials: each batch's sums are written as a folder of its own, overwritten if the
    batch is repeated, so a restart counts nothing twice. `merged_arcs` adds the folders up."""

    def write(batch: DataFrame, number: int) -> None:
        sums = batch.groupBy("src", "dst").agg(F.count("*").alias("n_events"), F.sum("duration").alias("talk"))
        sums.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return contacts.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def merged_arcs(spark: SparkSession, path: str) -> DataFrame:
    rows = spark.read.schema("src BIGINT, dst BIGINT, n_events BIGINT, talk DOUBLE, batch INT").parquet(path)
    return rows.groupBy("src", "dst").agg(F.sum("n_events").alias("n_events"), F.sum("talk").alias("talk"))


def live_score(rows: DataFrame, fitted, keep: list[str]) -> DataFrame:
    """A stream of feature rows scored by a fitted booster: a projection, without state."""
    return fitted.model.score(rows, keep)


def run_to_end(stream: DataFrame, name: str, mode: str, checkpoint: str) -> DataFrame:
    """All available batches: what is appended into files beside the checkpoint, whatever its size; other modes into a table in
    memory (tests and small queries)."""
    spark, rows = stream.sparkSession, f"{checkpoint}/rows"
    if mode == "append":
        spark.createDataFrame([], stream.schema).write.mode("ignore").parquet(rows)
        to = stream.writeStream.format("parquet").option("path", rows)
    else:
        to = stream.writeStream.format("memory")
    to.queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(rows) if mode == "append" else spark.table(name)
