"""Structured Streaming forms: gates, phase telemetry, late rows, duplicates, cuts with state, joins and sinks."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from clipforge.operators.buckets import PRINTED, assign_bucket
from clipforge.operators.container import metadata_gate
from clipforge.sources.tables import SCHEMAS


def event_stream(spark: SparkSession, folder: str, per_trigger: int = 1) -> DataFrame:
    """The events of a folder of Parquet files, as they arrive; times become TIMESTAMP, which watermarks need."""
    s = spark.readStream.schema(SCHEMAS["events"]).option("maxFilesPerTrigger", per_trigger).parquet(folder)
    return s.withColumn("ts", F.col("ts").cast("timestamp"))


def stream_gate(media: DataFrame) -> DataFrame:
    """What passes all metadata checks; stateless, so it runs on streams as on tables."""
    return metadata_gate(media).filter(F.size("reasons") == 0).drop("reasons")


def with_lateness(src: DataFrame, delay: str = "1 hour", ts: str = "ts") -> DataFrame:
    return src.withWatermark(ts, delay)


def stream_phase(src: DataFrame, size: str, slide: str | None = None, gap: str | None = None) -> DataFrame:
    """Counts and sums per phase in tumbling or sliding windows, or per user in sessions."""
    if gap:
        by = [F.session_window("ts", gap).alias("w"), F.col("user_id")]
    else:
        by = [F.window("ts", size, slide).alias("w"), F.col("event_type")]
    out = src.groupBy(*by).agg(F.count("*").alias("n"), F.sum(F.col("value").cast("decimal(18,2)")).cast("double").alias("ms"))
    us = [F.unix_micros(F.col("w.start")).alias("start_us"), F.unix_micros(F.col("w.end")).alias("end_us")]
    return out.select(*us, *[c for c in out.columns if c != "w"])


def stream_dedup(src: DataFrame, key: str = "event_id", delay: str = "1 hour") -> DataFrame:
    """Each key once among those within the watermark's reach."""
    return src.withWatermark("ts", delay).dropDuplicatesWithinWatermark([key])


def stream_cuts(src: DataFrame, t: float, delay: str = "1 hour", keep_hours: int = 24 * 30) -> DataFrame:
    """(media_id, event_id, cut): the step from the user's last frame exceeds ``t``; the state is one value per user.

    Rows of a user are taken in time order within a batch; batches must come in
    time order, as files of a replay do. A user is forgotten once the watermark is
    ``keep_hours`` past their last frame, so the state does not grow without end.
    """
    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        last = state.get[0] if state.exists else None
        rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
        cuts = []
        for v in rows["value"]:
            cuts.append(last is not None and abs(v - last) > t)
            last = v
        state.update((float(last),))
        state.setTimeoutTimestamp(max(int(rows["ts"].max().timestamp() * 1000), state.getCurrentWatermarkMs()) + keep_hours * 3_600_000)
        yield pd.DataFrame({"media_id": key[0], "event_id": rows["event_id"].to_numpy(), "cut": cuts})

    timed = src.withWatermark("ts", delay)
    return timed.groupBy("user_id").applyInPandasWithState(step, "media_id long, event_id long, cut boolean", "last double", "append", GroupStateTimeout.EventTimeTimeout)


def stream_bucket(media: DataFrame) -> DataFrame:
    """Media with their bucket; the configuration is literals, so it needs no join."""
    return assign_bucket(media, PRINTED)


def stream_handoff(produced: DataFrame, wanted: DataFrame, minutes: int = 30) -> DataFrame:
    """Requests met by results of the same user in the ``minutes`` before: a join of two streams under watermarks."""
    p = produced.select("user_id", F.col("ts").alias("made_at"), F.col("event_id").alias("made")).withWatermark("made_at", "1 hour")
    w = wanted.select(F.col("user_id").alias("who"), F.col("ts").alias("asked_at"), F.col("event_id").alias("asked")).withWatermark("asked_at", "1 hour")
    return p.join(w, F.expr(f"user_id = who and made_at <= asked_at and made_at >= asked_at - interval {minutes} minutes")).select("made", "asked")


def run_stream(df: DataFrame, name: str, mode: str = "append", checkpoint: str | None = None):
    """Drains what is there into a memory table (for tests and small results) and stops."""
    writer = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True)
    if checkpoint:
        writer = writer.option("checkpointLocation", checkpoint)
    q = writer.start()
    q.awaitTermination()
    return df.sparkSession.table(name), q


def run_to_parquet(df: DataFrame, path: str, checkpoint: str) -> None:
    """Drains into Parquet, batch by batch; a batch that is run again replaces its own folder."""
    from clipforge.sources.sinks import foreach_batch_once

    q = df.writeStream.foreachBatch(foreach_batch_once(path)).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
