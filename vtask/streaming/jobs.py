"""Scoring of streams against frozen parameters, and alert windows over the scores."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Stand-in for a fitted detector on events: nominal levels of `value` by type, frozen before the stream starts.
CUTS = (25.0, 50.0, 75.0, 100.0, 150.0)


def stream_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a file stream."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 16).parquet(f"{sf_dir}/[e]vents.parquet").withColumn("ts", F.col("ts").cast("timestamp"))


def score_events(events: DataFrame, cuts: tuple[float, ...] = CUTS) -> DataFrame:
    """Stateless: a projection with frozen literals."""
    above = F.size(F.filter(F.array(*(F.lit(c) for c in cuts)), lambda q: q > F.col("value")))
    return events.withColumn("surprisal", F.round(-F.log((above + 1) / F.lit(float(len(cuts) + 1))), 6))


def alert_windows(scored: DataFrame, width: str, slide: str | None = None, delay: str = "10 minutes", cut: float = 1.0) -> DataFrame:
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    g = scored.withWatermark("ts", delay).groupBy(w.alias("w"))
    return g.agg(F.sum((F.col("surprisal") >= cut).cast("long")).alias("alerts"), F.count("*").alias("n")).select(F.unix_timestamp("w.start").alias("start_s"), "alerts", "n")


def alert_sessions(scored: DataFrame, gap: str, delay: str = "10 minutes", cut: float = 1.0) -> DataFrame:
    hot = scored.filter(F.col("surprisal") >= cut).withWatermark("ts", delay)
    return hot.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("user_id", F.unix_timestamp("w.start").alias("start_s"), "n")


def dedup(stream: DataFrame, key: str, delay: str = "10 minutes") -> DataFrame:
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark([key])


def drift(scored: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Mean surprisal by hour, to be held against its calibrated mean of about one."""
    return scored.withWatermark("ts", delay).groupBy(F.window("ts", "1 hour").alias("w")).agg(F.avg("surprisal").alias("mean_surprisal"))


def user_state(scored: DataFrame, idle: str = "30 days", delay: str = "1 hour", cut: float = 1.0) -> DataFrame:
    """(user_id, n, alerts, peak) so far, updated batch by batch: three numbers a user, dropped once the watermark is `idle` past the last event.

    A null surprisal counts as an event without alert; rows behind the watermark
    are dropped by the engine before they get here.
    """
    import pandas as pd

    wait = int(pd.Timedelta(idle).total_seconds() * 1000)

    def step(key, batches, state):
        if state.hasTimedOut:
            state.remove()
            return
        n, alerts, peak = state.get if state.exists else (0, 0, 0.0)
        last = 0
        for b in batches:
            n, alerts = n + len(b), alerts + int((b["surprisal"] >= cut).sum())
            top = b["surprisal"].max()
            peak = peak if pd.isna(top) else max(peak, float(top))
            if b["ts"].notna().any():
                last = max(last, int(b["ts"].max().timestamp() * 1000))
        state.update((n, alerts, peak))
        state.setTimeoutTimestamp(max(last, state.getCurrentWatermarkMs()) + wait)
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "alerts": [alerts], "peak": [peak]})

    kind = scored.schema["user_id"].dataType.simpleString()
    few = scored.select("user_id", "ts", "surprisal").withWatermark("ts", delay)
    return few.groupBy("user_id").applyInPandasWithState(step, f"user_id {kind}, n long, alerts long, peak double", "n long, alerts long, peak double", "update", "EventTimeTimeout")


def run_once(stream: DataFrame, name: str, mode: str) -> DataFrame:
    """Process what is there, into a table in memory; for tests and small results."""
    name = f"{name}_{uuid.uuid4().hex[:8]}"
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return stream.sparkSession.table(name)


def run_to_files(stream: DataFrame) -> DataFrame:
    """Process what is there, each batch appended by the tasks to files in shared storage; for results of any size."""
    spark = stream.sparkSession
    shared = spark.sparkContext.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if not shared:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        shared = tempfile.mkdtemp(prefix="vtask-stream-")
    at = f"{shared}/stream-{uuid.uuid4().hex}"
    q = stream.writeStream.format("parquet").option("path", f"{at}/rows").option("checkpointLocation", f"{at}/progress").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{at}/rows")
