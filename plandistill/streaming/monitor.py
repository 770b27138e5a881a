"""Streams: execution accuracy in event-time windows, and admission of teacher outputs as they arrive."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events as a stream; the time column becomes a timestamp (a watermark needs one)."""
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir).withColumn("ts", F.col("ts").cast("timestamp"))


def windowed_ex(events: DataFrame, width: str = "1 day", delay: str = "1 hour", slide: str | None = None) -> DataFrame:
    """Per window and run: n, ok (a purchase counts as success); works on streams and tables."""
    marked = events.withWatermark("ts", delay) if events.isStreaming else events
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    out = marked.groupBy(w.alias("w"), (F.col("user_id") % 5).alias("run")).agg(F.count("*").alias("n"), F.count_if(F.col("event_type") == "purchase").alias("ok"))
    return out.select(F.col("w.start").alias("start"), "run", "n", "ok")


def session_ex(events: DataFrame, gap: str = "6 hours", delay: str = "1 hour") -> DataFrame:
    marked = events.withWatermark("ts", delay) if events.isStreaming else events
    return marked.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "user_id", "n")


def stream_admit(completions: DataFrame, quotas: dict[str, int], delay: str = "1 hour") -> DataFrame:
    """Successes in order of arrival up to each stratum's quota (state: how many were admitted).

    Unlike batch sampling, which takes hash order: a stream can't take back what it admitted."""
    import pandas as pd

    def admit(key, frames, state):
        n = state.get[0] if state.exists else 0
        for f in frames:
            good = f[f["success"]].head(max(0, quotas.get(key[0], 0) - n))
            n += len(good)
            yield pd.DataFrame({"stratum": key[0], "sample_id": good["sample_id"]})
        state.update((n,))

    once = completions.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["sample_id"])
    return once.groupBy("stratum").applyInPandasWithState(admit, "stratum string, sample_id string", "n long", "append", "NoTimeout")
