"""Deletion requests as a stream: windowed counts, a running removal set, and model versions.

A request is an event of a chosen type; its id is the sample to delete.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from delprop.scratch import new_path

SCHEMA = "event_id bigint, user_id bigint, ts timestamp, event_type string, value double, props string"


def requests(spark: SparkSession, folder: str, kind: str = "error", delay: str = "1 hour", pattern: str = "events*.parquet", schema: str | None = None) -> DataFrame:
    """(request_id, ts): requests in ``folder``, once each, late ones dropped by the watermark."""
    reader = spark.readStream.schema(schema or SCHEMA).option("pathGlobFilter", pattern).option("maxFilesPerTrigger", 8)
    rows = reader.parquet(folder).where(F.col("event_type") == kind)
    return rows.select(F.col("event_id").alias("request_id"), "ts").withWatermark("ts", delay).dropDuplicatesWithinWatermark(["request_id"])


def window_counts(stream: DataFrame, size: str = "1 day", slide: str | None = None) -> DataFrame:
    frame = F.window("ts", size, slide) if slide else F.window("ts", size)
    return stream.groupBy(frame.alias("w")).agg(F.count("*").alias("requests")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "requests")


def session_counts(stream: DataFrame, gap: str = "1 hour", models: int = 4) -> DataFrame:
    """Sessions of requests of each model shard; session windows need a key besides the window."""
    keyed = stream.withColumn("model", F.pmod("request_id", F.lit(models)).cast("int"))
    counts = keyed.groupBy(F.session_window("ts", gap).alias("w"), "model").agg(F.count("*").alias("requests"))
    return counts.select("model", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "requests")


def running_sets(stream: DataFrame, models: int = 4) -> DataFrame:
    """(model, removed, last_ts): how many requests each model shard has seen so far, as keyed state."""

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        count, last = state.get if state.exists else (0, 0)
        for frame in frames:
            count += len(frame)
            last = max(last, int(frame["ts"].astype("int64").max() // 10 ** (9 if frame["ts"].dtype == "datetime64[ns]" else 6)))
        state.update((count, last))
        yield pd.DataFrame({"model": [key[0]], "removed": [count], "last_ts": [last]})

    keyed = stream.select(F.pmod("request_id", F.lit(models)).cast("int").alias("model"), "ts")
    return keyed.groupBy("model").applyInPandasWithState(step, "model int, removed bigint, last_ts bigint", "removed bigint, last_ts bigint", "update", GroupStateTimeout.NoTimeout)


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run the stream over what is there now and read its output back from the shared scratch folder."""
    spark = stream.sparkSession
    out, state = new_path(spark, "stream"), new_path(spark, "stream-state")
    if mode == "append":
        stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(out)

    def write(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch", F.lit(number)).write.mode("append").parquet(out)

    stream.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(out)


def serve(stream: DataFrame, update: Callable[[DataFrame], list[float]], models_path: str, removals_path: str, state: str) -> None:
    """Every micro-batch adds its requests to the removal table and appends a model version made from all of it."""

    def step(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        ids = batch.select(F.col("request_id").alias("sample_id")).distinct()
        if ids.isEmpty():
            return
        ids.withColumn("version", F.lit(number)).write.mode("append").parquet(removals_path)
        w = update(spark.read.parquet(removals_path).select("sample_id").distinct())
        spark.createDataFrame([(number, [float(v) for v in w])], "version int, w array<double>").write.mode("append").parquet(models_path)

    stream.writeStream.foreachBatch(step).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()


def latest_model(models: DataFrame) -> DataFrame:
    return models.orderBy(F.desc("version")).limit(1)


def scored(stream: DataFrame, models: DataFrame, features) -> DataFrame:
    """Stream rows with the latest model's score: a join with one broadcast row."""
    w = F.broadcast(latest_model(models).select("w"))
    dot = F.aggregate(F.zip_with("w", features, lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)
    return stream.crossJoin(w).select(*stream.columns, dot.alias("score"))
