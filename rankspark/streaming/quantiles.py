"""Quantiles of streams: windows of dyadic counts, windows of packed summaries, and a summary table that micro-batches refresh."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from rankspark import engine, synopsis
from rankspark.params import MethodSpec
from rankspark.sources import scratch


def event_stream(spark, sf_dir: str) -> DataFrame:
    """The events table as a stream of files."""
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    one_file = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    single = not one_file.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(one_file).isDirectory()
    reader = spark.readStream.schema(schema)
    rows = reader.option("pathGlobFilter", "events.parquet").parquet(sf_dir) if single else reader.parquet(path)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))  # watermarks need a point in time; the session's zone gives it


def drained(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run a stream to the end of what is there and return its rows; in update mode those of every batch, with its number as `batch`."""
    spark = stream.sparkSession
    import uuid

    run = f"{name}_{uuid.uuid4().hex[:8]}"
    folder = f"{scratch(spark)}/streams/{run}"
    if mode == "append":
        query = stream.writeStream.format("parquet").option("path", f"{folder}/rows").option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
        query.awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{folder}/rows")
    kept = f"{folder}/rows"

    def save(batch: DataFrame, number: int) -> None:
        path = f"{kept}/batch={number}" if mode == "update" else kept  # complete mode: each batch is the whole result
        batch.write.mode("overwrite").parquet(path)

    query = stream.writeStream.outputMode(mode).foreachBatch(save).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    schema = stream.schema
    return spark.read.schema(T.StructType([*schema.fields, T.StructField("batch", T.LongType())]) if mode == "update" else schema).parquet(kept)


def window_counts(stream: DataFrame, ts: str, value: F.Column, length: str, slide: str | None = None, watermark: str = "1 day") -> DataFrame:
    """start, idx, cnt: a leaf histogram for each window, kept by the built-in aggregation."""
    w = F.window(ts, length, slide) if slide else F.window(ts, length)
    return stream.withWatermark(ts, watermark).groupBy(w.alias("w"), value.cast("long").alias("idx")).agg(F.count(F.lit(1)).alias("cnt")).select(F.col("w.start").alias("start"), "idx", "cnt")


def deduplicated(stream: DataFrame, ts: str, key: str, watermark: str = "1 day") -> DataFrame:
    return stream.withWatermark(ts, watermark).dropDuplicatesWithinWatermark([key])


def windowed_summaries(stream: DataFrame, ts: str, column: str, spec: MethodSpec, length: str, watermark: str = "1 day") -> DataFrame:
    """start, n, payload for each tumbling window that a batch changed, for update mode: the state is one packed summary.
    A window's last row is the whole of it; behind the watermark its state goes."""
    rows = stream.withWatermark(ts, watermark).select(F.window(ts, length).alias("w"), F.col(ts).alias("ts"), F.col(column).cast("double").alias("v")).select(F.col("w.start").alias("start"), F.col("w.end").alias("stop"), "ts", "v")

    def absorb(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        s = synopsis.unpack(state.get[0]) if state.exists else synopsis.new(spec)
        for f in frames:
            s.absorb(f["v"].dropna().to_numpy())
        payload = s.pack()
        state.update((payload, s.n))
        state.setTimeoutTimestamp(int(pd.Timestamp(key[1]).timestamp() * 1000) + 1)
        yield pd.DataFrame({"start": [key[0]], "n": [s.n], "payload": [payload]})

    return rows.groupBy("start", "stop").applyInPandasWithState(absorb, "start timestamp, n long, payload binary", "payload binary, n long", "update", GroupStateTimeout.EventTimeTimeout)


def refreshed(stream: DataFrame, column: str, spec: MethodSpec, path: str) -> None:
    """Each micro-batch becomes one summary under its batch number, so a repeated batch replaces itself; readers merge what is there."""

    def save(batch: DataFrame, number: int) -> None:
        engine.merge_summaries(engine.summarize(batch, column, spec)).write.mode("overwrite").parquet(f"{path}/batch={number}")

    stream.writeStream.foreachBatch(save).option("checkpointLocation", f"{path}_state").trigger(availableNow=True).start().awaitTermination()
