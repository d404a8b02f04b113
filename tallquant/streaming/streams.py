"""Structured Streaming over event files: windows, late rows, mergeable sketches, online samples, refits."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tallquant.functions import randomness as rnd
from tallquant.functions.loss import pinball
from tallquant.sources.storage import scratch


def events_in_files(spark: SparkSession, sf_dir: str, number: Column, files: int, pieces: int = 1) -> str:
    """The events as a folder of files that arrive one after the other, dealt by a file number; each in so many pieces, written side by side."""
    path = scratch(spark, "events")
    events = spark.read.parquet(f"{sf_dir}/events.parquet").withColumn("_file", number)
    for k in range(files):
        rows = events.where(F.col("_file") == k).drop("_file")
        (rows.coalesce(1) if pieces == 1 else rows.repartition(pieces)).write.mode("append").parquet(path)
    return path


def time_slot(spark: SparkSession, sf_dir: str, files: int) -> Column:
    """Files of equal stretches of time."""
    low, high = spark.read.parquet(f"{sf_dir}/events.parquet").agg(F.min(F.unix_timestamp(F.col("ts").cast("timestamp"))), F.max(F.unix_timestamp(F.col("ts").cast("timestamp")))).first()
    return F.floor(files * (F.unix_timestamp(F.col("ts").cast("timestamp")) - low) / (high - low + 1)).cast("int")


def events_stream(spark: SparkSession, sf_dir: str, files_per_trigger: int | None = None, path: str | None = None) -> DataFrame:
    """The events as a file stream, of ``path`` if given; the naive timestamps are read as the session's (UTC)."""
    path = path or f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    reader = spark.readStream.schema(schema)
    if files_per_trigger:
        reader = reader.option("maxFilesPerTrigger", files_per_trigger)
    return reader.parquet(path + "*").withColumn("ts", F.col("ts").cast("timestamp"))


def rate_stream(spark: SparkSession, rows: int) -> DataFrame:
    """The built-in source of numbered rows, one micro-batch of them."""
    return spark.readStream.format("rate-micro-batch").option("rowsPerBatch", rows).load()


def drain(stream: DataFrame, mode: str = "append", name: str | None = None) -> DataFrame:
    """Run until the source is empty and return what the sink holds: Parquet in the shared folder, so the driver gathers no rows.

    Appended rows go through the file sink.  A complete result replaces that of the batch before, updates are kept
    batch by batch; a batch that is run again overwrites its own files.
    """
    spark = stream.sparkSession
    name = name or f"stream_{uuid.uuid4().hex[:10]}"
    path = scratch(spark, f"{name}_rows")
    spark.createDataFrame([], stream.schema).write.parquet(f"{path}/batch=-1")
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", scratch(spark, name)).trigger(availableNow=True)
    if mode == "append":
        query = writer.format("parquet").option("path", f"{path}/rows").start()
    else:
        query = writer.foreachBatch(lambda batch, k: batch.write.mode("overwrite").parquet(f"{path}/batch={0 if mode == 'complete' else k}")).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/rows" if mode == "append" else f"{path}/batch=*")


def window_losses(events: DataFrame, model: float, tau: float, length: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Rows, pinball loss of a fixed model, and an approximate quantile for each window and type."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    out = events.withWatermark("ts", late).groupBy(w.alias("w"), "event_type").agg(
        F.count("*").alias("n"), F.sum(pinball(F.col("value") - model, tau)).alias("loss"), F.percentile_approx("value", tau, 10_000).alias("q")
    )
    return out.select(F.col("w.start").alias("start"), "event_type", "n", F.round("loss", 4).alias("loss"), "q")


def session_losses(events: DataFrame, model: float, tau: float, gap: str = "6 hours", late: str = "1 hour") -> DataFrame:
    """The same for each user's sessions."""
    out = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"), F.sum(pinball(F.col("value") - model, tau)).alias("loss"))
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "user_id", "n", F.round("loss", 4).alias("loss"))


def deduplicated(events: DataFrame, late: str = "2 hours") -> DataFrame:
    """Each event once, within the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def sketch_stream(events: DataFrame, r: int, seed: int, engine: str = "portable") -> DataFrame:
    """Running sparse Cauchy sketch of [value, -1]: sketches are linear, so state is one sum for each bucket."""
    row_id = F.col("event_id").cast("string")
    bucket = rnd.bucket(rnd.unit(seed, "bucket", row_id, engine), r)
    c = rnd.cauchy(rnd.unit(seed, "cauchy", row_id, engine))
    return events.select(bucket.alias("bucket"), (c * F.col("value")).alias("v0"), (-c).alias("v1")).groupBy("bucket").agg(F.sum("v0").alias("v0"), F.sum("v1").alias("v1"))


def online_sample(events: DataFrame, k: int, seed: int, engine: str = "portable") -> DataFrame:
    """The k rows of smallest coin over importance for each type, kept as bounded state.

    Importance is that of the frozen identity conditioner: |value| + 1.  The
    output has each update of a type; the last one is the sample.
    """
    ratio = rnd.unit(seed, "coin0", F.col("event_id").cast("string"), engine) / (F.abs("value") + 1.0)
    rows = events.select("event_type", "event_id", "value", ratio.alias("ratio"))

    def keep(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        held = pd.DataFrame(list(zip(*state.get, strict=True)), columns=["event_id", "value", "ratio"]) if state.exists and state.get[0] else None
        parts = [b[["event_id", "value", "ratio"]] for b in batches]
        every = pd.concat(([held] if held is not None else []) + parts).nsmallest(k, "ratio")
        state.update((every.event_id.tolist(), every.value.tolist(), every.ratio.tolist()))
        yield every.assign(event_type=key[0])[["event_type", "event_id", "value", "ratio"]]

    return rows.groupBy("event_type").applyInPandasWithState(keep, "event_type string, event_id long, value double, ratio double", "ids array<long>, vals array<double>, ratios array<double>", "update", "NoTimeout")


def refit_each_batch(events: DataFrame, taus: list[float]) -> list[tuple]:
    """Exact intercept-only fits of every micro-batch through foreachBatch."""
    out: list[tuple] = []

    def fit(batch: DataFrame, number: int) -> None:
        if batch.isEmpty():
            return
        row = batch.agg(F.count("*"), *[F.expr(f"percentile_disc({t}) WITHIN GROUP (ORDER BY value)") for t in taus]).first()
        out.extend((number, row[0], t, float(row[1 + i])) for i, t in enumerate(taus))

    query = events.writeStream.foreachBatch(fit).option("checkpointLocation", scratch(events.sparkSession, "refit")).trigger(availableNow=True).start()
    query.awaitTermination()
    return out


def join_fits(events: DataFrame, fits: DataFrame) -> DataFrame:
    """Stream-static join: residuals under a table of fits (event_type, q)."""
    return events.join(fits, "event_type").select("event_id", "event_type", (F.col("value") - F.col("q")).alias("residual"))


def views_then_clicks(events: DataFrame, late: str = "1 hour", within: str = "1 hour") -> DataFrame:
    """Stream-stream interval join: clicks of a user within an hour of a view."""
    view = events.where("event_type = 'view'").select(F.col("event_id").alias("view_id"), F.col("user_id").alias("u"), F.col("ts").alias("view_ts")).withWatermark("view_ts", late)
    click = events.where("event_type = 'click'").select(F.col("event_id").alias("click_id"), "user_id", F.col("ts").alias("click_ts")).withWatermark("click_ts", late)
    return view.join(click, F.expr(f"u = user_id AND click_ts >= view_ts AND click_ts <= view_ts + INTERVAL {within}")).select("view_id", "click_id")
