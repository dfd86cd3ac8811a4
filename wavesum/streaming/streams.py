"""Summaries kept up to date by Structured Streaming."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wavesum.functions import haar
from wavesum.sources.gen import stream_files


def source(events: DataFrame, folder: str) -> DataFrame:
    """The events as a file stream, one file a trigger."""
    stream_files(events, f"{folder}/in")
    return events.sparkSession.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(f"{folder}/in")


def freq(stream: DataFrame) -> DataFrame:
    """Running counts by key (update or complete mode)."""
    return stream.groupBy("pos").agg(F.count("*").alias("cnt"))


def deduplicated(stream: DataFrame, late: str = "7 days") -> DataFrame:
    """Events once each, repeats dropped as long as the watermark reaches.

    A watermark begins at 1970 and drops what isn't later, so it runs on a column far ahead
    of ts: events of any age come through.  The result has no watermark on ts.
    """
    mark = "ts_ahead"
    while mark in stream.columns:
        mark = f"_{mark}"
    ahead = stream.withColumn(mark, F.col("ts") + F.expr("INTERVAL 3000 YEAR"))
    return ahead.withWatermark(mark, late).dropDuplicatesWithinWatermark(["event_id"]).drop(mark)


def windows(stream: DataFrame, by: str, late: str = "7 days", size: str = "1 day", slide: str | None = None) -> DataFrame:
    """Tumbling or sliding counts; rows later than the watermark are dropped."""
    return stream.withWatermark("ts", late).groupBy(F.window("ts", size, slide or size), by).agg(F.count("*").alias("n"))


def sessions(stream: DataFrame, by: str, gap: str = "30 minutes", late: str = "7 days") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.session_window("ts", gap), by).agg(F.count("*").alias("n"))


def coefficient_sink(log2u: int, folder: str):
    """A foreachBatch function: the batch's delta coefficients as files of its own epoch.

    An epoch that is run again overwrites its own folder, so each counts once.  The state is
    the sum over epochs; `compact` folds old ones together.
    """

    def sink(batch: DataFrame, epoch: int) -> None:
        delta = haar.by_basis(batch.groupBy("pos").agg(F.count("*").alias("cnt")), log2u)
        delta.write.mode("overwrite").parquet(f"{folder}/epoch={epoch}")

    return sink


def coefficient_state(spark: SparkSession, folder: str) -> DataFrame:
    """All coefficients so far: a dropped one may matter later, so none is."""
    return spark.read.parquet(folder).groupBy("coef_id", "level").agg(F.sum("diff").cast("long").alias("diff")).filter("diff <> 0")


def compact(spark: SparkSession, folder: str, to: str) -> None:
    """The state as one epoch of a new folder."""
    coefficient_state(spark, folder).write.mode("overwrite").parquet(f"{to}/epoch=0")


def finish(query) -> None:
    query.processAllAvailable()
    query.stop()


def _final(stream: DataFrame, mode: str, folder: str) -> DataFrame:
    """A stream run over all there is, into Parquet; in complete mode the last epoch is the result."""
    spark = stream.sparkSession

    def sink(batch: DataFrame, epoch: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/out" if mode == "complete" else f"{folder}/out/epoch={epoch}")

    finish(stream.writeStream.outputMode(mode).option("checkpointLocation", f"{folder}/checkpoint").foreachBatch(sink).start())
    return spark.read.parquet(f"{folder}/out")


def run_freq(events: DataFrame, folder: str) -> DataFrame:
    return _final(freq(source(events, folder)), "complete", folder)


def run_windows(events: DataFrame, folder: str) -> DataFrame:
    stream = source(events, folder).withColumn("ts", F.col("ts").cast("timestamp"))
    got = _final(windows(stream, "event_type", late="3650 days"), "complete", folder)
    return got.select(F.col("window.start").cast("timestamp_ntz").alias("start"), "event_type", "n")


def run_sliding(events: DataFrame, folder: str) -> DataFrame:
    stream = source(events, folder).withColumn("ts", F.col("ts").cast("timestamp"))
    got = _final(windows(stream, "event_type", late="3650 days", size="1 day", slide="12 hours"), "complete", folder)
    return got.select(F.col("window.start").cast("timestamp_ntz").alias("start"), "event_type", "n")


def run_sessions(events: DataFrame, folder: str, gap: str = "6 hours") -> DataFrame:
    stream = source(events, folder).withColumn("ts", F.col("ts").cast("timestamp"))
    got = _final(sessions(stream, "user_id", gap, late="3650 days"), "complete", folder)
    return got.select("user_id", F.col("session_window.start").cast("timestamp_ntz").alias("start"), "n")


def run_deduplicated(events: DataFrame, folder: str) -> DataFrame:
    stream = source(events, folder).withColumn("ts", F.col("ts").cast("timestamp"))
    return _final(deduplicated(stream, late="3650 days"), "append", folder).drop("epoch")


def run_state(events: DataFrame, folder: str) -> DataFrame:
    """The last total of each key from the stateful operator's updates."""
    got = _final(running_counts_with_state(source(events, folder)), "update", folder)
    return got.groupBy("pos").agg(F.max("total").alias("cnt"))


def run_late(events: DataFrame, folder: str, late: str = "1 day") -> DataFrame:
    """Daily counts of a stream in which rows of windows that the watermark has passed are dropped."""
    stream = source(events, folder).withColumn("ts", F.col("ts").cast("timestamp"))
    got = _final(windows(stream, "event_type", late=late), "update", folder)
    return got.groupBy(F.col("window.start").cast("timestamp_ntz").alias("start"), "event_type").agg(F.max("n").alias("n"))


def run_coefs(events: DataFrame, log2u: int, folder: str) -> DataFrame:
    stream = source(events, folder)
    finish(stream.writeStream.option("checkpointLocation", f"{folder}/checkpoint").foreachBatch(coefficient_sink(log2u, f"{folder}/state")).start())
    return coefficient_state(events.sparkSession, f"{folder}/state").select("coef_id", "diff")


def running_counts_with_state(stream: DataFrame) -> DataFrame:
    """(pos, total) after each trigger by a stateful operator: one long of state a key."""
    import pandas as pd

    def add(key, frames, state):
        n = (state.get[0] if state.exists else 0) + sum(len(f) for f in frames)
        state.update((n,))
        yield pd.DataFrame({"pos": [key[0]], "total": [n]})

    return stream.groupBy("pos").applyInPandasWithState(add, "pos bigint, total bigint", "n bigint", "update", "NoTimeout")
