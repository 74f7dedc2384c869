"""Streamed cell counts: disjoint windows are disjoint cells, so every record counts in one release."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.noise import gauss_sigma, gaussian
from .ledger import Ledger


def window_cells(events: DataFrame, width: str = "1 hour", delay: str = "1 hour", key: str = "event_id") -> DataFrame:
    """(window_start, event_type, cnt) for a stream or a table of events (ts, event_type, key).

    On a stream, repeats within the watermark are dropped and late rows ignored; on a table, all repeats go.
    """
    kept = events.withWatermark("ts", delay)
    kept = kept.dropDuplicatesWithinWatermark([key]) if events.isStreaming else kept.dropDuplicates([key])
    counted = kept.groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count("*").alias("cnt"))
    return counted.select(F.col("w.start").alias("window_start"), "event_type", "cnt")


def calendar(spark: SparkSession, start: str, end: str, types: list[str], width: str = "1 hour") -> DataFrame:
    """(window_start, event_type) of every window from start to before end, which are public, as are the types."""
    first, last = (F.lit(x).cast("timestamp") for x in (start, end))
    every = spark.range(1).select(F.explode(F.sequence(first, last, F.expr(f"interval {width}"))).alias("window_start")).where(F.col("window_start") < last)
    return every.withColumn("event_type", F.explode(F.array(*[F.lit(t) for t in types])))


def release_windows(counts: DataFrame, every: DataFrame, eps: float, delta: float, seed: int, secret: Column | None = None) -> DataFrame:
    """Windows of a calendar with noise by (window, type): a re-run emits the same noise.

    Windows come from the calendar, not from the counts: one without an event is released as
    zero plus noise like any other, and counts outside the calendar are left out.
    """
    full = every.join(counts, ["window_start", "event_type"], "left")
    key = F.concat_ws("|", F.unix_timestamp("window_start").cast("string"), "event_type")
    return full.select("window_start", "event_type", (F.coalesce("cnt", F.lit(0)) + F.lit(gauss_sigma(1.0, eps, delta)) * gaussian(seed, key, secret)).alias("answer"))


def sliding_answers(released: DataFrame, panes: int, width_s: int) -> DataFrame:
    """(window_start, event_type, answer) of windows of so many panes, from released panes alone.

    A sliding window is a range of panes, so its answer is a sum of what was released: it costs no
    further budget, where counting every window by itself would count a record many times.
    """
    moved = released.select("event_type", "answer", F.explode(F.sequence(F.lit(0), F.lit(panes - 1))).alias("k"), F.unix_timestamp("window_start").alias("s"))
    summed = moved.groupBy((F.col("s") - F.col("k") * width_s).alias("s"), "event_type").agg(F.sum("answer").alias("answer"), F.count("*").alias("n"))
    return summed.where(F.col("n") == panes).select(F.timestamp_seconds("s").alias("window_start"), "event_type", "answer")


def release_sessions(*_, **__) -> None:
    """Refused: where a session begins and ends depends on the records, so sessions are no public partition."""
    raise ValueError("session windows have private borders: count them exactly for yourself, or release windows of a calendar")


def release_stream(
    events: DataFrame, folder: str, types: list[str], start: str, eps: float, delta: float, seed: int, checkpoint: str,
    ledger: Ledger | None = None, width: str = "1 hour",
):
    """Starts a query that releases each closed window once, as Parquet under ``folder``.

    Every batch releases the calendar from where the last one ended up to the newest window that has
    closed.  A batch that runs again writes the same noise over its own result.  The ledger is charged
    once for the whole stream (its windows are disjoint) and stops it if the budget does not suffice.
    """
    spark = events.sparkSession
    if ledger is not None:
        ledger.spend("stream " + folder, eps, delta)

    def once(batch: DataFrame, batch_id: int) -> None:
        newest = batch.agg(F.max(F.col("window_start") + F.expr(f"interval {width}")).cast("string")).first()[0]
        if newest is None:
            return
        try:
            done = spark.read.parquet(folder).where(F.col("batch") < batch_id).agg(F.max(F.col("window_start") + F.expr(f"interval {width}")).cast("string")).first()[0]
        except Exception as e:  # nothing released yet
            if "PATH_NOT_FOUND" not in str(e) and "UNABLE_TO_INFER_SCHEMA" not in str(e):
                raise
            done = None
        every = calendar(spark, done or start, newest, types, width)
        release_windows(batch, every, eps, delta, seed).write.mode("overwrite").parquet(f"{folder}/batch={batch_id}")

    return window_cells(events, width).writeStream.outputMode("append").foreachBatch(once).option("checkpointLocation", checkpoint).start()
