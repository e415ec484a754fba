"""Streams of events: labels that come from the events, windows, watermarks, state.

The batch engine explains a finished input; an appended batch is where new labels come from.  A stream's element labels are
derived from the events, never from their arrival, so the same event has the same label in any run.
"""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout


def events(spark: SparkSession, folder: str) -> DataFrame:
    """The event table as a stream; its zoneless time becomes a timestamp, which watermarks need (session zone: UTC)."""
    schema = spark.read.parquet(f"{folder}/events.parquet").schema
    # A file source watches a folder; the glob picks the table, be it a file or a folder of parts.
    return spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet").parquet(f"{folder}/events.parquet*").withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling(df: DataFrame, width: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """``(lbl, event_type, n, cents)`` per window and type; the label is the window's start in microseconds, then the type."""
    agg = df.withWatermark("ts", late).groupBy(F.window("ts", width), "event_type").agg(F.count("*").alias("n"), F.sum(F.round(F.col("value") * 100).cast("long")).alias("cents"))
    return agg.select(F.concat_ws(".", F.unix_micros("window.start").cast("string"), "event_type").alias("lbl"), "event_type", "n", "cents")


def sliding(df: DataFrame, width: str = "2 hours", step: str = "1 hour", late: str = "1 hour") -> DataFrame:
    agg = df.withWatermark("ts", late).groupBy(F.window("ts", width, step), "event_type").agg(F.count("*").alias("n"))
    return agg.select(F.unix_micros("window.start").alias("start"), "event_type", "n")


def sessions(df: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    agg = df.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))
    return agg.select(F.unix_micros("session_window.start").alias("start"), "user_id", "n")


def without_repeats(df: DataFrame, keys: list[str], late: str = "1 hour") -> DataFrame:
    return df.withWatermark("ts", late).dropDuplicatesWithinWatermark(keys)


def with_static(df: DataFrame, static: DataFrame, key: str) -> DataFrame:
    """A stream-static join; the static side is read anew for every batch."""
    return df.join(static, key)


def running_totals(df: DataFrame) -> DataFrame:
    """``(user_id, n, cents)`` after each batch, kept as state per user."""

    def update(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, cents = state.get if state.exists else (0, 0)
        for part in parts:
            n += len(part)
            cents += int((part["value"] * 100).round().sum())
        state.update((n, cents))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "cents": [cents]})

    return df.select("user_id", "value").groupBy("user_id").applyInPandasWithState(update, "user_id long, n long, cents long", "n long, cents long", "update", GroupStateTimeout.NoTimeout)


def unknown_labels(df: DataFrame, known: DataFrame, key: str) -> DataFrame:
    """Arriving elements that a stored trace does not know, by an anti-join with its labels: a replay would refuse them."""
    return df.join(known.select(F.col(key).alias("__known")), F.col(key) == F.col("__known"), "left_anti")


def traced(expr_of: Callable[[DataFrame], object], name: str, key: str, folder: str, columns: list[str]) -> Callable[[DataFrame], DataFrame]:
    """For ``drained(each=…)``: evaluates a query over every micro-batch as table ``name``, labelled by ``key``, and appends its
    trace to a folder.  Labels come from the events, so traces of batches never collide."""
    from backtrail.operators.runs import trace, trace_rows
    from backtrail.sources.catalog import Catalog

    def step(batch: DataFrame) -> DataFrame:
        cat = Catalog(batch.sparkSession).register(name, batch.select(*columns), [key])
        run = trace(expr_of(batch), cat)
        trace_rows(run).write.mode("append").parquet(folder)
        return run.value()

    return step


def drained(df: DataFrame, mode: str = "append", each: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """Runs a stream over all that is there now and returns its output, kept as files through ``foreachBatch``.

    Mode ``complete`` and ``update`` keep the last word on every row: of complete results the last batch.
    """
    spark = df.sparkSession
    base = spark.sparkContext.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="streams-")
    folder = f"{base}/stream-{uuid.uuid4().hex}"

    def keep(batch: DataFrame, number: int) -> None:
        (each(batch) if each else batch).withColumn("__batch", F.lit(number)).write.mode("append").parquet(f"{folder}/out")

    if each is None:  # so that an empty stream has a result with its columns
        spark.createDataFrame([], df.schema).withColumn("__batch", F.lit(0)).write.mode("append").parquet(f"{folder}/out")
    stream = df.writeStream.outputMode(mode).option("checkpointLocation", f"{folder}/log").trigger(availableNow=True).foreachBatch(keep).start()
    stream.awaitTermination()
    out = spark.read.parquet(f"{folder}/out")
    if mode == "complete":
        last = out.agg(F.max("__batch").alias("m"))
        out = out.join(F.broadcast(last), F.col("__batch") == F.col("m")).drop("m")
    return out.drop("__batch")


