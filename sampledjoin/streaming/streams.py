"""Filters, windows and incremental strata on streams of events."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import FilterParams
from ..operators.filters import apply_filter


def events_stream(spark: SparkSession, folder: str, schema, files_per_trigger: int = 1) -> DataFrame:
    """A folder of Parquet files as a stream; ts becomes a timestamp of the session's zone, as watermarks need one."""
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).option("pathGlobFilter", "*.parquet").parquet(folder)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def filter_stream(stream: DataFrame, table: DataFrame, params: FilterParams) -> DataFrame:
    """Rows (with jk) that a filter built before may know: a join of the stream with a static table."""
    return apply_filter(stream, table, params)


def windowed(stream: DataFrame, kind: str = "tumbling", size: str = "1 hour", slide: str = "30 minutes", gap: str = "30 minutes", late: str = "10 minutes", by: str = "event_type") -> DataFrame:
    """Counts and sums of ``value`` by window and ``by``; rows later than the watermark are dropped. In append mode a window comes once it is over, in update mode whenever it changes."""
    w = {"tumbling": lambda: F.window("ts", size), "sliding": lambda: F.window("ts", size, slide), "session": lambda: F.session_window("ts", gap)}[kind]()
    out = stream.withWatermark("ts", late).groupBy(w.alias("w"), by).agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), by, "n", "total")


def incremental_partials(stream: DataFrame, path: str, checkpoint: str, value: str = "value", once: bool = True):
    """Merges each micro-batch's (jk, n, s1, s2) into a table of partials: the sums add up, so a batch's id makes a repeated batch harmless."""

    def merge(batch: DataFrame, batch_id: int) -> None:
        v = F.col(value)
        part = batch.groupBy("jk").agg(F.count("*").alias("n"), F.sum(v).alias("s1"), F.sum(v * v).alias("s2"))
        part.write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    w = stream.writeStream.foreachBatch(merge).option("checkpointLocation", checkpoint)
    return (w.trigger(availableNow=True) if once else w).start()


def merged_partials(spark: SparkSession, path: str) -> DataFrame:
    """The partials of all batches so far."""
    return spark.read.parquet(path).groupBy("jk").agg(F.sum("n").alias("n"), F.sum("s1").alias("s1"), F.sum("s2").alias("s2"))


def interval_join(left: DataFrame, right: DataFrame, within: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    """Pairs of a user's rows, the right one at most ``within`` after the left one; state is dropped as the watermarks pass."""
    a = left.select(F.col("user_id").alias("user_a"), F.col("ts").alias("ts_a"), F.col("value").alias("value_a")).withWatermark("ts_a", late)
    b = right.select(F.col("user_id").alias("user_b"), F.col("ts").alias("ts_b"), F.col("value").alias("value_b")).withWatermark("ts_b", late)
    return a.join(b, F.expr(f"user_a = user_b AND ts_b >= ts_a AND ts_b <= ts_a + INTERVAL {within}"))


def dedupe_stream(stream: DataFrame, keys: list[str], late: str = "10 minutes") -> DataFrame:
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(keys)


def running_moments(stream: DataFrame) -> DataFrame:
    """(user_id, n, total) after each batch, from state kept by user."""

    def update(key: tuple, frames: Iterable[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n, total = state.get if state.exists else (0, 0.0)
        for f in frames:
            n, total = n + len(f), total + float(f["value"].sum())
        state.update((n, total))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "total": [total]})

    return stream.groupBy("user_id").applyInPandasWithState(update, "user_id bigint, n bigint, total double", "n bigint, total double", "update", "NoTimeout")


def replay(spark: SparkSession, df: DataFrame, name: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """Runs a stream over all that is there and returns what it gave, as a table in memory."""
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)
