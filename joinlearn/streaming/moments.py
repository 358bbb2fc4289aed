"""Moments kept up to date over streams: sums add up, so each micro-batch contributes its own and deltas are merged.

Event times without zone are cast to TIMESTAMP before a watermark, which Spark asks for."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout


def sums(df: DataFrame, keys: list[str], value: str, sign: str | None = None) -> DataFrame:
    """(keys, n, s1, s2): count, sum and sum of squares; a sign column of 1 and -1 makes retractions subtract."""
    one = F.col(sign) if sign else F.lit(1)
    return df.groupBy(*keys).agg(F.sum(one).cast("long").alias("n"), F.sum(one * F.col(value)).alias("s1"), F.sum(one * F.col(value) * F.col(value)).alias("s2"))


def maintain(stream: DataFrame, keys: list[str], value: str, path: str, checkpoint: str, sign: str | None = None, **trigger) -> StreamingQuery:
    """Write each micro-batch's sums to its own folder under path; a batch that is run again overwrites itself."""

    def merge(batch: DataFrame, number: int) -> None:
        sums(batch, keys, value, sign).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return stream.writeStream.foreachBatch(merge).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()


def current(spark, keys: list[str], path: str) -> DataFrame:
    """The sum of all deltas so far."""
    return spark.read.parquet(path).groupBy(*keys).agg(F.sum("n").cast("long").alias("n"), F.sum("s1").alias("s1"), F.sum("s2").alias("s2"))


def timed(df: DataFrame, time: str = "ts") -> DataFrame:
    return df.withColumn(time, F.col(time).cast("timestamp"))


def windowed(df: DataFrame, keys: list[str], value: str, length: str = "1 day", slide: str | None = None, time: str = "ts", late: str | None = None) -> DataFrame:
    """Tumbling or sliding sums; `late` sets a watermark (streams), after which late rows are dropped."""
    if late:
        df = timed(df, time).withWatermark(time, late)
    w = F.window(time, length, slide) if slide else F.window(time, length)
    out = df.groupBy(w.alias("w"), *keys).agg(F.count(F.lit(1)).alias("n"), F.sum(value).alias("s1"))
    return out.select(F.col("w.start").alias("window_start"), F.col("w.end").alias("window_end"), *keys, "n", "s1")


def sessions(df: DataFrame, keys: list[str], value: str, gap: str = "30 minutes", time: str = "ts", late: str | None = None) -> DataFrame:
    if late:
        df = timed(df, time).withWatermark(time, late)
    out = df.groupBy(F.session_window(time, gap).alias("w"), *keys).agg(F.count(F.lit(1)).alias("n"), F.sum(value).alias("s1"))
    return out.select(F.col("w.start").alias("window_start"), F.col("w.end").alias("window_end"), *keys, "n", "s1")


def distinct_events(df: DataFrame, key: str = "event_id", time: str = "ts", late: str = "1 day") -> DataFrame:
    return timed(df, time).withWatermark(time, late).dropDuplicatesWithinWatermark([key])


def running(stream: DataFrame, key: str, value: str) -> DataFrame:
    """(key, n, s1, s2) after each micro-batch, from state kept for each key."""
    kind = stream.schema[key].dataType.simpleString()

    def step(k: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, s1, s2 = state.get if state.exists else (0, 0.0, 0.0)
        for p in parts:
            n, s1, s2 = n + len(p), s1 + float(p[value].sum()), s2 + float((p[value] ** 2).sum())
        state.update((n, s1, s2))
        yield pd.DataFrame({key: [k[0]], "n": [n], "s1": [s1], "s2": [s2]})

    return stream.groupBy(key).applyInPandasWithState(step, f"{key} {kind}, n long, s1 double, s2 double", "n long, s1 double, s2 double", "update", GroupStateTimeout.NoTimeout)


def enrich(stream: DataFrame, static: DataFrame, key: str) -> DataFrame:
    """Stream rows with a static view's columns."""
    return stream.join(static, key)
