"""Event-time windows of moments on a stream, and keyed moments in arbitrary state."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def event_time(df: DataFrame, column: str = "ts", late: str | None = "10 minutes") -> DataFrame:
    """Times without zone read as UTC timestamps, with a watermark."""
    df = df.withColumn(column, F.col(column).cast("timestamp"))
    return df.withWatermark(column, late) if late else df


def window_moments(df: DataFrame, window: Column, by: list[str], value: str) -> DataFrame:
    """start, end, by, c, s, q of a value per window; rows with mult count with it, so deletes are rows with -1."""
    m = F.col("mult") if "mult" in df.columns else F.lit(1)
    x = F.col(value).cast("decimal(12,2)")
    out = df.groupBy(window.alias("w"), *by).agg(F.sum(m).cast("long").alias("c"), F.sum(m * x).alias("s"), F.sum(m * x * x).alias("q"))
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *by, "c", "s", "q")


def tumbling(df: DataFrame, by: list[str], value: str, size: str, column: str = "ts") -> DataFrame:
    return window_moments(df, F.window(column, size), by, value)


def sliding(df: DataFrame, by: list[str], value: str, size: str, step: str, column: str = "ts") -> DataFrame:
    return window_moments(df, F.window(column, size, step), by, value)


def sessions(df: DataFrame, by: list[str], value: str, gap: str, column: str = "ts") -> DataFrame:
    return window_moments(df, F.session_window(column, gap), by, value)


def deduplicated(df: DataFrame, key: list[str], column: str = "ts") -> DataFrame:
    """Repeated deliveries of an event within the watermark dropped."""
    return df.dropDuplicatesWithinWatermark(key)


def keyed_moments(df: DataFrame, key: str, value: str) -> DataFrame:
    """key, c, s, q running per key in arbitrary state, for update mode."""

    def update(k: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        c, s, q = state.get if state.exists else (0, 0.0, 0.0)
        for f in frames:
            m = f["mult"] if "mult" in f else pd.Series(1, index=f.index)
            c, s, q = c + int(m.sum()), s + float((m * f[value]).sum()), q + float((m * f[value] ** 2).sum())
        state.update((c, s, q))
        yield pd.DataFrame({key: [k[0]], "c": [c], "s": [s], "q": [q]})

    kind = df.schema[key].dataType.simpleString()
    return df.groupBy(key).applyInPandasWithState(update, f"{key} {kind}, c long, s double, q double", "c long, s double, q double", "update", "NoTimeout")
