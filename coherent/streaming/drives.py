"""Drives from event streams: windowed means, deduplication, stream-static joins and stateful propagation."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coherent.operators import integrate

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def tumbling(events: DataFrame, length: str = "1 day", watermark: str | None = None) -> DataFrame:
    """t0, t1, n, eps: mean value of each window; batch or, with a watermark, stream."""
    e = events.withWatermark("ts", watermark) if watermark else events
    w = e.groupBy(F.window("ts", length)).agg(F.count(F.lit(1)).alias("n"), F.avg("value").alias("eps"))
    return w.select(F.col("window.start").alias("t0"), F.col("window.end").alias("t1"), "n", "eps")


def sliding(events: DataFrame, length: str = "2 days", slide: str = "1 day", watermark: str | None = None) -> DataFrame:
    e = events.withWatermark("ts", watermark) if watermark else events
    w = e.groupBy(F.window("ts", length, slide)).agg(F.count(F.lit(1)).alias("n"), F.avg("value").alias("eps"))
    return w.select(F.col("window.start").alias("t0"), F.col("window.end").alias("t1"), "n", "eps")


def sessions(events: DataFrame, gap: str = "6 hours", watermark: str | None = None) -> DataFrame:
    e = events.withWatermark("ts", watermark) if watermark else events
    w = e.groupBy("user_id", F.session_window("ts", gap).alias("window")).agg(F.count(F.lit(1)).alias("n"), F.avg("value").alias("eps"))
    return w.select("user_id", F.col("window.start").alias("t0"), F.col("window.end").alias("t1"), "n", "eps")


def once(events: DataFrame, watermark: str = "1 hour") -> DataFrame:
    """Each event_id once within the watermark."""
    return events.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])


def rescaled(windows: DataFrame, sys: str) -> DataFrame:
    """sys, t0, t1, eps: a drive from windowed means, rescaled to [-1, 1] and timed in shares of its whole span."""
    seconds = lambda c: F.unix_micros(F.col(c).cast("timestamp")) / 1e6
    w = windows.select(seconds("t0").alias("a"), seconds("t1").alias("b"), "eps")
    ends = w.agg(F.min("a").alias("lo"), F.max("b").alias("hi"), F.min("eps").alias("least"), F.max("eps").alias("most"))
    span, width = F.col("hi") - F.col("lo"), F.col("most") - F.col("least")
    scaled = F.when(width > 0, 2 * (F.col("eps") - F.col("least")) / width - 1).otherwise(0.0)
    return w.crossJoin(ends).select(F.lit(sys).alias("sys"), ((F.col("a") - F.col("lo")) / span).alias("t0"), ((F.col("b") - F.col("lo")) / span).alias("t1"), scaled.alias("eps"))  # one row on the right


def with_static(events: DataFrame, table: DataFrame, key: str) -> DataFrame:
    """Each event (stream or batch) with its row of a static table, or nulls."""
    return events.join(table, key, "left")


def upsert(path: str, key: str):
    """A sink for foreachBatch: each batch in a folder of its number, written over if it is tried again, so that a batch counts once."""

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/{key}={number}")

    return write


def propagated(events: DataFrame, a0: np.ndarray, a1: np.ndarray, k: np.ndarray, hours_per_step: float = 6.0) -> DataFrame:
    """user_id, events, t, x: per user, the vector v carried from event to event under the drive's last value.

    State is v, the last value and the last time; late events (before the last time) only set the drive. Steps of
    `hours_per_step` advance by the collapsed map. A stream gives a row for each user of each trigger, a batch one for each
    user: its tasks read sorted events and hold one user's state at a time. Events without a time are left out; a null user is a user.
    """
    m = len(k)
    schema = "user_id long, events long, t double, x array<double>"
    fresh = ([0.0] * m, 0.0, -1.0, 0)
    timed = events.where(F.col("ts").isNotNull())

    def advance(v: np.ndarray, eps: float, hours: float) -> np.ndarray:
        steps = int(hours // hours_per_step)
        if steps <= 0:
            return v
        power = np.linalg.matrix_power(integrate.step_map(a0 + eps * a1, k, 0.05), steps)
        return (power @ np.append(v, 1.0))[:m]

    def carried(state: tuple, rows: pd.DataFrame) -> tuple:
        v, eps, last, seen = state
        v = np.array(v)
        for ts, value in zip(rows["ts"], rows["value"], strict=True):
            t = ts.timestamp() / 3600
            if last >= 0 and t > last:
                v = advance(v, eps, t - last)
            last, eps, seen = max(last, t), float(value), seen + 1
        return v.tolist(), eps, last, seen

    def table(ended: list[tuple]) -> pd.DataFrame:
        users, states = [u for u, _ in ended], [s for _, s in ended]
        return pd.DataFrame({"user_id": pd.array(users, "Int64"), "events": [s[3] for s in states], "t": [s[2] for s in states], "x": [s[0] for s in states]})

    def on_trigger(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        now = carried(state.get if state.exists else fresh, pd.concat(list(frames)).sort_values(["ts", "event_id"]))
        state.update(now)
        yield table([(key[0], now)])

    def on_sorted(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        user, state = None, None
        number = lambda u: int(u) if u else None
        for frame in frames:
            ended = []
            for u, rows in frame.groupby("user", sort=False):
                if u != user:
                    if user is not None:
                        ended.append((number(user), state))
                    user, state = u, fresh
                state = carried(state, rows)
            if ended:
                yield table(ended)
        if user is not None:
            yield table([(number(user), state)])

    if events.isStreaming:
        return timed.groupBy("user_id").applyInPandasWithState(on_trigger, schema, "v array<double>, eps double, last double, seen long", "update", "NoTimeout")
    keyed = timed.select(F.coalesce(F.col("user_id").cast("string"), F.lit("")).alias("user"), "ts", "event_id", "value")
    return keyed.repartition("user").sortWithinPartitions("user", "ts", "event_id").mapInPandas(on_sorted, schema)
