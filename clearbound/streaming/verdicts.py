"""Live verdict monitor over ``events``: windows, sessions, deduplication, joins of two
streams and a running kappa with bounded state. The same functions run on batches."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

WATERMARK = "10 minutes"


def timed(events: DataFrame, watermark: str | None = None) -> DataFrame:
    """``ts`` as a zoned timestamp (a watermark refuses others), with the watermark on a stream."""
    out = events.withColumn("ts", F.col("ts").cast("timestamp"))
    return out.withWatermark("ts", watermark or WATERMARK) if events.isStreaming else out


def _counts():
    return F.count_if(F.col("event_type") == "purchase").alias("yes"), F.count(F.lit(1)).alias("n")


def windowed(events: DataFrame, width: str, slide: str | None = None) -> DataFrame:
    """user_id, start, yes, n by tumbling or sliding windows."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return timed(events).groupBy("user_id", w.alias("w")).agg(*_counts()).select("user_id", F.col("w.start").alias("start"), "yes", "n")


def sessions(events: DataFrame, gap: str) -> DataFrame:
    w = F.session_window("ts", gap)
    return timed(events).groupBy("user_id", w.alias("w")).agg(*_counts()).select("user_id", F.col("w.start").alias("start"), "yes", "n")


def deduplicated(events: DataFrame, keys: list[str]) -> DataFrame:
    """Repeated deliveries out; on a stream their keys are kept as long as the watermark."""
    e = timed(events)
    return e.dropDuplicatesWithinWatermark(keys) if events.isStreaming else e.dropDuplicates(keys)


def click_to_purchase(clicks: DataFrame, purchases: DataFrame) -> DataFrame:
    """Clicks followed by a purchase of the user within an hour; both sides may be streams."""
    c = timed(clicks).select(F.col("user_id").alias("c_user"), F.col("event_id").alias("click_id"), F.col("ts").alias("c_ts"))
    p = timed(purchases).select(F.col("user_id").alias("p_user"), F.col("event_id").alias("purchase_id"), F.col("ts").alias("p_ts"))
    return c.join(p, F.expr("c_user = p_user and p_ts >= c_ts and p_ts <= c_ts + interval 1 hour")).select("click_id", "purchase_id")


def running_kappa(verdicts: DataFrame) -> DataFrame:
    """verdicts: model, a, b (0/1), ts. model, n, kappa after each trigger; the state of a
    model is its four counts."""

    def step(key, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        c = list(state.get) if state.exists else [0, 0, 0, 0]
        for f in frames:
            for i, n in (2 * f["a"] + f["b"]).value_counts().items():
                c[int(i)] += int(n)
        state.update(tuple(c))
        n = sum(c)
        po, pa, pb = (c[0] + c[3]) / n, (c[2] + c[3]) / n, (c[1] + c[3]) / n
        pe = pa * pb + (1 - pa) * (1 - pb)
        yield pd.DataFrame({"model": [key[0]], "n": [n], "kappa": [1.0 if pe == 1 else (po - pe) / (1 - pe)]})

    return verdicts.groupBy("model").applyInPandasWithState(step, "model long, n long, kappa double", "c0 long, c1 long, c2 long, c3 long", "update", "NoTimeout")
