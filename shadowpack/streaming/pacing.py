"""Online use of solved prices: spend per window, admission at fixed prices, pacing by the remaining budget."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout


def _cents():
    return F.floor(F.col("value") * 100 + 0.5).cast("bigint")


def _watermarked(events: DataFrame, watermark: str) -> DataFrame:
    """Watermarks need instants: local times count in the session's time zone."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark)


def window_spend(events: DataFrame, length: str, slide: str | None = None, watermark: str | None = None) -> DataFrame:
    """Spend (cents) per event type and tumbling or sliding window; late rows go if there is a watermark."""
    if watermark:
        events = _watermarked(events, watermark)
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return events.groupBy("event_type", w.alias("w")).agg(F.sum(_cents()).alias("cents")).select("event_type", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "cents")


def session_spend(events: DataFrame, gap: str, watermark: str | None = None) -> DataFrame:
    """Spend and events per user session (events less than `gap` apart)."""
    if watermark:
        events = _watermarked(events, watermark)
    s = F.session_window("ts", gap)
    return events.groupBy("user_id", s.alias("s")).agg(F.count(F.lit(1)).alias("n"), F.sum(_cents()).alias("cents")).select("user_id", F.col("s.start").alias("start"), "n", "cents")


def asof_version(events: DataFrame, versions: DataFrame, at: str, valid_from: str) -> DataFrame:
    """events with the latest version at or before them. versions: a short list of distinct times; each becomes
    the half-open interval to the next one, and the join is a broadcast range join."""
    nxt = F.lead(valid_from).over(Window.orderBy(valid_from))
    spans = F.broadcast(versions.withColumn("_until", nxt))
    return events.join(spans, (F.col(at) >= F.col(valid_from)) & (F.col("_until").isNull() | (F.col(at) < F.col("_until")))).drop("_until")


def admit(events: DataFrame, prices: DataFrame) -> DataFrame:
    """Stream or batch of events (event_type, value) against a small static price table (event_type, price in
    cents per event): takes those with a positive net."""
    net = _cents() - F.col("price")
    return events.join(F.broadcast(prices), "event_type").withColumn("net", net).where("net > 0")


def deduplicated(events: DataFrame, watermark: str = "1 hour") -> DataFrame:
    """Each event_id once within the watermark."""
    return _watermarked(events, watermark).dropDuplicatesWithinWatermark(["event_id"])


PACED = "event_type string, taken long, spent long"


def paced_spend(events: DataFrame, budget_cents: int) -> DataFrame:
    """Running admissions per event type: each event is taken while the type's spend stays within its budget;
    spend is kept as state between micro-batches."""

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        taken, spent = state.get if state.exists else (0, 0)
        for frame in frames:
            for cents in frame.sort_values(["ts", "event_id"])["cents"]:
                if spent + cents <= budget_cents:
                    taken, spent = taken + 1, spent + int(cents)
        state.update((taken, spent))
        yield pd.DataFrame({"event_type": [key[0]], "taken": [taken], "spent": [spent]})

    rows = events.select("event_type", "event_id", "ts", _cents().alias("cents"))
    return rows.groupBy("event_type").applyInPandasWithState(step, PACED, "taken long, spent long", "update", GroupStateTimeout.NoTimeout)


def resolve_each_batch(events: DataFrame, solve_batch: Callable[[DataFrame, int], None], checkpoint: str):
    """Starts a query that re-solves prices on every micro-batch (foreachBatch)."""
    return events.writeStream.foreachBatch(solve_batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
