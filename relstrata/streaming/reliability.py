"""Reliability over time: a fixed signature meets failure probabilities from an event stream.

``component_rates`` is the same plan for batch and stream: errors and events per component
and window. With a watermark, rows that come later than it are left out.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.baselines import reliability_column

EVENTS = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"


def as_instant(ts: str = "ts"):
    """A timestamp without zone as the UTC instant, whatever the session's zone; watermarks need instants."""
    return F.expr(f"cast(concat(cast(cast({ts} as timestamp_ntz) as string), '+00:00') as timestamp)")


def as_wall(instant: str):
    """The way back, as text; from the seconds alone, so that no zone's clock changes come in."""
    day = f"cast(date_from_unix_date(cast(floor(unix_seconds({instant}) / 86400) as int)) as string)"
    part = lambda unit, top: f"lpad(cast(pmod(floor(unix_seconds({instant}) / {unit}), {top}) as string), 2, '0')"
    return F.expr(f"concat({day}, ' ', {part(3600, 24)}, ':', {part(60, 60)}, ':', {part(1, 60)})")


def component_rates(events: DataFrame, n: int, window: str = "1 day", slide: str | None = None, scale: float = 0.05, watermark: str | None = None) -> DataFrame:
    """(w_start, comp_id, errors, events, p)"""
    if watermark:
        events = events.withWatermark("ts", watermark)
    err = F.count_if(F.col("event_type") == "error")
    g = events.groupBy(F.window("ts", window, slide).alias("w"), F.pmod("user_id", F.lit(n)).cast("int").alias("comp_id"))
    a = g.agg(err.alias("errors"), F.count(F.lit(1)).alias("events"))
    return a.select(F.col("w.start").alias("w_start"), "comp_id", "errors", "events", (F.lit(scale) * (F.col("errors") + 1) / (F.col("events") + 2)).alias("p"))


def mean_rate(events: DataFrame, window: str = "1 day", scale: float = 0.05, watermark: str | None = None) -> DataFrame:
    """(w_start, p): one rate for all components, as the signature of equal components needs."""
    if watermark:
        events = events.withWatermark("ts", watermark)
    err = F.count_if(F.col("event_type") == "error")
    a = events.groupBy(F.window("ts", window).alias("w")).agg((F.lit(scale) * (err + 1) / (F.count(F.lit(1)) + 2)).alias("p"))
    return a.select(F.col("w.start").alias("w_start"), "p")


def reliability(rates: DataFrame, phis: list[float], n: int) -> DataFrame:
    """(w_start, p, reliability): the signature is not recomputed when rates move."""
    return rates.select("w_start", "p", reliability_column(phis, n, F.col("p")).alias("reliability"))


def error_sessions(events: DataFrame, gap: str = "30 minutes", watermark: str | None = None) -> DataFrame:
    if watermark:
        events = events.withWatermark("ts", watermark)
    e = events.where("event_type = 'error'")
    return e.groupBy("user_id", F.session_window("ts", gap).alias("s")).agg(F.count(F.lit(1)).alias("errors")).select("user_id", F.col("s.start").alias("s_start"), "errors")


def deduplicated(events: DataFrame, watermark: str = "1 hour") -> DataFrame:
    """Each event_id once within the watermark."""
    return events.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])


def running_counts(events: DataFrame, n: int) -> DataFrame:
    """(comp_id, errors, events): running counts per component, kept as state in the default state store."""

    def count(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        errors, events = state.get if state.exists else (0, 0)
        for pdf in batches:
            errors += int((pdf["event_type"] == "error").sum())
            events += len(pdf)
        state.update((errors, events))
        yield pd.DataFrame({"comp_id": [key[0]], "errors": [errors], "events": [events]})

    keyed = events.select(F.pmod("user_id", F.lit(n)).cast("int").alias("comp_id"), "event_type")
    return keyed.groupBy("comp_id").applyInPandasWithState(count, "comp_id int, errors long, events long", "errors long, events long", "update", "NoTimeout")


def read_stream(spark: SparkSession, path: str, files_per_trigger: int = 1, schema: str = EVENTS) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
