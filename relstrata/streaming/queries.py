"""Streams over a copy of the events table, run to the end of the input."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans import n10
from ..sources.scratch import scratch_path
from ..sources.tables import load
from . import reliability as rel

Q: dict[str, Callable] = {}
O: dict[str, str] = {}


def event_files(spark, sf: str, parts: int = 6) -> str:
    """The events in time-ordered files, as a stream would find them."""

    def make():
        path = scratch_path(spark, "events-stream")
        load(spark, sf, "events").repartitionByRange(parts, "ts").sortWithinPartitions("ts").write.parquet(path)
        return path

    return n10.once(spark, "event-files", sf, make)


def run(spark, sf: str, build, mode: str) -> DataFrame:
    """Run a stream over all files, with its checkpoint in the shared folder.

    Rows that are only ever appended grow with the input and go to files in the shared folder; a row
    a window or component, sent anew as it changes, goes to a table in memory.
    """
    path = event_files(spark, sf)
    # All files in one batch: files carry no order of their own, and a watermark moves between batches.
    events = rel.read_stream(spark, path, 10_000, spark.read.parquet(path).schema)
    df = build(events.withColumn("ts", rel.as_instant()))
    writer = df.writeStream.outputMode(mode).option("checkpointLocation", scratch_path(spark, "stream")).trigger(availableNow=True)
    if mode == "append":
        out = scratch_path(spark, "stream-rows")
        writer.format("parquet").start(out).awaitTermination()
        return spark.read.schema(df.schema).parquet(out)
    name = f"stream_{uuid.uuid4().hex}"
    writer.format("memory").queryName(name).start().awaitTermination()
    return spark.table(name)


def phis(spark, sf: str) -> list[float]:
    rows = n10.states(spark, sf).groupBy("i").agg(F.avg((~F.col("fail")).cast("int")).alias("phi")).orderBy("i").collect()
    return [x["phi"] for x in rows]


def w21_reliability_stream(spark, sf):
    out = run(spark, sf, lambda e: rel.mean_rate(e), "complete")
    return rel.reliability(out, phis(spark, sf), n10.N).select(rel.as_wall("w_start").alias("w_start"), F.round("p", 12).alias("p"), F.round("reliability", 10).alias("reliability"))


def op_stream_watermark(spark, sf):
    """Complete rates per window; append mode would hold back the last windows."""
    out = run(spark, sf, lambda e: rel.component_rates(e, 10, watermark="1 hour"), "update")
    last = out.groupBy("w_start", "comp_id").agg(F.max_by(F.struct("errors", "events"), "events").alias("x"))
    return last.select(rel.as_wall("w_start").alias("w_start"), "comp_id", "x.errors", "x.events")


def op_stream_dedup(spark, sf):
    out = run(spark, sf, lambda e: rel.deduplicated(e.union(e)).select("event_id"), "append")
    return out.agg(F.count(F.lit(1)).alias("n"), F.count_distinct("event_id").alias("ids"))


def op_stream_state(spark, sf):
    """Running counts per component, kept as state; the last update of each is the whole count."""
    out = run(spark, sf, lambda e: rel.running_counts(e, 10), "update")
    return out.groupBy("comp_id").agg(F.max("errors").alias("errors"), F.max("events").alias("events"))


Q |= {f.__name__: f for f in (w21_reliability_stream, op_stream_watermark, op_stream_dedup, op_stream_state)}
O["op_stream_state"] = "SELECT (user_id % 10)::INT AS comp_id, count_if(event_type = 'error') AS errors, count(*) AS events FROM events GROUP BY 1"
O["w21_reliability_stream"] = n10.sql(""", ph AS (SELECT i, sum((NOT fail)::INT) AS works FROM g GROUP BY i),
rt AS (SELECT time_bucket(INTERVAL 1 DAY, ts)::VARCHAR AS w_start, 0.05 * (count_if(event_type = 'error') + 1) / (count(*) + 2) AS p FROM events GROUP BY 1)
SELECT w_start, round(p, 12) AS p, round(sum(works * pow(p, i) * pow(1 - p, 10 - i)), 10) AS reliability FROM rt, ph GROUP BY w_start, p""")
O["op_stream_watermark"] = "SELECT time_bucket(INTERVAL 1 DAY, ts)::VARCHAR AS w_start, (user_id % 10)::INT AS comp_id, count_if(event_type = 'error') AS errors, count(*) AS events FROM events GROUP BY 1, 2"
O["op_stream_dedup"] = "SELECT count(DISTINCT event_id) AS n, count(DISTINCT event_id) AS ids FROM events"
