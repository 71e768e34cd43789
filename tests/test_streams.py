"""Streams equal their batch twins; rows later than the watermark are left out; state is kept per component."""

from datetime import datetime, timedelta

import pytest
from pyspark.sql import functions as F

from relstrata.sources.tables import load
from relstrata.streaming import reliability as rel


@pytest.fixture(scope="module")
def files(spark, sf, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("events"))
    ev = load(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp")).orderBy("ts", "event_id").collect()
    step = -(-len(ev) // 10)
    for k in range(10):
        spark.createDataFrame(ev[k * step : (k + 1) * step], rel.EVENTS).coalesce(1).write.parquet(f"{path}/all", mode="append")
    late = [(10**6 + i, datetime(2020, 1, 1) + timedelta(hours=i), i, "error", 1.0, "{}") for i in range(5)]
    spark.createDataFrame(late, rel.EVENTS).coalesce(1).write.parquet(f"{path}/late")
    return path, ev, late


def drain(df, name, mode, tmp):
    q = df.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", tmp).trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.table(name)


@pytest.mark.parametrize("slide", [None, "6 hours"])
def test_windows_equal_batch(spark, files, tmp_path, slide):
    path = files[0] + "/all"
    got = drain(rel.component_rates(rel.read_stream(spark, path), 10, slide=slide), f"w_{slide is None}", "complete", str(tmp_path / "c"))
    want = rel.component_rates(spark.read.schema(rel.EVENTS).parquet(path), 10, slide=slide)
    assert got.exceptAll(want).count() == 0 and want.exceptAll(got).count() == 0 and got.count()


def test_late_rows_are_left_out(spark, files, tmp_path):
    path, ev, late = files
    out = str(tmp_path / "in")
    spark.createDataFrame(ev, rel.EVENTS).coalesce(1).write.parquet(out)
    build = lambda: rel.component_rates(rel.read_stream(spark, out), 10, watermark="1 hour")
    seen = []

    def keep(df, _):
        seen.extend(df.collect())

    for _ in range(2):
        q = build().writeStream.outputMode("update").foreachBatch(keep).option("checkpointLocation", str(tmp_path / "c2")).trigger(availableNow=True).start()
        q.awaitTermination()
        spark.createDataFrame(late, rel.EVENTS).coalesce(1).write.parquet(out, mode="append")
    assert seen and not [r for r in seen if r["w_start"].year == 2020]


def test_sessions_equal_batch(spark, files, tmp_path):
    path = files[0] + "/all"
    got = drain(rel.error_sessions(rel.read_stream(spark, path)), "sessions", "complete", str(tmp_path / "c"))
    want = rel.error_sessions(spark.read.schema(rel.EVENTS).parquet(path))
    assert got.exceptAll(want).count() == 0 and got.count() == want.count()


def test_running_state(spark, files, tmp_path):
    path, ev, _ = files
    got = drain(rel.running_counts(rel.read_stream(spark, path + "/all", 3), 10), "running", "update", str(tmp_path / "c"))
    last = {r["comp_id"]: (r["e"], r["n"]) for r in got.groupBy("comp_id").agg(F.max("errors").alias("e"), F.max("events").alias("n")).collect()}
    for c in range(10):
        own = [r for r in ev if r["user_id"] % 10 == c]
        assert last.get(c, (0, 0)) == (sum(r["event_type"] == "error" for r in own), len(own))


def test_duplicates_within_the_watermark(spark, files, tmp_path):
    path, ev, _ = files
    stream = rel.read_stream(spark, path + "/all", 20)
    got = drain(rel.deduplicated(stream.union(stream)).select("event_id"), "dedup", "append", str(tmp_path / "c"))
    assert got.count() == len({r["event_id"] for r in ev})


def test_instants_do_not_depend_on_the_zone(spark):
    before = spark.conf.get("spark.sql.session.timeZone")
    try:
        for zone in ("UTC", "America/New_York"):
            spark.conf.set("spark.sql.session.timeZone", zone)
            df = spark.sql("SELECT timestamp_ntz'2024-03-10 02:30:00' AS ts").withColumn("t", rel.as_instant()).select(rel.as_wall("t").alias("x"))
            assert df.first()["x"] == "2024-03-10 02:30:00"
    finally:
        spark.conf.set("spark.sql.session.timeZone", before)


def test_appended_rows_never_come_to_the_driver(spark, sf):
    from relstrata.streaming import queries

    out = queries.run(spark, sf, lambda e: rel.deduplicated(e.union(e)).select("event_id"), "append")
    assert out.inputFiles()  # a table in memory has none
    want = load(spark, sf, "events").select("event_id").distinct()
    assert out.exceptAll(want).count() == 0 and out.count() == want.count()
