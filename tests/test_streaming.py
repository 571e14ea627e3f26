"""Streams: late rows, recovery, replayed batches, sinks."""

import datetime

from pyspark.sql import functions as F

from slowlens.operators.selectors import Selector
from slowlens.sources import formats
from slowlens.streaming import pipelines as st

T0 = datetime.datetime(2024, 1, 1)
SCHEMA = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def rows(*hours, start=0):
    return [(start + i, T0 + datetime.timedelta(hours=h), i % 3, "error" if i % 2 else "view", float(i), "{}") for i, h in enumerate(hours)]


def put(spark, path, data):
    spark.createDataFrame(data, SCHEMA).coalesce(1).write.mode("append").parquet(path)


def test_late_rows_are_dropped_and_counted(spark):
    path = formats.work_path(spark, "late")
    put(spark, path, rows(0, 1, 30, 50))
    mark, out = formats.work_path(spark, "mark"), formats.work_path(spark, "out")

    def go():
        q = st.tumbling_waits(st.read_stream(spark, path), "1 hour").writeStream.format("parquet").option("path", out).option("checkpointLocation", mark).trigger(availableNow=True).start()
        q.awaitTermination()
        return q

    go()
    put(spark, path, rows(2, 80, start=10))  # hour 2 is far behind the watermark of hour 49
    second = go()
    dropped = sum(o["numRowsDroppedByWatermark"] for p in second.recentProgress for o in p["stateOperators"])
    got = {r["start"] for r in spark.read.parquet(out).collect()}
    assert dropped == 1 and T0 + datetime.timedelta(hours=2) not in {g.replace(tzinfo=None) for g in got} and len(got) == 4


def test_recovery_reads_each_file_once(spark):
    path, mark = formats.work_path(spark, "in"), formats.work_path(spark, "mark")
    out = formats.work_path(spark, "out")
    for part in (rows(1, 2, 3), rows(4, 5, start=10)):
        put(spark, path, part)
        q = st.read_stream(spark, path).writeStream.format("parquet").option("path", out).option("checkpointLocation", mark).trigger(availableNow=True).start()
        q.awaitTermination()
    assert sorted(r["event_id"] for r in spark.read.parquet(out).collect()) == [0, 1, 2, 10, 11]


def test_watch_ignores_a_replayed_batch(spark):
    watch = st.Watch(spark, [(Selector("event_type", "=", "error"),)], "value", 1.0)
    assert watch.table().count() == 0
    batch = spark.createDataFrame(rows(1, 2, 3, 4), SCHEMA)
    watch.update(batch, 0)
    watch.update(batch, 0)
    watch.update(batch, 1)
    got = {r["description"]: (r["n"], r["mean"], r["crossed"]) for r in watch.table().collect()}
    assert got == {"all": (8, 1.5, True), "event_type=error": (4, 2.0, True)}


def test_watch_goes_on_after_a_restart(spark):
    path, where = formats.work_path(spark, "in"), formats.work_path(spark, "watch")
    for part in (rows(1, 2, 3, 4), rows(5, 6, start=10), rows(7, start=20)):
        put(spark, path, part)
        watch = st.Watch(spark, [(Selector("event_type", "=", "error"),)], "value", 1.0, where)  # made anew each time
        watch.start(st.read_stream(spark, path)).awaitTermination()
    got = {r["description"]: (r["n"], r["mean"]) for r in watch.table().collect()}
    assert got == {"all": (7, 1.0), "event_type=error": (3, round(5 / 3, 6))}
    assert watch._versions() == [1, 2]


def test_watch_keeps_the_scale_of_its_target(spark):
    watch = st.Watch(spark, [(Selector("k", "<", 2),)], "t", 0.0)
    watch.update(spark.sql("SELECT id AS k, CAST(0.0015 AS DECIMAL(10,4)) AS t FROM range(4) UNION ALL SELECT 9, NULL"), 0)
    assert {r["description"]: (r["n"], r["mean"]) for r in watch.table().collect()} == {"all": (4, 0.0015), "k<2": (2, 0.0015)}


def test_complete_mode_and_result_sink(spark):
    path = formats.work_path(spark, "in")
    put(spark, path, rows(1, 2, 3))
    total = st.run_available(st.read_stream(spark, path).groupBy("event_type").agg(F.count("*").alias("n")), "complete")
    assert {r["event_type"]: r["n"] for r in total.collect()} == {"view": 2, "error": 1}
    where = formats.work_path(spark, "result")
    formats.save_result(total, where)
    assert spark.read.parquet(f"{where}/parquet").count() == spark.read.json(f"{where}/json").count() == 2


def test_bucketed_join_exchanges_nothing(spark):
    df = spark.range(1000).select(F.col("id").alias("k"))
    a, b = formats.bucketed(df, "k", 4), formats.bucketed(df, "k", 4)
    plan = a.join(b.hint("merge"), a.k == b.k)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan.replace("BroadcastExchange", "")


def test_filters_reach_the_scan(spark):
    from slowlens.plans.registry import QUERIES
    from slowlens.plans import text_queries  # noqa: F401

    plan = QUERIES["p_record_threshold"](spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
    assert "GreaterThan(value,5.0)" in plan and "props" not in plan
