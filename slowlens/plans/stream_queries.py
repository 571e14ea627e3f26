"""Streams over the events, run on what is there; their oracles are the batch form without windows still open."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from slowlens.operators.dataset import SubgroupDataset
from slowlens.operators.selectors import Selector
from slowlens.plans import oracle
from slowlens.plans.registry import query
from slowlens.session import load
from slowlens.sources import datasets
from slowlens.sources.formats import work_path
from slowlens.streaming import pipelines as st


def event_files(spark: SparkSession, d: str, parts: int = 4) -> str:
    """The events in files of rising time, as a log directory."""
    path = work_path(spark, "events")
    load(spark, d, "events").repartitionByRange(parts, "ts").sortWithinPartitions("ts").write.parquet(path)
    return path


def stream(spark: SparkSession, d: str) -> DataFrame:
    return st.read_stream(spark, event_files(spark, d))


# windows that end at or before the watermark (the last event less the delay) are final in append mode
_MARK = "(SELECT max(ts) - INTERVAL 1 HOUR FROM events)"

query("st_ingest", "SELECT event_id, user_id, event_type, value FROM events")(lambda spark, d: st.run_available(stream(spark, d).select("event_id", "user_id", "event_type", "value")))
query("st_tumbling", f"SELECT date_trunc('day', ts) AS start, event_type, CAST(count(*) AS BIGINT) AS n FROM events GROUP BY 1, 2 HAVING date_trunc('day', ts) + INTERVAL 1 DAY <= {_MARK}")(lambda spark, d: st.run_available(st.tumbling_waits(stream(spark, d))))
query("st_sliding", f"SELECT s AS start, CAST(count(*) AS BIGINT) AS n, CAST(count(*) FILTER (WHERE event_type = 'error') AS BIGINT) AS errors FROM (SELECT *, unnest([date_trunc('hour', ts), date_trunc('hour', ts) - INTERVAL 1 HOUR]) AS s FROM events) GROUP BY 1 HAVING s + INTERVAL 2 HOUR <= {_MARK}")(lambda spark, d: st.run_available(st.sliding_alerts(stream(spark, d))))
query("st_session", f"WITH a AS (SELECT user_id, ts, CASE WHEN ts <= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events), b AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS g FROM a) SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 6 HOUR AS \"end\", CAST(count(*) AS BIGINT) AS n FROM b GROUP BY user_id, g HAVING max(ts) + INTERVAL 6 HOUR <= {_MARK}")(lambda spark, d: st.run_available(st.sessions(stream(spark, d))))
query("st_env", "SELECT event_id, c_mktsegment FROM events LEFT JOIN customer ON user_id = c_custkey")(lambda spark, d: st.run_available(st.with_environment(stream(spark, d), datasets.environment(spark, d)).select("event_id", "c_mktsegment")))
query("st_interval", "SELECT x.event_id AS oid, y.event_id AS alert FROM events x JOIN events y ON x.user_id = y.user_id AND y.event_type = 'error' AND x.ts > y.ts AND x.ts <= y.ts + INTERVAL 48 HOUR")(lambda spark, d: (lambda p: st.run_available(st.runs_with_alerts(st.read_stream(spark, p), st.read_stream(spark, p))))(event_files(spark, d)))


@query("st_dedupe", "SELECT event_id FROM events")
def st_dedupe(spark: SparkSession, d: str) -> DataFrame:
    path = work_path(spark, "twice")
    e = load(spark, d, "events")
    e.unionByName(e.where("event_id % 3 = 0")).write.parquet(path)
    return st.run_available(st.deduplicated(st.read_stream(spark, path)).select("event_id"))


@query("st_watch", f"SELECT description, CAST(count(*) AS BIGINT) AS n, round(CAST(sum(time_s) AS DOUBLE) / count(*), 6) AS mean, CAST(sum(time_s) AS DOUBLE) / count(*) > 50 AS crossed FROM (SELECT time_s, unnest(list_filter(['all', CASE WHEN event_type = 'error' THEN 'event_type=error' END, CASE WHEN user_id < 50 THEN 'user_id<50' END], lambda x: x IS NOT NULL)) AS description FROM (SELECT *, CAST(value AS DECIMAL(18,2)) AS time_s FROM events)) GROUP BY 1")
def st_watch(spark: SparkSession, d: str) -> DataFrame:
    watch = st.Watch(spark, [(Selector("event_type", "=", "error"),), (Selector("user_id", "<", 50),)], "value", 50)
    watch.start(st.read_stream(spark, event_files(spark, d), 1)).awaitTermination()
    return watch.table()


@query("st_remine", oracle.search(oracle.EVENTS_PLAIN, oracle.selectors(("event_type",)), "wracc", 5, 1, 50))
def st_remine(spark: SparkSession, d: str) -> DataFrame:
    out: list[DataFrame] = []
    build = lambda df: SubgroupDataset(df.select(F.col("event_id").alias("oid"), F.col("value").cast("decimal(18,2)").alias("t"), "event_type"), nominal=("event_type",))
    st.remine(stream(spark, d), build, ["event_type"], out, depth=1).awaitTermination()
    return out[-1]
