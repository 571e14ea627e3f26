"""Operating context of a statement: environment, waiting sessions, alerts, and the clock."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BROADCAST_ROWS = 1_000_000


def small(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """df with a broadcast hint if it has at most `rows` rows, else as it is, to be shuffled."""
    return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df


def with_env(log: DataFrame, env: DataFrame, on: str | list[str]) -> DataFrame:
    """Properties of the server that ran a statement."""
    return log.join(small(env), on, "left")


def with_clock(log: DataFrame, ts: str = "started") -> DataFrame:
    """Hour, and day of the week from 1 (Monday)."""
    return log.withColumn("hour", F.hour(ts)).withColumn("dow", F.weekday(ts) + 1)


def run_end(started: Column, seconds: Column) -> Column:
    """End of a run, at least a microsecond after its start, so that every run is a proper interval [started, ended)."""
    length = F.greatest(F.coalesce((seconds * 1_000_000).cast("bigint"), F.lit(1)), F.lit(1).cast("bigint"))
    return F.timestamp_micros(F.unix_micros(started) + length)


def overlapping(log: DataFrame, spans: DataFrame, server: str = "server", start: str = "started", end: str = "ended", bucket_hours: int = 24) -> DataFrame:
    """Pairs of a run (oid, _ts, _te) and a span [from_ts, to_ts) of its server that share time; spans keep their columns.

    Both sides are cut into buckets of time; the join is on server and bucket, the exact test follows. A pair that meets in
    several buckets counts in the first of them. Spans that don't end after they begin, and rows with nulls, pair with none.
    """
    bucket = lambda c: F.floor(F.unix_micros(c) / (bucket_hours * 3_600_000_000))
    cut = lambda a, b: F.explode(F.sequence(bucket(F.col(a)), bucket(F.col(b))))
    spread = spans.where("from_ts < to_ts").withColumnRenamed("server", "_server").withColumn("_b", cut("from_ts", "to_ts"))
    runs = log.select("oid", F.col(server).alias("_s"), F.col(start).alias("_ts"), F.col(end).alias("_te")).where("_ts < _te").withColumn("_rb", cut("_ts", "_te"))
    first = F.col("_b") == F.greatest(bucket(F.col("_ts")), bucket(F.col("from_ts")))
    on = (F.col("_s") == F.col("_server")) & (F.col("_rb") == F.col("_b")) & (F.col("_te") > F.col("from_ts")) & (F.col("_ts") < F.col("to_ts")) & first
    return runs.join(spread, on).drop("_s", "_server", "_b", "_rb")


def _joined(log: DataFrame, found: DataFrame, columns: list[Column]) -> DataFrame:
    return log.join(found.select(F.col("oid").alias("_oid"), *columns), F.col("oid") == F.col("_oid"), "left").drop("_oid")


def with_waits(log: DataFrame, waits: DataFrame, classes: list[str], agg: str = "count", value: str | None = None, kind: str = "kind", **interval) -> DataFrame:
    """For each class of waits a column `w_<class>` over the waits of the server during the run; 0 where there is none.

    `waits` has server, from_ts, to_ts and the class: a row for each waiting session (counted), or for each sample of an
    active session history (then `value` holds its number of sessions, and agg is sum, avg or max).
    """
    how = {"avg": F.avg, "sum": F.sum, "count": F.count, "max": F.max}[agg]
    wide = overlapping(log, waits, **interval).groupBy("oid").pivot(kind, classes).agg(how(F.col(value) if value else F.lit(1)))
    return _joined(log, wide, [F.col(f"`{c}`").alias(f"w_{c}") for c in classes]).fillna(0, [f"w_{c}" for c in classes])


def with_alerts(log: DataFrame, alerts: DataFrame, kinds: list[str], levels: tuple[str, ...], **interval) -> DataFrame:
    """For each kind the highest level on at any time of the run, as an ordinal column `a_<kind>`; null where none is."""
    place = F.array_position(F.lit(list(levels)), F.col("level"))
    hit = overlapping(log, alerts, **interval).groupBy("oid").pivot("kind", kinds).agg(F.max(place))
    return _joined(log, hit, [F.try_element_at(F.lit(list(levels)), F.col(f"`{k}`").cast("int")).alias(f"a_{k}") for k in kinds])
