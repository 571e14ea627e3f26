"""Targets of a search."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from slowlens.operators.enrich import overlapping


def threshold(col: Column | str, op: str, value: float) -> Column:
    """1 where the comparison holds, 0 where it doesn't; slow is strictly above."""
    c = F.col(col) if isinstance(col, str) else col
    return {">": c > value, ">=": c >= value, "<": c < value, "<=": c <= value}[op].cast("int")


def in_levels(col: str, levels: list[str]) -> Column:
    return F.coalesce(F.col(col).isin(levels), F.lit(False)).cast("int")


def one_vs_rest(col: str, value: object) -> Column:
    return (F.col(col) == F.lit(value)).cast("int")


def painted(left: Column, right: Column) -> Column:
    """1 for rows of both selections, 0 for the rest of the first, null outside of it."""
    return F.when(left & right, 1).when(left, 0)


def all_of(*targets: Column) -> Column:
    """Several binary targets at once."""
    return F.least(*targets)


def concurrence(log: DataFrame, waits: DataFrame, level: float, period_s: int = 10, **interval) -> DataFrame:
    """Column `concurrence`: whether `level` or more sessions wait on average in some period of the run.

    Periods go from the start of the run, the last one to its end; a session counts by its share of the period. Sessions
    that wait all through a run add one to each of its periods; only others are dealt over periods.
    """
    step = period_s * 1_000_000
    s, e, f, t = (F.unix_micros(c) for c in ("_ts", "_te", "from_ts", "to_ts"))
    pairs = overlapping(log, waits, **interval).select("oid", (e - s).alias("len"), F.greatest(f - s, F.lit(0)).alias("a"), (F.least(t, e) - s).alias("b"))
    through = (F.col("a") == 0) & (F.col("b") == F.col("len"))
    place = lambda c: F.floor(c / step)
    dealt = pairs.withColumn("p", F.explode(F.when(through, F.array(F.lit(-1).cast("bigint"))).otherwise(F.sequence(place(F.col("a")), place(F.col("b") - 1)))))
    low, high = F.col("p") * step, F.least((F.col("p") + 1) * step, F.col("len"))
    within = F.when(F.col("p") < 0, F.lit(1)).otherwise(F.least(F.col("b"), high) - F.greatest(F.col("a"), low))
    summed = dealt.groupBy("oid", "p", F.when(F.col("p") < 0, F.lit(1)).otherwise(high - low).alias("size")).agg(F.sum(within).alias("x"))
    whole = F.coalesce(F.max(F.when(F.col("p") < 0, F.col("x"))), F.lit(0))
    part = F.coalesce(F.max(F.when(F.col("p") >= 0, F.col("x") / F.col("size"))), F.lit(0.0))
    best = summed.groupBy("oid").agg((whole + part).alias("_best")).withColumnRenamed("oid", "_oid")
    joined = log.join(best, F.col("oid") == F.col("_oid"), "left")
    return joined.withColumn("concurrence", (F.coalesce("_best", F.lit(0.0)) >= level).cast("int")).drop("_oid", "_best")
