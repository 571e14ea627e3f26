"""Exact quantiles without a task that holds all distinct values.

A sketch of fixed size cuts the values into bins, the bins are counted, and only the bins in which a wanted place lies are
looked at again, until their distinct values are few. Interpolation is as in Spark's own `percentile`.
"""

from __future__ import annotations

import bisect

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from slowlens.functions.literals import constant

BINS, FEW = 2048, 200_000


def place(value: Column, edges: list[float]) -> Column:
    """How many of the sorted edges lie at or below the value, by binary search."""
    cuts = constant(edges, "array<double>")
    steps = [1 << b for b in range(len(edges).bit_length() - 1, -1, -1)]
    return F.aggregate(F.lit(steps), F.lit(0), lambda at, step: F.when((at + step <= len(edges)) & (F.try_element_at(cuts, at + step) <= value), at + step).otherwise(at))


def _counted(rows: DataFrame, wanted: list[int], few: int, bins: int) -> dict[int, float]:
    """The values of `v` at the wanted places (from 0) of the sorted rows."""
    head = rows.groupBy("v").agg(F.count("*").alias("n")).limit(few + 1)
    if head.agg(F.count("*")).first()[0] <= few:
        counts = sorted((r["v"], r["n"]) for r in rows.groupBy("v").agg(F.count("*").alias("n")).collect())  # at most `few` rows
        upto, total = [], 0
        for _, n in counts:
            total += n
            upto.append(total)
        return {p: counts[bisect.bisect_right(upto, p)][0] for p in wanted}
    edges = edges_of(rows, "v", bins)
    binned = rows.withColumn("bin", place(F.col("v"), edges))
    sizes = sorted((r["bin"], r["n"]) for r in binned.groupBy("bin").agg(F.count("*").alias("n")).collect())  # at most bins + 2 rows
    out, before = {}, 0
    for b, n in sizes:
        mine = [p - before for p in wanted if before <= p < before + n]
        if mine:
            inside = binned.where(F.col("bin") == b).select("v")
            out |= {p + before: v for p, v in _counted(inside, mine, few, bins).items()}
        before += n
    return out


def quantiles(rows: DataFrame, column: str, at: list[float], n: int | None = None, few: int = FEW, bins: int = BINS) -> list[float]:
    """Interpolated quantiles of a column at shares `at`; nulls take no part; no values, no quantiles."""
    values = rows.select(F.col(column).cast("double").alias("v")).where("v is not null")
    n = values.count() if n is None else n
    if not n:
        return []
    spots = [q * (n - 1) for q in at]
    wanted = sorted({p for s in spots for p in (int(s // 1), min(n - 1, int(-(-s // 1))))})
    found = _counted(values, wanted, few, bins)
    out = []
    for s in spots:
        lo, hi = int(s // 1), min(n - 1, int(-(-s // 1)))
        a, b = found[lo], found[hi]
        out.append(a if lo == hi or a == b else (hi - s) * a + (s - lo) * b)
    return out


def median(rows: DataFrame, column: str, n: int | None = None) -> float | None:
    return next(iter(quantiles(rows, column, [0.5], n)), None)


def edges_of(rows: DataFrame, column: str, bins: int = BINS) -> list[float]:
    """Sorted bin edges from a sketch of the column, its extremes included; empty without rows."""
    v = F.col(column).cast("double")
    row = rows.agg(F.percentile_approx(v, [i / bins for i in range(bins + 1)], 10 * bins).alias("q"), F.min(v).alias("lo"), F.max(v).alias("hi")).first()
    return sorted({row["lo"], *row["q"], row["hi"]}) if row["q"] else []


def middle_bins(counts: DataFrame, key: str) -> DataFrame:
    """From (key, bin, n) the one or two bins that hold a key's middle rows: (_k, _bin, before, low, high)."""
    run = Window.partitionBy(key).orderBy("bin").rowsBetween(Window.unboundedPreceding, 0)
    counts = counts.withColumn("upto", F.sum("n").over(run)).withColumn("all", F.sum("n").over(Window.partitionBy(key)))
    low, high = F.floor((F.col("all") + 1) / 2), F.floor(F.col("all") / 2) + 1
    held = counts.where((F.col("upto") >= low) & (F.col("upto") - F.col("n") < high))
    return held.select(F.col(key).alias("_k"), F.col("bin").alias("_bin"), (F.col("upto") - F.col("n")).alias("before"), low.alias("low"), high.alias("high"))


def medians_from(counts: DataFrame, middle: DataFrame, key: str) -> DataFrame:
    """(_k, med) from (key, bin, v, n), the counts by value, of which only those in `middle` are ordered."""
    met = counts.join(middle, (F.col(key) == F.col("_k")) & (F.col("bin") == F.col("_bin"))).groupBy("_k", "bin", "v", "before", "low", "high").agg(F.sum("n").alias("n"))
    by_value = Window.partitionBy("_k", "bin").orderBy("v").rowsBetween(Window.unboundedPreceding, 0)
    placed = met.withColumn("upto", F.col("before") + F.sum("n").over(by_value))
    at = lambda spot: F.max(F.when((F.col("upto") >= F.col(spot)) & (F.col("upto") - F.col("n") < F.col(spot)), F.col("v")))
    return placed.groupBy("_k").agg(at("low").alias("a"), at("high").alias("b")).select("_k", (F.col("a") * 0.5 + F.col("b") * 0.5).alias("med"))


def grouped_medians(rows: DataFrame, key: str, column: str, bins: int = BINS) -> DataFrame:
    """(_k, med): the exact median of a column for each key, no task ordering more than a key's middle bins."""
    edges = edges_of(rows, column, bins)
    v = F.col(column).cast("double")
    counts = rows.where(v.isNotNull()).groupBy(key, place(v, edges).alias("bin"), v.alias("v")).agg(F.count("*").alias("n"))
    return medians_from(counts, middle_bins(counts.groupBy(key, "bin").agg(F.sum("n").alias("n")), key), key)
