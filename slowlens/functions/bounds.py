"""Optimistic estimates: no refinement with `floor` rows or more can score above them.

They come from the same aggregation as the score: pos (sum of the positive deviations), npos (rows above the mean),
tmax and, for the two-sided measure, neg. Derivations: a refinement gains most by keeping the rows above the mean; its i
best rows sum to at most min(pos, i x largest deviation).
"""

from __future__ import annotations

from pyspark.sql import Column, Window
from pyspark.sql import functions as F

from slowlens.functions.measures import Measure, Norms

INPUTS = ("pos", "neg", "npos", "tmax")


def of_row(target: Column, norms: Norms) -> dict[str, Column]:
    """What a row adds to the extra aggregates, on doubles."""
    d = target.cast("double") - F.lit(norms.mean)
    zero = F.lit(0.0)
    return {"pos": F.greatest(d, zero), "neg": F.greatest(-d, zero), "npos": (d > 0).cast("long"), "tmax": target.cast("double")}


def inputs(target: Column, norms: Norms) -> dict[str, Column]:
    """The extra aggregates."""
    return {k: F.max(c) if k == "tmax" else F.sum(c) for k, c in of_row(target, norms).items()}


def _family(a: float, g: Norms, floor: int, binary: bool) -> Column:
    n0 = float(g.n) ** -a
    low = float(max(1, floor)) ** (a - 1)
    if binary:
        full = F.pow(F.col("npos") / F.lit(float(g.n)), F.lit(a)) * (1 - g.mean)
        filled = F.lit(n0 * low) * (F.col("npos") * (1 - g.mean) - (floor - F.col("npos")) * g.mean)
        return F.when(F.col("npos") >= floor, full).otherwise(filled)
    top = F.col("tmax") - g.mean
    turn = F.col("pos") / top
    best = F.when(turn >= floor, F.lit(n0) * F.pow(turn, F.lit(a)) * top).otherwise(F.lit(n0 * low) * F.col("pos"))
    if a == 1:
        best = F.col("pos") / g.n
    return F.when(top > 0, best).otherwise(F.lit(0.0))


def estimate(measure: Measure, g: Norms, floor: int, binary: bool = False) -> Column:
    """The moment form; null where the measure has no estimate, which prunes nothing."""
    a = measure.a or 0.0
    if measure.bound == "family":
        return _family(a, g, floor, binary)
    if measure.bound == "lift" and g.mean > 0:
        return 1 + _family(0.0, g, floor, binary) / g.mean
    if measure.bound == "binomial" and 0 < g.mean < 1:
        return _family(0.5, g, floor, True) * (g.n / (g.mean * (1 - g.mean))) ** 0.5
    if measure.bound == "two_sided":
        return F.greatest("pos", "neg") / g.n
    if measure.bound == "median":
        return F.greatest(F.pow(F.col("n") / F.lit(float(g.n)), F.lit(a)) * (F.col("tmax") - g.median), F.lit(0.0))
    return F.lit(None).cast("double")


def _by_falling_bins(bins, key: list[str]):
    """Running counts and sums before each bin, from the highest bin down: at most a row for each candidate and bin."""
    down = Window.partitionBy(*key).orderBy(F.desc("bin")).rowsBetween(Window.unboundedPreceding, -1)
    zero = lambda c: F.coalesce(F.sum(c).over(down), F.lit(0.0))
    return bins.withColumn("_before", zero("n")).withColumn("_sum", zero("s")).withColumn("_end", F.col("_before") + F.col("n"))


def binned_family(bins, key: list[str], a: float, g: Norms, floor: int):
    """At least the optimum over all refinements for any target, and exactly it where a bin holds one value.

    `bins` has key, bin, n, s (sum of the target), top (its maximum in the bin). The best refinement of i rows takes the i
    largest; within a bin they sum to no more than i times its top, and the value is greatest at an end of the bin.
    """
    runs = _by_falling_bins(bins, key)
    deviation = F.col("_sum") - F.col("_before") * g.mean

    def value(i: Column) -> Column:
        return F.lit(float(g.n) ** -a) * F.pow(i, F.lit(a - 1)) * (deviation + (i - F.col("_before")) * (F.col("top") - g.mean))

    first = F.greatest(F.col("_before"), F.lit(float(max(floor, 1))))
    return runs.where(F.col("_end") >= max(floor, 1)).groupBy(*key).agg(F.max(F.greatest(value(first), value(F.col("_end").cast("double")))).alias("bound"))


def binned_median(bins, key: list[str], a: float, g: Norms, floor: int):
    """The same for the median score: of q rows the median is at most the ceil(q / 2)-th largest value."""
    runs = _by_falling_bins(bins, key).withColumn("_n", F.sum("n").over(Window.partitionBy(*key)))
    gain = F.col("top") - g.median
    most = F.greatest(F.least(2 * F.col("_end"), F.col("_n")), F.lit(float(floor)))
    least = F.greatest(2 * F.col("_before") + 1, F.lit(float(floor)))
    ok = (F.col("_n") >= floor) & (2 * F.col("_before") + 1 <= F.col("_n")) & (least <= most)
    size = lambda q: F.pow(q.cast("double") / g.n, F.lit(a))
    return runs.where(ok).groupBy(*key).agg(F.max(F.greatest(size(most) * gain, size(least) * gain)).alias("bound"))
