"""Statistics of all refinements of a set of patterns in one scan of the encoded data."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from slowlens.functions.exact import Form, summand
from slowlens.functions.literals import constant
from slowlens.functions.quantiles import edges_of, medians_from, middle_bins, place
from slowlens.operators.dataset import SubgroupDataset
from slowlens.operators.selectors import Selector

BOUND_INPUTS = ("pos", "neg", "npos")
BINS, UNROLLED = 1024, 64


def blocked_pairs(selectors: list[Selector]) -> list[list[int]]:
    """For each selector the ids that must not join it in a pattern."""
    by_attr: dict[str, list[int]] = {}
    for i, s in enumerate(selectors):
        by_attr.setdefault(s.label if s.op == "token" else s.attr, []).append(i)
    return [[j for j in by_attr[s.label if s.op == "token" else s.attr] if s.conflicts(selectors[j])] for s in selectors]


def parents(patterns: list[tuple[int, ...]], n_selectors: int) -> Column:
    """The places in `patterns` of those that a row's `sels` holds whole."""
    if patterns == [()]:
        return F.array(F.lit(0))
    if len(patterns) <= UNROLLED:
        return F.filter(F.array(*[F.when(_holds(p), F.lit(i)) for i, p in enumerate(patterns)]), lambda x: x.isNotNull())
    # the plan must not grow with the beam, nor a row's work: only patterns that begin with a selector of the row are tried
    by_first: list[list[int]] = [[] for _ in range(n_selectors)]
    for i, p in enumerate(patterns):
        by_first[p[0]].append(i)
    index, rest = constant(by_first, "array<array<int>>"), constant([list(p[1:]) for p in patterns], "array<array<int>>")
    tried = F.flatten(F.transform("sels", lambda s: F.element_at(index, s + 1)))
    return F.filter(tried, lambda i: F.forall(F.element_at(rest, i + 1), lambda s: F.array_contains("sels", s)))


def _holds(pattern: tuple[int, ...]) -> Column:
    out = F.lit(True)
    for i in pattern:
        out = out & F.array_contains("sels", i)
    return out


def denied(patterns: list[tuple[int, ...]], blocked: list[list[int]], ordered: bool) -> list[list[int]]:
    """For each pattern the selectors it must not take: those that conflict with it and, unless `ordered`, those that lead
    to a refinement which an earlier pattern of the list has already."""
    out = []
    for i, p in enumerate(patterns):
        own = {s for q in p for s in blocked[q]} | set(p)
        if not ordered:
            for q in patterns[:i]:
                new = set(q) - set(p)
                if len(new) == 1 and len(q) == len(p):
                    own |= new
        out.append(sorted(own))
    return out


def refinements(encoded: DataFrame, patterns: list[tuple[int, ...]], blocked: list[list[int]], ordered: bool = False) -> DataFrame:
    """The rows of `encoded`, once for each refinement of a pattern they hold, named by `code`: place of the pattern times
    the number of selectors, plus the selector (see pattern_of).

    A refinement that two patterns lead to is the earlier one's. `ordered` adds only selectors after the pattern's last,
    so that an enumeration meets each set once.
    """
    n = len(blocked)
    rows = encoded.withColumn("_i", F.explode(parents(patterns, n)))
    free = F.col("sels")
    if patterns != [()]:
        if ordered:
            last = F.element_at(constant([p[-1] if p else -1 for p in patterns], "array<int>"), F.col("_i") + 1)
            at = F.array_position("sels", last)
            free = F.slice("sels", (at + 1).cast("int"), F.greatest(F.size("sels") - at, F.lit(0)).cast("int"))
        not_now = constant(denied(patterns, blocked, ordered), "array<array<int>>")
        free = F.array_except(free, F.element_at(not_now, F.col("_i") + 1))
    return rows.withColumn("_s", F.explode(free)).withColumn("code", F.col("_i").cast("bigint") * n + F.col("_s")).drop("_i", "_s")


def pattern_of(patterns: list[tuple[int, ...]], n_selectors: int) -> Column:
    """The sorted array of selector ids that `code` names."""
    own = F.element_at(constant([list(p) for p in patterns], "array<array<int>>"), F.expr(f"cast(code div {n_selectors} as int)") + 1)
    return F.array_sort(F.concat(own, F.array((F.col("code") % n_selectors).cast("int"))))


def level_counts(cells: DataFrame, form: Form, patterns: list[tuple[int, ...]], blocked: list[list[int]], ordered: bool = False, spread: bool = True, bounded: bool = True) -> DataFrame:
    """Additive statistics of every refinement, from cells (see encode.cells): summed map-side in longs and doubles, one
    shuffle of groups. s2 and the inputs of estimates are summed only where asked for."""
    names = ["n", *form.columns, *(["s2"] if spread else []), *(BOUND_INPUTS if bounded else [])]
    sums = [F.sum(c).alias(c) for c in names] + ([F.max("tmax").alias("tmax")] if bounded else [])
    kept = cells.select("sels", *names, *(["tmax"] if bounded else []), "sig_x", "sig_s")
    out = refinements(kept, patterns, blocked, ordered).groupBy("code").agg(*sums, F.bit_xor("sig_x").alias("sig_x"), F.sum("sig_s").alias("sig_s"))
    return out.withColumn("s1", form.total()).withColumn("p", pattern_of(patterns, len(blocked))).drop("s1_low")


def named_level_counts(rows: DataFrame, form: Form, patterns: list[tuple[str, ...]], blocked: dict[str, list[str]], spread: bool = True, bounded: bool = True, free: Column | None = None, only: DataFrame | None = None) -> DataFrame:
    """As level_counts, from rows by name (see encode.named_rows). `free` are the names of a row that patterns may take, by
    default all; `only` holds those of the column `s`. The plan holds the patterns and what each of them is denied."""
    names = ["n", *form.columns, *(["s2"] if spread else []), *(BOUND_INPUTS if bounded else [])]
    sums = [F.sum(c).alias(c) for c in names] + ([F.max("tmax").alias("tmax")] if bounded else [])
    held = constant([list(p) for p in patterns], "array<array<string>>")
    if patterns == [()] or len(patterns) <= UNROLLED:
        at = parents(patterns, 0)
    else:
        at = F.filter(F.sequence(F.lit(0), F.lit(len(patterns) - 1)), lambda i: F.forall(F.element_at(held, i + 1), lambda s: F.array_contains("sels", s)))
    free = F.col("sels") if free is None else free
    added = rows.select(F.explode(at).alias("_i"), free.alias("_free"), *names, *(["tmax"] if bounded else []), "sig_x", "sig_s")
    not_now = constant(denied(patterns, blocked, False), "array<array<string>>")
    added = added.withColumn("s", F.explode(F.array_except("_free", F.element_at(not_now, F.col("_i") + 1))))
    if only is not None:
        added = added.join(only.select(F.col("s").alias("_s")), F.col("s") == F.col("_s"), "left_semi")
    out = added.groupBy("_i", "s").agg(*sums, F.bit_xor("sig_x").alias("sig_x"), F.sum("sig_s").alias("sig_s"))
    return out.withColumn("s1", form.total()).withColumn("p", F.array_sort(F.concat(F.element_at(held, F.col("_i") + 1), F.array("s")))).drop("_i", "s1_low")


def with_medians(cands: DataFrame, encoded: DataFrame, edges: list[float], small: DataFrame, patterns: list[tuple[int, ...]], blocked: list[list[int]], ordered: bool = False) -> DataFrame:
    """Add the exact interpolated median `med` of each candidate in `cands`.

    Counts by target bin say in which bins a candidate's middle rows lie; only rows of those bins are counted by value and
    ordered, so what is sorted for a candidate is a small share of its distinct values, and it may spill.
    """
    bins = _of(cands, refinements(small.select("sels", "bin", "n"), patterns, blocked, ordered)).groupBy("code", "bin").agg(F.sum("n").alias("n"))
    v = F.col("t").cast("double")
    rows = encoded.groupBy("sels", place(v, edges).alias("bin"), v.alias("v")).agg(F.count("*").alias("n"))
    med = medians_from(refinements(rows, patterns, blocked, ordered), middle_bins(bins, "code"), "code")
    return cands.join(med, F.col("code") == F.col("_k")).drop("_k")


def _of(cands: DataFrame, rows: DataFrame) -> DataFrame:
    """The rows of the candidates in `cands`."""
    return rows.join(cands.select(F.col("code").alias("_c")), F.col("code") == F.col("_c"), "left_semi")


def bin_edges(encoded: DataFrame, bins: int = BINS) -> list[float]:
    """Quantile edges of the target, for median brackets; approximate quantiles do, as the brackets stay true bounds."""
    return edges_of(encoded, "t", bins)


def binned(encoded: DataFrame, edges: list[float]) -> DataFrame:
    """(sels, bin, n, s, top): rows by selector set and target bin, a bin being the number of edges at or below the target."""
    t = F.col("t").cast("double")
    rows = encoded.select("sels", place(t, edges).alias("bin"), t.alias("v"))
    return rows.groupBy("sels", "bin").agg(F.count("*").alias("n"), F.sum("v").alias("s"), F.max("v").alias("top"))


def target_bins(cands: DataFrame, small: DataFrame, patterns: list[tuple[int, ...]], blocked: list[list[int]], ordered: bool) -> DataFrame:
    """(code, bin, n, s, top) of the candidates: at most a row for each candidate and bin."""
    rows = _of(cands, refinements(small, patterns, blocked, ordered))
    return rows.groupBy("code", "bin").agg(F.sum("n").alias("n"), F.sum("s").alias("s"), F.max("top").alias("top"))


def median_brackets(small: DataFrame, edges: list[float], patterns: list[tuple[int, ...]], blocked: list[list[int]], ordered: bool = False) -> DataFrame:
    """(code, n, med_lo, med_hi): bounds of each candidate's median from counts by target bin (see binned), summed map-side."""
    cuts = constant(edges, "array<double>")
    counted = refinements(small.select("sels", "bin", "n"), patterns, blocked, ordered).groupBy("code", "bin").agg(F.sum("n").alias("n"))
    run = Window.partitionBy("code").orderBy("bin").rowsBetween(Window.unboundedPreceding, 0)
    placed = counted.withColumn("upto", F.sum("n").over(run)).withColumn("all", F.sum("n").over(Window.partitionBy("code")))
    lower, upper = F.floor((F.col("all") + 1) / 2), F.floor(F.col("all") / 2) + 1
    lo = F.min(F.when(F.col("upto") >= lower, F.col("bin")))
    hi = F.min(F.when(F.col("upto") >= upper, F.col("bin")))
    at = placed.groupBy("code").agg(F.first("all").alias("n"), lo.alias("lo"), hi.alias("hi"))
    edge = lambda i: F.element_at(cuts, F.greatest(F.lit(1), F.least(i, F.lit(len(edges)))).cast("int"))
    return at.select("code", "n", edge(F.col("lo")).alias("med_lo"), edge(F.col("hi") + 1).alias("med_hi"))


def prefix_counts(ds: SubgroupDataset, attr: str, cuts: list, min_support: int = 1) -> DataFrame:
    """All `>= c` and `< c` selectors of one numeric attribute from one bin per row: counts by bin, then running sums."""
    edges = sorted(cuts)
    value = F.col(attr).cast("double")
    at = place(value, [float(c) for c in edges])
    rows = ds.rows().where(value.isNotNull() & ~F.isnan(value)).select(at.alias("bin"), summand(F.col("t"), ds.df.schema[ds.target].dataType).alias("t"))
    binned = rows.groupBy("bin").agg(F.count("*").alias("n"), F.sum("t").alias("s1"))
    frame = ds.df.sparkSession.range(1, len(edges) + 1).select(F.col("id").cast("int").alias("i"), F.element_at(F.lit([float(c) for c in edges]), F.col("id").cast("int")).alias("cut"))
    both = F.broadcast(frame).crossJoin(binned)  # cuts x bins, both bounded by the cut list
    side = both.select("cut", F.when(F.col("bin") >= F.col("i"), ">=").otherwise("<").alias("op"), "n", "s1").groupBy("cut", "op").agg(F.sum("n").alias("n"), F.sum("s1").alias("s1"))
    return side.where(F.col("n") >= min_support).select(F.lit(attr).alias("attr"), "op", "cut", "n", "s1")


def bitmap_store(encoded: DataFrame) -> DataFrame:
    """One bitmap for each selector and bucket of 32,768 numbered rows: the vertical layout for dense attributes."""
    numbered = encoded.withColumn("rid", F.monotonically_increasing_id())
    hot = numbered.select("rid", F.explode("sels").alias("sel"))
    return hot.groupBy("sel", F.bitmap_bucket_number("rid").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("rid")).alias("bits"))


def bitmap_sizes(store: DataFrame, patterns: DataFrame) -> DataFrame:
    """(pattern_id, size) of patterns (pattern_id, sel): a bucket counts only where all selectors of a pattern occur."""
    want = patterns.groupBy("pattern_id").agg(F.count("*").alias("k")).withColumnRenamed("pattern_id", "_id")
    met = store.join(F.broadcast(patterns), "sel").groupBy("pattern_id", "bucket").agg(F.bitmap_and_agg("bits").alias("bits"), F.count("*").alias("have"))
    whole = met.join(F.broadcast(want), (F.col("pattern_id") == F.col("_id")) & (F.col("have") == F.col("k")))
    return whole.groupBy("pattern_id").agg(F.sum(F.bitmap_count("bits")).alias("size"))
