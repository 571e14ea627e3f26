"""Reports on datasets and on found subgroups."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DataType

from slowlens.functions.exact import summand
from slowlens.functions.literals import constant
from slowlens.functions.quantiles import grouped_medians
from slowlens.operators.dataset import SubgroupDataset
from slowlens.operators.lattice import describe, to_column
from slowlens.operators.selectors import Selector

Pattern = tuple[Selector, ...]


def norms(ds: SubgroupDataset) -> DataFrame:
    """The norm that subgroups are compared with, as one row."""
    g = ds.norms()
    row = (g.n, g.mean if g.n else None, g.median, g.std if g.n else None)
    out = ds.df.sparkSession.createDataFrame([row], "n bigint, mean double, median double, std double")
    return out.select("n", *[F.round(c, 6).alias(c) for c in ("mean", "median", "std")])


def matches(ds: SubgroupDataset, patterns: list[Pattern]) -> DataFrame:
    """(oid, t, pid) for each pattern that covers a row, in one scan; pid is the place in the list."""
    flags = F.filter(F.array(*[F.when(to_column(p), F.lit(i)) for i, p in enumerate(patterns)]), lambda x: x.isNotNull())
    return ds.rows().withColumn("_m", flags).where(F.size("_m") > 0)


def describe_patterns(ds: SubgroupDataset, patterns: list[Pattern]) -> DataFrame:
    """Size, mean, median and deviation of the target in each pattern."""
    rows = matches(ds, patterns).select(F.explode("_m").alias("g"), "t")
    return _described(rows, [describe(p) for p in patterns], ds.df.schema[ds.target].dataType)


def describe_selectors(session) -> DataFrame:
    """The same for every single selector of a session, from its encoded rows."""
    rows = session.encoded.select(F.explode("sels").alias("g"), "t")
    return _described(rows, session.labels, session.encoded.schema["t"].dataType)


def _described(rows: DataFrame, names: list[str], kind: DataType) -> DataFrame:
    t = F.col("t")
    sums = rows.groupBy("g").agg(F.count("*").alias("size"), (F.sum(summand(t, kind)).cast("double") / F.count("*")).alias("mean"), F.stddev_pop(t.cast("double")).alias("std"))
    out = sums.join(grouped_medians(rows, "g", "t"), F.col("g") == F.col("_k"))
    return out.select(F.element_at(constant(names, "array<string>"), F.col("g") + 1).alias("description"), "size", *[F.round(c, 6).alias(a) for c, a in (("mean", "mean"), ("std", "std"), ("med", "median"))])


def dataset_stats(ds: SubgroupDataset) -> DataFrame:
    """Rows, features, share of zero cells: one pass over rows and one over their tokens."""
    rows = ds.rows()
    dense = [*ds.numeric, *ds.nominal, *ds.boolean, *ds.ordinal]
    filled = reduce(lambda a, b: a + b, [F.coalesce((F.col(c).cast("string") != "0") & F.col(c).isNotNull(), F.lit(False)).cast("long") for c in dense], F.lit(0))
    token_cells = F.size(ds.tokens) if ds.tokens else F.lit(0)
    base = rows.agg(F.count("*").alias("n_rows"), F.sum(filled + token_cells).alias("filled"))
    if ds.tokens:
        kinds = rows.select(F.explode(F.map_keys(ds.tokens)).alias("k")).agg(F.count_distinct("k").alias("n_tokens"))
        base = base.crossJoin(kinds)  # one row each
    else:
        base = base.withColumn("n_tokens", F.lit(0).cast("long"))
    features = F.col("n_tokens") + len(dense)
    return base.select("n_rows", features.alias("n_features"), "n_tokens", F.round(1 - F.col("filled") / (F.col("n_rows") * features), 6).alias("sparsity"))


def clause_stats(ds: SubgroupDataset) -> DataFrame:
    """Distinct tokens for each clause prefix."""
    return ds.rows().select(F.explode(F.map_keys(ds.tokens)).alias("k")).groupBy(F.substring_index("k", "_", 1).alias("clause")).agg(F.count_distinct("k").alias("tokens"))


def feature_catalog(ds: SubgroupDataset) -> DataFrame:
    rows = [(a, kind) for kind, names in (("numeric", ds.numeric), ("nominal", ds.nominal), ("boolean", ds.boolean), ("ordinal", ds.ordinal), ("tokens", [ds.tokens] if ds.tokens else [])) for a in names]
    return ds.df.sparkSession.createDataFrame(rows, "attribute string, kind string")


def density(ds: SubgroupDataset, pattern: Pattern, lo: float, hi: float, bins: int) -> DataFrame:
    """Share of rows by bin of the target, in the subgroup and in all rows."""
    b = F.greatest(F.lit(0), F.least(F.lit(bins + 1), F.width_bucket(F.col("t").cast("double"), F.lit(float(lo)), F.lit(float(hi)), F.lit(bins).cast("long"))))
    inside = to_column(pattern).cast("long")
    counts = ds.rows().groupBy(b.cast("int").alias("bin")).agg(F.count("*").alias("n"), F.sum(inside).alias("m"))
    total = counts.agg(F.sum("n").alias("all_n"), F.sum("m").alias("all_m"))
    return counts.join(F.broadcast(total)).select("bin", F.round(F.col("n") / F.col("all_n"), 6).alias("overall"), F.round(F.col("m") / F.col("all_m"), 6).alias("subgroup"))


def token_usage(ds: SubgroupDataset, pattern: Pattern, prefix: str) -> DataFrame:
    """How often each token of a prefix occurs in the rows of a subgroup."""
    rows = ds.rows().where(to_column(pattern)).select(F.explode(F.map_keys(ds.tokens)).alias("token")).where(F.col("token").startswith(prefix))
    return rows.groupBy("token").agg(F.count("*").alias("rows"))


def containment(ds: SubgroupDataset, patterns: list[Pattern]) -> DataFrame:
    """Pairs (inner, outer) where every row of one is a row of the other."""
    names = F.lit([describe(p) for p in patterns])
    m = matches(ds, patterns).select("_m")
    sizes = m.select(F.explode("_m").alias("p")).groupBy("p").agg(F.count("*").alias("n"))
    pairs = m.select(F.explode("_m").alias("p"), "_m").select("p", F.explode("_m").alias("q")).where("p <> q").groupBy("p", "q").agg(F.count("*").alias("both"))
    out = pairs.join(F.broadcast(sizes), "p").where("both = n")
    at = lambda c: F.element_at(names, F.col(c) + 1)
    return out.select(at("p").alias("inside"), at("q").alias("outside"), F.col("n").alias("size"))


def contributions(ds: SubgroupDataset, pattern: Pattern, n: int, mean: float) -> DataFrame:
    """WRAcc of a pattern, and of it without each of its selectors, in one pass."""
    variants = [("all", pattern)] + [(f"without {s.label}", tuple(x for x in pattern if x != s)) for s in sorted(pattern, key=lambda s: s.label)]
    t = summand(F.col("t"), ds.df.schema[ds.target].dataType)

    def wracc(p: Pattern) -> Column:
        c = to_column(p)
        size = F.sum(c.cast("long"))
        return F.round(size / n * (F.sum(F.when(c, t)).cast("double") / size - mean), 6)

    row = ds.rows().agg(F.array(*[F.struct(F.lit(name).alias("selectors"), wracc(p).alias("wracc")) for name, p in variants]).alias("v"))
    return row.select(F.inline("v"))


def ks_distance(ds: SubgroupDataset, pattern: Pattern) -> DataFrame:
    """Largest gap between the distribution functions of the target in the subgroup and in all rows."""
    from pyspark.sql import Window

    counts = ds.rows().groupBy(F.col("t").cast("double").alias("v")).agg(F.count("*").alias("n"), F.sum(to_column(pattern).cast("long")).alias("m"))
    # one row for each distinct value: dealt by range, summed within ranges, shifted by the ranges before
    parts = counts.repartitionByRange("v").withColumn("_p", F.spark_partition_id())
    sums = parts.groupBy("_p").agg(F.sum("n").alias("pn"), F.sum("m").alias("pm"))
    order = Window.orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)
    before = sums.select("_p", *[F.coalesce(F.sum(f"p{c}").over(order), F.lit(0)).alias(f"b{c}") for c in "nm"])
    total = counts.agg(F.sum("n").alias("an"), F.sum("m").alias("am"))
    run = Window.partitionBy("_p").orderBy("v").rowsBetween(Window.unboundedPreceding, 0)
    cdf = parts.withColumn("cn", F.sum("n").over(run)).withColumn("cm", F.sum("m").over(run)).join(F.broadcast(before), "_p").join(F.broadcast(total))
    gap = F.abs((F.col("cn") + F.col("bn")) / F.col("an") - (F.col("cm") + F.col("bm")) / F.col("am"))
    return cdf.agg(F.round(F.max(gap), 6).alias("ks"))
