"""A dataset for subgroup discovery: objects, a target, and descriptive attributes by kind."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from slowlens.functions import exact
from slowlens.functions.measures import Norms
from slowlens.functions.quantiles import median


@dataclass(frozen=True)
class SubgroupDataset:
    """`df` has the columns `oid` (any type), `t` (the target) and the attributes; `tokens` names a map column of counts.

    The target is never descriptive; a null attribute satisfies no selector; rows with a null target are an error or are
    dropped, as `on_null_target` says.
    """

    df: DataFrame
    oid: str = "oid"
    target: str = "t"
    numeric: tuple[str, ...] = ()
    nominal: tuple[str, ...] = ()
    boolean: tuple[str, ...] = ()
    ordinal: dict[str, tuple[str, ...]] = field(default_factory=dict)
    tokens: str | None = None
    on_null_target: str = "drop"

    def __post_init__(self) -> None:
        names = [*self.numeric, *self.nominal, *self.boolean, *self.ordinal, *([self.tokens] if self.tokens else [])]
        if self.target in names:
            raise ValueError("the target must not be a descriptive attribute")
        missing = [c for c in [self.oid, self.target, *names] if c not in self.df.columns]
        if missing:
            raise ValueError(f"no columns {missing}")
        if self.on_null_target not in ("drop", "error"):
            raise ValueError("on_null_target is drop or error")

    @property
    def attributes(self) -> list[str]:
        return [*self.numeric, *self.nominal, *self.boolean, *self.ordinal, *([self.tokens] if self.tokens else [])]

    def rows(self) -> DataFrame:
        """The needed columns of the rows with a target."""
        t = F.col(self.target)
        out = self.df.select(F.col(self.oid).alias("oid"), t.alias("t"), *self.attributes)
        if self.on_null_target == "error":
            return out.withColumn("t", F.when(F.col("t").isNull(), F.raise_error(F.lit("the target is null"))).otherwise(F.col("t")))
        return out.where(F.col("t").isNotNull())

    def persisted(self) -> SubgroupDataset:
        """The same over kept rows; the caller ends that by `df.unpersist()`."""
        return replace(self, df=self.rows().persist(), oid="oid", target="t")

    def where(self, condition: Column | str) -> SubgroupDataset:
        return replace(self, df=self.df.where(condition))

    def with_target(self, target: Column) -> SubgroupDataset:
        return replace(self, df=self.df.withColumn(self.target, target))

    def norms(self, with_median: bool = True) -> Norms:
        """One pass over the target, two more for its median."""
        rows = self.rows().select("t")
        kind, t = rows.schema["t"].dataType, F.col("t")
        stats = [F.count("*").alias("n"), F.sum(exact.summand(t, kind)).alias("s1"), F.stddev_pop(t.cast("double")).alias("sd"), F.sum((t.cast("double") > 0).cast("long")).alias("pos"), F.max(F.abs(t.cast("double"))).alias("most")]
        row = rows.agg(*stats).first()
        n = row["n"]
        middle = median(rows, "t", n) if with_median else None
        return Norms(n, float(row["s1"]) / n if n else 0.0, middle, row["sd"] or 0.0, row["pos"], exact.Form.of(kind, row["most"], n))
