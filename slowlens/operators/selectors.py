"""Selectors: restrictions of one attribute, built from the data in one pass per kind."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

from slowlens.functions.quantiles import quantiles
from slowlens.operators.dataset import SubgroupDataset


def _text(v: object) -> str:
    return f"{v:g}" if isinstance(v, float) else str(v)


@dataclass(frozen=True)
class Selector:
    """`op` is one of = >= > < <= in level>= token; `key` is what two selectors of a pattern must not share."""

    attr: str
    op: str
    value: object
    tokens: str | None = None
    levels: tuple[str, ...] = ()

    @property
    def label(self) -> str:
        if self.op == "token":
            return f"{self.value}>0" if self.levels == () else f"{self.value}>={self.levels[0]}"
        if self.op == "in":
            low, high, low_open, high_open = self.value
            return f"{self.attr} in {'(' if low_open else '['}{_text(low)},{_text(high)}{')' if high_open else ']'}"
        return f"{self.attr}{self.op.replace('level', '')}{_text(self.value)}"

    @property
    def side(self) -> str:
        return {">=": "low", ">": "low", "<": "high", "<=": "high", "level>=": "low"}.get(self.op, "point")

    def conflicts(self, other: Selector) -> bool:
        """A second value of one attribute selects nothing, a second bound on one side is redundant."""
        if self.op == "token" or other.op == "token":
            return self.label == other.label
        return self.attr == other.attr and (self.side == other.side or "point" in (self.side, other.side))

    def column(self) -> Column:
        """A native predicate; null and NaN values satisfy none."""
        c = F.col(self.attr) if self.op != "token" else None
        if self.op == "token":
            least = int(self.levels[0]) if self.levels else 1
            return F.coalesce(F.try_element_at(F.col(self.tokens), F.lit(self.value)), F.lit(0)) >= least
        if self.op == "level>=":
            return F.coalesce(F.array_position(F.lit(list(self.levels)), c) >= self.levels.index(self.value) + 1, F.lit(False))
        if self.op == "in":
            low, high, low_open, high_open = self.value
            p = (c > low if low_open else c >= low) & (c < high if high_open else c <= high)
        else:
            p = {"=": c == F.lit(self.value), ">=": c >= F.lit(self.value), ">": c > F.lit(self.value), "<": c < F.lit(self.value), "<=": c <= F.lit(self.value)}[self.op]
            if self.op in (">=", ">") and isinstance(self.value, float):
                p = p & ~F.isnan(c.cast("double"))
        return F.coalesce(p, F.lit(False))


def numeric(attr: str, cuts: list, shape: str = "both", low_op: str = ">=", high_op: str = "<") -> list[Selector]:
    """`shape`: lower, upper or both one-sided bounds at each cut, or the intervals between neighbouring cuts."""
    if shape == "interval":
        return [Selector(attr, "in", (a, b, False, True)) for a, b in zip(cuts, cuts[1:], strict=False)]
    lower = [Selector(attr, low_op, c) for c in cuts] if shape in ("lower", "both") else []
    upper = [Selector(attr, high_op, c) for c in cuts] if shape in ("upper", "both") else []
    return lower + upper


def equals(attr: str, values: list) -> list[Selector]:
    return [Selector(attr, "=", v) for v in values]


def boolean(attr: str) -> list[Selector]:
    return equals(attr, [0, 1])


def ordinal(attr: str, levels: tuple[str, ...], up: bool = False) -> list[Selector]:
    """Each level, or each level and above (but the lowest, which is no restriction)."""
    return [Selector(attr, "level>=", v, levels=levels) for v in levels[1:]] if up else equals(attr, list(levels))


def cuts(ds: SubgroupDataset, attrs: list[str], policy: str = "quantile", bins: int = 5, values: dict[str, list] | None = None, most: int = 10_000) -> dict[str, list[float]]:
    """Cut points of all attributes: quantile, width, distinct (refused beyond `most` values), positive or explicit."""
    if policy == "positive":
        return {a: [0.0] for a in attrs}
    if policy == "explicit":
        return {a: list((values or {})[a]) for a in attrs}
    rows = ds.rows()
    if policy == "quantile":
        at = [i / bins for i in range(1, bins)]
        return {a: sorted(set(quantiles(rows, a, at))) for a in attrs}
    if policy == "width":
        row = rows.agg(*[F.struct(F.min(F.col(a).cast("double")).alias("lo"), F.max(F.col(a).cast("double")).alias("hi")).alias(a) for a in attrs]).first()
        return {a: sorted({row[a]["lo"] + (row[a]["hi"] - row[a]["lo"]) * i / bins for i in range(1, bins)}) if row[a]["lo"] is not None else [] for a in attrs}
    if policy == "distinct":
        found = {a: [r[0] for r in rows.select(F.col(a).cast("double").alias("v")).where("v is not null").distinct().limit(most + 1).collect()] for a in attrs}
        wide = [a for a in attrs if len(found[a]) > most]
        if wide:
            raise ValueError(f"over {most} distinct values of {wide}; cut them by quantiles")
        return {a: sorted(found[a]) for a in attrs}
    raise ValueError(f"no policy {policy}")


def nominal(ds: SubgroupDataset, attrs: list[str], min_support: int = 1, max_values: int = 10_000) -> list[Selector]:
    """The categories of all attributes in one pass, without those under min_support; most frequent first.

    More than max_values an attribute on average are refused, as they must fit the driver: raise min_support then.
    """
    if not attrs:
        return []
    pairs = F.explode(F.array(*[F.struct(F.lit(a).alias("attr"), F.col(a).cast("string").alias("v")) for a in attrs]))
    found = ds.rows().select(pairs.alias("p")).where("p.v is not null").groupBy("p.attr", "p.v").count().where(F.col("count") >= min_support)
    rows = found.limit(max_values * len(attrs) + 1).collect()
    if len(rows) > max_values * len(attrs):
        raise ValueError(f"over {max_values} categories an attribute; raise min_support")
    rows.sort(key=lambda r: (r["attr"], -r["count"], r["v"]))
    return [Selector(r["attr"], "=", r["v"]) for r in rows]


def tokens(ds: SubgroupDataset, min_support: int, counts: tuple[int, ...] = (1,)) -> list[Selector]:
    """Tokens that min_support rows or more hold at least c times; only these reach the driver."""
    entry = ds.rows().select(F.explode(F.map_entries(ds.tokens)).alias("e"))
    least = F.explode(F.filter(F.lit(list(counts)), lambda c: c <= F.col("e.value")))
    rows = entry.select(F.col("e.key").alias("token"), least.alias("c")).groupBy("token", "c").count().where(F.col("count") >= min_support).orderBy("token", "c").collect()
    return [Selector(r["token"], "token", r["token"], ds.tokens, () if r["c"] == 1 else (str(r["c"]),)) for r in rows]


def build(ds: SubgroupDataset, policy: str = "quantile", bins: int = 5, values: dict[str, list] | None = None, min_support: int = 1, up: bool = False) -> list[Selector]:
    """Selectors for every attribute of the dataset."""
    out = [s for a, c in (cuts(ds, list(ds.numeric), policy, bins, values) if ds.numeric else {}).items() for s in numeric(a, c)]
    out += nominal(ds, list(ds.nominal), min_support)
    out += [s for a in ds.boolean for s in boolean(a)]
    out += [s for a, levels in ds.ordinal.items() for s in ordinal(a, levels, up)]
    return out + (tokens(ds, min_support) if ds.tokens else [])
