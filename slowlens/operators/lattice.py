"""Patterns as sorted sets of selectors, their refinements, order and number."""

from __future__ import annotations

from functools import reduce
from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from slowlens.operators.dataset import SubgroupDataset
from slowlens.operators.selectors import Selector


def describe(pattern: tuple[Selector, ...]) -> str:
    return " & ".join(sorted(s.label for s in pattern))


def to_column(pattern: tuple[Selector, ...]) -> Column:
    """The conjunction as one native predicate; the empty pattern restricts nothing."""
    return reduce(lambda a, b: a & b, (s.column() for s in pattern), F.lit(True))


def extent(ds: SubgroupDataset, pattern: tuple[Selector, ...]) -> DataFrame:
    return ds.rows().where(to_column(pattern)).select("oid")


def refine(patterns: list[tuple[Selector, ...]], selectors: list[Selector]) -> list[tuple[Selector, ...]]:
    """Every pattern with one more selector, each once."""
    out = {}
    for p in patterns:
        for s in selectors:
            if not any(s.conflicts(x) for x in p):
                new = tuple(sorted((*p, s), key=lambda x: x.label))
                out.setdefault(describe(new), new)
    return list(out.values())


def is_refinement(p: tuple[Selector, ...], q: tuple[Selector, ...]) -> bool:
    """Whether p has every selector of q."""
    return {s.label for s in q} <= {s.label for s in p}


def generalisations(pattern: tuple[Selector, ...]) -> list[tuple[Selector, ...]]:
    return [c for k in range(len(pattern)) for c in combinations(pattern, k)]


def space_size(selectors: list[Selector], depth: int) -> int:
    """Patterns of at most `depth` selectors, the unrestricted one included: a product over attributes."""
    groups: dict[str, list[Selector]] = {}
    for s in selectors:
        groups.setdefault(s.label if s.op == "token" else s.attr, []).append(s)
    ways = [1] + [0] * depth
    for group in groups.values():
        own = [1, len(group), sum(not a.conflicts(b) for a, b in combinations(group, 2))]
        ways = [sum(own[j] * ways[d - j] for j in range(min(2, d) + 1)) for d in range(depth + 1)]
    return sum(ways)


def signature_of_row(oid: str = "oid") -> dict[str, Column]:
    return {"sig_x": F.xxhash64(oid), "sig_s": F.shiftrightunsigned(F.xxhash64(F.lit(7), oid), 40)}


def signature_columns(oid: str = "oid") -> list[Column]:
    """Two aggregates that, with the count, tell extents apart; they add up over partial groups.

    The second is a sum of 24 bits a row, which tells rows that share an oid from rows that cancel out.
    """
    own = signature_of_row(oid)
    return [F.bit_xor(own["sig_x"]).alias("sig_x"), F.sum(own["sig_s"]).alias("sig_s")]


def distinct_extents(cands: DataFrame) -> DataFrame:
    """One pattern for each extent: fewest selectors, then the first description."""
    first = F.min_by(F.struct(*cands.columns), F.struct("n_sel", "description"))
    return cands.groupBy("n", "sig_x", "sig_s").agg(first.alias("_r")).select("_r.*")
