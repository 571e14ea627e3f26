"""Sums of a target that don't depend on the order of rows and don't round it beforehand.

A target becomes a whole number, its value times a power of ten: whole numbers and decimals keep all their digits,
floating targets the 15 that a double has. Where n such numbers may not fit a long, each is split into a high and a low
part whose sums do. Only targets of more than 18 digits before the point are summed as doubles.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql.types import DataType, DecimalType, FractionalType


def is_floating(kind: DataType) -> bool:
    return isinstance(kind, FractionalType) and not isinstance(kind, DecimalType)


def summand(t: Column, kind: DataType) -> Column:
    """The target as it may be summed without a look at its range: exact unless it is floating."""
    if is_floating(kind):
        return t.cast("double")
    return t if isinstance(kind, DecimalType) else t.cast("decimal(38,0)")


@dataclass(frozen=True)
class Form:
    """How the targets of a dataset are summed: `whole` and `scale` digits, `low` bits in the low part (0: no split)."""

    whole: int = 0
    scale: int = 0
    low: int = 0

    @classmethod
    def of(cls, kind: DataType, largest: float | None, n: int) -> Form:
        """For n targets of that type and of at most `largest`."""
        if largest is not None and not math.isfinite(largest):
            return cls()
        whole = max(1, math.floor(math.log10(largest)) + 1) if largest else 1
        bits = max(1, n).bit_length()
        room = min(18, math.floor((124 - 2 * bits) * math.log10(2)))  # digits that two parts can hold n times
        if whole > room:
            return cls()
        own = kind.scale if isinstance(kind, DecimalType) else 15 - whole if is_floating(kind) else 0
        scale = max(0, min(own, room - whole))
        fits = (whole + scale) * math.log2(10) + bits < 62
        return cls(whole, scale, 0 if fits else 62 - bits)

    def parts(self, t: Column) -> dict[str, Column]:
        """The summands of s1."""
        if not self.whole:
            return {"s1": t.cast("double")}
        digits = f"decimal({self.whole + self.scale},{self.scale})"
        x = (t.cast(digits) * F.lit(10**self.scale).cast("decimal(19,0)")).cast("bigint")
        return {"s1": F.shiftright(x, self.low), "s1_low": x.bitwiseAND((1 << self.low) - 1)} if self.low else {"s1": x}

    @property
    def columns(self) -> tuple[str, ...]:
        return ("s1", "s1_low") if self.low else ("s1",)

    def total(self) -> Column:
        """The sum as a double, from the sums of its parts."""
        s = F.col("s1").cast("double")
        if self.low:
            s = s * float(1 << self.low) + F.col("s1_low").cast("double")
        return s / float(10**self.scale) if self.scale else s
