"""Interestingness measures as Columns over the statistics of a candidate subgroup.

A measure turns the statistics n, s1 (sum of the target), s2 (sum of its squared distances from the mean of all rows), med (median) into a score, given the
norms of the whole dataset. Scores are rounded to 9 decimals so that ties are ties in every engine.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

from slowlens.functions.exact import Form

DIGITS = 9


@dataclass(frozen=True)
class Norms:
    """Statistics of the whole dataset, taken to the driver once and used as literals."""

    n: int
    mean: float
    median: float | None
    std: float
    positives: int | None = None
    form: Form = Form()  # how targets are summed

    @property
    def rate(self) -> float:
        return self.mean


@dataclass(frozen=True)
class Measure:
    """`needs`: moments or median. `a`: exponent of the size factor, None where there is none. `score` builds the Column."""

    name: str
    needs: str
    score: Callable[[Norms], Column]
    a: float | None = None
    binary_only: bool = False
    bound: str = "none"  # family of its optimistic estimate, see functions.bounds
    spread: bool = False  # whether it reads s2


def _n() -> Column:
    return F.col("n").cast("double")


def _mean() -> Column:
    return F.col("s1").cast("double") / _n()


def _std(g: Norms) -> Column:
    """Population deviation."""
    off = _mean() - g.mean
    return F.sqrt(F.greatest(F.col("s2").cast("double") / _n() - off * off, F.lit(0.0)))


def klosgen(a: float) -> Measure:
    """Size to the power a times the deviation of the mean."""
    if not 0 <= a <= 1:
        raise ValueError("the exponent must lie between 0 and 1")
    return Measure(f"klosgen_{a:g}", "moments", lambda g: F.pow(_n() / g.n, F.lit(float(a))) * (_mean() - g.mean), a, bound="family")


def median_score(a: float) -> Measure:
    if not 0 <= a <= 1:
        raise ValueError("the exponent must lie between 0 and 1")
    return Measure(f"median_{a:g}", "median", lambda g: F.pow(_n() / g.n, F.lit(float(a))) * (F.col("med") - g.median), a, bound="median")


def tscore(ddof: int = 0, sigma_floor: float | None = None) -> Measure:
    """Deviation of the mean in units of its spread; null without spread or under two rows."""

    def score(g: Norms) -> Column:
        sd = _std(g) * (F.sqrt(_n() / (_n() - ddof)) if ddof else F.lit(1.0))
        sd = F.greatest(sd, F.lit(sigma_floor)) if sigma_floor else sd
        return F.when((_n() >= 2) & (sd > 1e-9), F.sqrt(_n() / g.n) / sd * (_mean() - g.mean))

    return Measure("tscore", "moments", score, 0.5, bound="tscore" if sigma_floor else "none", spread=True)


def _binomial(g: Norms) -> Column:
    spread = (g.mean * (1 - g.mean)) ** 0.5
    return F.sqrt(_n()) * (_mean() - g.mean) / F.lit(spread) if spread else F.lit(None).cast("double")


def _low(m: Measure) -> Measure:
    return Measure(f"low_{m.name}", m.needs, lambda g: -m.score(g), m.a, m.binary_only, spread=m.spread)


_REGISTRY: dict[str, Measure] = {
    "support": Measure("support", "moments", lambda g: _n() / g.n),
    "average": Measure("average", "moments", lambda g: _mean() - g.mean, 0.0, bound="family"),
    "lift": Measure("lift", "moments", lambda g: _mean() / F.lit(g.mean) if g.mean else F.lit(None).cast("double"), 0.0, bound="lift"),
    "wracc": Measure("wracc", "moments", lambda g: _n() / g.n * (_mean() - g.mean), 1.0, bound="family"),
    "wracc_binary": Measure("wracc_binary", "moments", lambda g: F.col("s1").cast("double") / g.n - _n() / g.n * g.mean, 1.0, True, bound="family"),
    "wracc_abs": Measure("wracc_abs", "moments", lambda g: F.abs(_n() / g.n * (_mean() - g.mean)), 1.0, bound="two_sided"),
    "mean_test": Measure("mean_test", "moments", lambda g: F.sqrt(_n() / g.n) * (_mean() - g.mean), 0.5, bound="family"),
    "binomial": Measure("binomial", "moments", _binomial, 0.5, True, bound="binomial"),
    "tscore": tscore(),
    "precision": Measure("precision", "moments", lambda g: _mean(), 0.0, True),
    "median": median_score(0.5),
    "median_ratio": Measure("median_ratio", "median", lambda g: F.col("med") / F.lit(g.median) if g.median else F.lit(None).cast("double"), 0.0),
}


def register(name: str, needs: str, score: Callable[[Norms], Column], bound: str = "none", a: float | None = None) -> Measure:
    """Add a measure of the user's own."""
    if needs not in ("moments", "median"):
        raise ValueError("needs is moments or median")
    _REGISTRY[name] = m = Measure(name, needs, score, a, bound=bound, spread=True)
    return m


def get(name: str | Measure) -> Measure:
    """By name; `klosgen_<a>` and `median_<a>` take any exponent, `low_<name>` turns the direction."""
    if isinstance(name, Measure):
        return name
    if name in _REGISTRY:
        return _REGISTRY[name]
    if name.startswith("low_"):
        return _low(get(name[4:]))
    for prefix, make in (("klosgen_", klosgen), ("median_", median_score)):
        if name.startswith(prefix):
            return make(float(name[len(prefix) :]))
    raise KeyError(f"no measure {name}")


def scored(measure: str | Measure, norms: Norms) -> Column:
    return F.round(get(measure).score(norms), DIGITS)
