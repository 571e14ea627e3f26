"""The interactive loop without its screen: slice the data, paint a target, mine, look, refine."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from slowlens.operators import selectors as sel
from slowlens.operators import stats, targets
from slowlens.operators.dataset import SubgroupDataset
from slowlens.operators.selectors import Selector
from slowlens.plans import search


@dataclass(frozen=True)
class Exploration:
    """A working set and a target. Every action gives a new exploration: only the root of the plan changes, and the
    selectors of the whole data stay in use unless recut() asks for new ones."""

    ds: SubgroupDataset
    selectors: list[Selector] = field(default_factory=list)
    found: search.Found | None = None

    def where(self, condition: Column | str) -> Exploration:
        return replace(self, ds=self.ds.where(condition), found=None)

    def brush(self, x: str, y: str, x_range: tuple[float, float], y_range: tuple[float, float]) -> Exploration:
        """The rows in a rectangle of the plot become the working set."""
        return self.where(F.col(x).between(*x_range) & F.col(y).between(*y_range))

    def paint_target(self, x: str, y: str, x_range: tuple[float, float], y_range: tuple[float, float]) -> Exploration:
        """The rows in a rectangle of the working set are positive, its other rows negative."""
        right = F.col(x).between(*x_range) & F.col(y).between(*y_range)
        return replace(self, ds=self.ds.with_target(targets.painted(F.lit(True), right)), found=None)

    def target(self, column: Column | str) -> Exploration:
        return replace(self, ds=self.ds.with_target(F.col(column) if isinstance(column, str) else column), found=None)

    def recut(self, **options) -> Exploration:
        return replace(self, selectors=sel.build(self.ds, **options))

    def mine(self, measure: str = "wracc", algorithm: str = "beam", k: int = 10, depth: int = 2, **options) -> Exploration:
        session = search.Session(self.ds, self.selectors, search.get(measure).needs == "median")
        try:
            return replace(self, found=getattr(search, algorithm)(session, measure=measure, k=k, depth=depth, **options))
        finally:
            session.close()

    def drill(self, pattern: tuple[Selector, ...], measure: str = "wracc", k: int = 10, depth: int = 1, **options) -> Exploration:
        """Refinements of a found pattern only."""
        session = search.Session(self.ds, self.selectors, search.get(measure).needs == "median")
        try:
            seed = tuple(sorted(self.selectors.index(s) for s in pattern))
            return replace(self, found=search.beam(session, measure, k, depth, seed=seed, **options))
        finally:
            session.close()

    def results(self) -> DataFrame:
        return self._mined().frame(self.ds.df.sparkSession)

    def report(self) -> DataFrame:
        """Size, mean, median and deviation of each found pattern."""
        return stats.describe_patterns(self.ds, self._mined().patterns())

    def points(self, x: str, y: str, x_range: tuple[float, float], y_range: tuple[float, float], bins: int = 20) -> DataFrame:
        """The scatter plot as counts on a grid, whatever the number of rows."""
        cell = lambda c, r: F.width_bucket(F.col(c).cast("double"), F.lit(float(r[0])), F.lit(float(r[1])), F.lit(bins).cast("long")).cast("int")
        return self.ds.df.groupBy(cell(x, x_range).alias("x_bin"), cell(y, y_range).alias("y_bin")).agg(F.count("*").alias("rows"))

    def _mined(self) -> search.Found:
        if self.found is None:
            raise ValueError("mine() first")
        return self.found
