"""Beam search, exhaustive search with pruning, and naive enumeration of subgroups."""

from __future__ import annotations

import time
from collections import defaultdict
from dataclasses import dataclass, field
from decimal import ROUND_HALF_UP, Decimal

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from slowlens.functions import bounds
from slowlens.functions.literals import constant
from slowlens.functions.quantiles import quantiles
from slowlens.functions.measures import Measure, Norms, get, scored
from slowlens.operators import counting, lattice
from slowlens.operators.dataset import SubgroupDataset
from slowlens.operators.encode import cells, encode, encode_by_index, named_rows, token_map_is_large
from slowlens.operators.selectors import Selector

RESULT = "rank int, description string, n_sel int, size bigint, mean double, score double"
KEPT = ("p", "n", "s1", "sig_x", "sig_s", "med", "score")


@dataclass
class Found:
    """Patterns with statistics, as rows on the driver (at most width x depth, or k with ties), and what the search did."""

    rows: list[dict]
    trace: list[dict] = field(default_factory=list)
    complete: bool = True
    selectors: list[Selector] = field(default_factory=list)
    norms: Norms | None = None

    def patterns(self) -> list[tuple[Selector, ...]]:
        return [tuple(self.selectors[i] for i in r["p"]) for r in self.rows]

    def frame(self, spark) -> DataFrame:
        if not self.complete:
            raise TimeoutError("the time limit ended the search; `rows` holds the best so far, raise time_limit_s for the answer")
        data = [(r["rank"], r["description"], len(r["p"]), r["n"], _round(r["s1"] / r["n"]), r["score"]) for r in self.rows]
        return spark.createDataFrame(data, RESULT)


def _round(x: float | None, digits: int = 6) -> float | None:
    """Half away from zero on the decimal form, as the SQL engines round."""
    return None if x is None else float(Decimal(repr(float(x))).quantize(Decimal(1).scaleb(-digits), ROUND_HALF_UP))


def _key(r: dict) -> tuple:
    return (-r["score"], len(r["p"]), r["description"])


def distinct(rows: list[dict]) -> list[dict]:
    """One row for each extent: fewest selectors, then the first description."""
    best: dict[tuple, dict] = {}
    for r in sorted(rows, key=lambda r: (len(r["p"]), r["description"])):
        best.setdefault((r["n"], r["sig_x"], r["sig_s"]), r)
    return list(best.values())


def top(rows: list[dict], k: int, ties: bool) -> list[dict]:
    """The best k by score; with ties all that have fewer than k strictly better ones."""
    ordered = sorted(rows, key=_key)
    out, rank = [], 0
    for i, r in enumerate(ordered):
        rank = rank if i and ordered[i - 1]["score"] == r["score"] else i + 1
        if (rank if ties else i + 1) > k:
            break
        out.append({**r, "rank": rank if ties else i + 1})
    return out


class Session:
    """The encoded data of one dataset, shared by searches: selectors, norms, cells, and rows where medians ask for them."""

    def __init__(self, ds: SubgroupDataset, selectors: list[Selector], median: bool = True):
        self.ds, self.selectors = ds, selectors
        self.norms = ds.norms(median)
        self.blocked = counting.blocked_pairs(selectors)
        self.labels = [s.label for s in selectors]
        code = encode_by_index if token_map_is_large(selectors) else encode
        self.encoded = code(ds, selectors)
        if median:  # read by every median; moments come from cells alone
            self.encoded = self.encoded.persist()
        self.cells = cells(self.encoded, self.norms).persist()
        self.edges: list[float] = []
        self.binned: DataFrame | None = None
        self.level: DataFrame | None = None

    def __enter__(self) -> Session:
        return self

    def __exit__(self, *_) -> None:
        self.close()

    def end_level(self) -> None:
        if self.level is not None:
            self.level.unpersist()
            self.level = None

    def close(self) -> None:
        self.end_level()
        if self.binned is not None:
            self.binned.unpersist()
        self.cells.unpersist()
        self.encoded.unpersist()

    def describe(self, p) -> str:
        return " & ".join(sorted(self.labels[i] for i in p))

    def default_floor(self) -> int:
        return max(5, -(-self.norms.n // 1000))

    def bins(self) -> tuple[list[float], DataFrame]:
        """Edges of target bins, and the rows counted by selector set and bin."""
        if self.binned is None:
            self.edges = counting.bin_edges(self.encoded)
            self.binned = counting.binned(self.encoded, self.edges).persist()
        return self.edges, self.binned

    def candidates(self, patterns: list[tuple[int, ...]], measure: Measure, floor: int, ordered: bool, keep: int | None = None, bounded: bool = False) -> DataFrame:
        """Refinements with `floor` rows or more, their statistics, description and score.

        For a median measure with `keep`, brackets from bin counts first rule out candidates that cannot be among the
        best `keep`; exact medians are taken of the rest only.
        """
        names = F.array_join(F.array_sort(F.transform("p", lambda i: F.element_at(constant(self.labels, "array<string>"), i + 1))), " & ")
        cands = counting.level_counts(self.cells, self.norms.form, patterns, self.blocked, ordered, measure.spread, bounded).where(F.col("n") >= floor)
        cands = cands.withColumn("description", names).withColumn("n_sel", F.size("p"))
        if measure.needs == "median":
            if keep is not None:
                self.level = lattice.distinct_extents(cands).persist()  # candidates of one level, read three times
                cands = self.within_reach(self.level, patterns, measure, ordered, keep)
            edges, small = self.bins()
            cands = counting.with_medians(cands, self.encoded, edges, small, patterns, self.blocked, ordered)
        else:
            cands = cands.withColumn("med", F.lit(None).cast("double"))
        return cands.withColumn("score", scored(measure, self.norms))

    def within_reach(self, cands: DataFrame, patterns: list[tuple[int, ...]], measure: Measure, ordered: bool, keep: int) -> DataFrame:
        """Candidates of distinct extents whose median bracket allows them among the best `keep`."""
        edges, small = self.bins()
        b = counting.median_brackets(small, edges, patterns, self.blocked, ordered)
        b = b.join(cands.select(F.col("code").alias("_c")), F.col("code") == F.col("_c"), "left_semi")
        s = scored(measure, self.norms)
        worst = b.withColumn("med", F.col("med_lo")).select(s.alias("s")).orderBy(F.desc("s")).limit(keep).agg(F.min("s"), F.count("*")).first()
        if worst[1] < keep:
            return cands  # all may be among the best
        hold = b.withColumn("med", F.col("med_hi")).where(s >= worst[0]).select(F.col("code").alias("_c"))
        return cands.join(hold, F.col("code") == F.col("_c"), "left_semi")

    def with_tight(self, cands: DataFrame, patterns: list[tuple[int, ...]], m: Measure, floor: int) -> DataFrame:
        """Add `tight`, an estimate from each candidate's rows counted by target bin, close to the optimum over all refinements."""
        counts = counting.target_bins(cands, self.bins()[1], patterns, self.blocked, True)
        make = bounds.binned_family if m.bound == "family" else bounds.binned_median
        best = make(counts, ["code"], m.a or 0.0, self.norms, floor).select(F.col("code").alias("_c"), F.col("bound").alias("tight"))
        return cands.join(best, F.col("code") == F.col("_c"), "left").drop("_c")

    def collect(self, df: DataFrame) -> list[dict]:
        return [{k: r[k] for k in (*KEPT, "description")} | {"p": tuple(r["p"])} for r in df.collect()]


class _ByName(dict):
    """Selectors by name; those of tokens are made when asked for."""

    tokens: str | None = None

    def __missing__(self, name: str) -> Selector:
        return Selector(name[1:], "token", name[1:], self.tokens)


class TokenSession(Session):
    """A session for beam searches over tokens that grow with the table: every token of a row takes part, but no list of
    them is made. The driver sees the patterns of a level and at most FEW names."""

    FEW = 1000

    def __init__(self, ds: SubgroupDataset, dense: list[Selector]):
        self.ds, self.norms = ds, ds.norms(False)
        self.selectors = _ByName({str(i): s for i, s in enumerate(dense)})
        self.selectors.tokens = ds.tokens
        self.labels = [s.label for s in dense]
        self.blocked = defaultdict(list, {str(i): [str(j) for j in b] for i, b in enumerate(counting.blocked_pairs(dense))})
        self.encoded = named_rows(ds, dense, self.norms)
        self.level: DataFrame | None = None
        self.one: tuple[Measure, int, DataFrame] | None = None

    def close(self) -> None:
        if self.one is not None:
            self.one[2].unpersist()
            self.one = None

    def describe(self, p) -> str:
        return " & ".join(sorted(self.selectors[i].label for i in p))

    def candidates(self, patterns: list[tuple[str, ...]], measure: Measure, floor: int, ordered: bool, keep: int | None = None, bounded: bool = False) -> DataFrame:
        """As Session.candidates for moments; with `keep`, a selector whose own rows hold no refinement among the best
        `keep` is not tried: its optimistic estimate lies below a score that `keep` refinements reach."""
        if ordered or measure.needs == "median":
            raise ValueError("tokens by name are searched by beam, with measures of moments")
        if patterns == [()]:
            return self.singles(measure, floor)
        if keep is None or measure.bound == "none":
            return self.counted(patterns, measure, floor)
        one = self.singles(measure, floor)
        near = [r["s"] for r in one.orderBy(F.desc("bound")).select("s").limit(self.FEW).collect()]
        first = self.counted(patterns, measure, floor, free=F.filter("sels", lambda s: s.isin(near)))
        best = lattice.distinct_extents(first.where(F.col("score").isNotNull())).select("score").orderBy(F.desc("score")).limit(keep)
        worst = best.agg(F.min("score"), F.count("*")).first()
        hold = one.where(F.col("bound") >= worst[0]) if worst[1] == keep else one
        if hold.count() <= self.FEW:  # they are the first of `one` by bound
            return first
        return self.counted(patterns, measure, floor, only=hold)

    def singles(self, measure: Measure, floor: int) -> DataFrame:
        """Every selector of `floor` rows or more, with the estimate of its refinements; read by each level."""
        if self.one is None or self.one[:2] != (measure, floor):
            self.close()
            rows = self.counted([()], measure, floor, bounded=measure.bound != "none")
            estimate = bounds.estimate(measure, self.norms, floor) if measure.bound != "none" else F.lit(None).cast("double")
            # a margin for the rounding of scores and of sums
            rows = rows.withColumn("bound", F.coalesce(estimate + F.abs(estimate) * 1e-9 + 1e-8, F.lit(float("inf"))))
            self.one = (measure, floor, rows.persist())
        return self.one[2]

    def counted(self, patterns: list[tuple[str, ...]], measure: Measure, floor: int, bounded: bool = False, **which) -> DataFrame:
        labels = constant(self.labels, "array<string>")
        label = lambda s: F.when(s.startswith("="), F.concat(s.substr(F.lit(2), F.length(s)), F.lit(">0"))).otherwise(F.try_element_at(labels, s.try_cast("int") + 1))
        rows = counting.named_level_counts(self.encoded, self.norms.form, patterns, self.blocked, measure.spread, bounded, **which).where(F.col("n") >= floor)
        rows = rows.withColumn("description", F.array_join(F.array_sort(F.transform("p", label)), " & ")).withColumn("n_sel", F.size("p"))
        return rows.withColumn("med", F.lit(None).cast("double")).withColumn("score", scored(measure, self.norms))


def beam(session: Session, measure: str | Measure = "wracc", k: int = 10, depth: int = 2, width: int = 50, min_support: int | None = None, seed: tuple[int, ...] = ()) -> Found:
    """Level by level: refine the kept patterns, score all refinements in one scan, keep the best `width` extents of the
    level; the result is the best k of all that was kept. One driver round trip a level, of `width` rows."""
    m = get(measure)
    floor = min_support if min_support is not None else session.default_floor()
    width = max(width, 1)
    patterns, kept, trace = [tuple(seed)], [], []
    for level in range(1, depth + 1):
        began = time.time()
        cands = session.candidates(patterns, m, floor, False, width)
        cands = cands.where(F.col("score").isNotNull())
        best = lattice.distinct_extents(cands).orderBy(F.desc("score"), "n_sel", "description").limit(width)
        rows = session.collect(best)
        session.end_level()
        trace.append({"level": level, "parents": len(patterns), "kept": len(rows), "threshold": min((r["score"] for r in rows), default=None), "seconds": time.time() - began})
        if not rows:
            break
        kept += [r | {"level": level} for r in rows]
        patterns = [r["p"] for r in rows]
    return Found(top(distinct(kept), k, False), trace, True, session.selectors, session.norms)


def beam_levels(session: Session, measure: str, depth: int, width: int, min_support: int | None = None) -> list[dict]:
    """All that a beam search keeps, by level."""
    m, floor = get(measure), min_support if min_support is not None else session.default_floor()
    patterns, out = [()], []
    for level in range(1, depth + 1):
        cands = session.candidates(patterns, m, floor, False).where(F.col("score").isNotNull())
        rows = session.collect(lattice.distinct_extents(cands).orderBy(F.desc("score"), "n_sel", "description").limit(width))
        out += [r | {"level": level, "place": i + 1} for i, r in enumerate(rows)]
        patterns = [r["p"] for r in rows]
        if not rows:
            break
    return out


def exhaustive(
    session: Session, measure: str | Measure = "wracc", k: int = 10, depth: int = 2, min_support: int | None = None, order: str = "depth", bound: str = "moment", batch: int = 150, time_limit_s: float = 1000.0, allow_small: bool = False, binary: bool = False
) -> Found:
    """Every pattern of at most `depth` selectors that could be among the best k, ties at rank k included.

    Patterns grow by selectors of greater id only, so each is met once. A batch of prefixes is counted in one scan;
    refinements under min_support, and those whose optimistic estimate lies below the k-th score, leave in that same
    job. `order` says which prefixes go next: depth, level or best.
    """
    m = get(measure)
    if m.a == 0.0 and min_support is None and not allow_small:
        raise ValueError(f"{m.name} ignores size: give min_support, or allow_small=True")
    if bound not in ("none", "moment", "tight"):
        raise ValueError("bound is none, moment or tight")
    if order not in ("depth", "level", "best"):
        raise ValueError("order is depth, level or best")
    floor = min_support if min_support is not None else session.default_floor()
    began, best, trace, complete = time.time(), [], [], True
    frontier: list[tuple[float, tuple[int, ...]]] = [(float("inf"), ())]
    while frontier:
        if time.time() - began > time_limit_s:
            complete = False
            break
        if order == "best":
            frontier.sort(key=lambda x: x[0])
        elif order == "depth":
            frontier.sort(key=lambda x: len(x[1]))
        else:
            frontier.sort(key=lambda x: -len(x[1]))
        threshold = best[-1]["score"] if len(best) >= k else None
        take, frontier = frontier[-batch:], frontier[:-batch]
        alive = [p for b, p in take if threshold is None or b >= threshold]
        cut = len(take) - len(alive)
        if not alive:
            continue
        cands = session.candidates(alive, m, floor, True, bounded=bound != "none")
        estimate = bounds.estimate(m, session.norms, floor, binary) if bound != "none" else F.lit(None).cast("double")
        if bound == "tight" and not binary and m.bound in ("family", "median"):
            cands, estimate = session.with_tight(cands, alive, m, floor), F.col("tight")
        # the score is rounded, so is the estimate's margin
        cands = cands.withColumn("bound", F.coalesce(estimate + 1e-8, F.lit(float("inf"))))
        cands = cands.persist()
        counted = cands.count()
        better = cands.where(F.col("score").isNotNull() & (F.col("score") >= threshold if threshold is not None else F.lit(True)))
        offered = session.collect(_top_with_ties(lattice.distinct_extents(better), k))
        best = top(distinct([{x: r[x] for x in r if x != "rank"} for r in best] + offered), k, True)
        threshold = best[-1]["score"] if len(best) >= k else None
        grow = cands.where((F.size("p") < depth) & (F.col("bound") >= threshold if threshold is not None else F.lit(True)))
        new = [(r["bound"], tuple(r["p"])) for r in grow.select("p", "bound").collect()]
        cands.unpersist()
        frontier += new
        trace.append({"level": len(trace) + 1, "parents": len(alive), "evaluated": counted, "pushed": len(new), "pruned_parents": cut, "threshold": threshold, "seconds": time.time() - began})
    return Found(best, trace, complete, session.selectors, session.norms)


def _top_with_ties(df: DataFrame, k: int) -> DataFrame:
    """Rows with fewer than k strictly better scores: first the k-th score by a bounded sort, then all at or above it."""
    floor = df.select("score").orderBy(F.desc("score")).limit(k).agg(F.min("score")).first()[0]
    return df.where(F.col("score") >= floor) if floor is not None else df.limit(0)


def brute(session: Session, measure: str | Measure = "wracc", k: int = 10, depth: int = 2, min_support: int | None = None, ties: bool = True) -> DataFrame:
    """Naive enumeration: every row names all its selector sets of at most `depth`, and a group-by counts them."""
    m, floor = get(measure), min_support if min_support is not None else session.default_floor()
    one = F.transform("sels", lambda s: F.array(s))
    sets = one
    lookup = constant(session.blocked, "array<array<int>>")
    for _ in range(depth - 1):
        def larger(p):
            last = F.element_at(p, -1)
            free = lambda s: (s > last) & ~F.exists(p, lambda q: F.array_contains(F.element_at(lookup, q + 1), s))
            return F.transform(F.filter("sels", free), lambda s: F.concat(p, F.array(s)))

        sets = F.concat(one, F.flatten(F.transform(sets, larger)))
    every = session.cells.withColumn("p", F.explode(F.array_distinct(sets)))
    stats = every.groupBy("p").agg(*[F.sum(c).alias(c) for c in ("n", *session.norms.form.columns, "s2")], F.bit_xor("sig_x").alias("sig_x"), F.sum("sig_s").alias("sig_s")).where(F.col("n") >= floor)
    stats = stats.withColumn("s1", session.norms.form.total())
    names = F.array_join(F.array_sort(F.transform("p", lambda i: F.element_at(constant(session.labels, "array<string>"), i + 1))), " & ")
    rows = stats.withColumn("description", names).withColumn("n_sel", F.size("p")).withColumn("score", scored(m, session.norms)).where("score is not null")
    rows = lattice.distinct_extents(rows)
    order = [F.desc("score")] if ties else [F.desc("score"), F.asc("n_sel"), F.asc("description")]
    ranked = _top_with_ties(rows, k).withColumn("rank", F.rank().over(Window.orderBy(*order)))  # a result-size table
    return ranked.where(F.col("rank") <= k).select("rank", "description", "n_sel", F.col("n").alias("size"), F.round(F.col("s1").cast("double") / F.col("n"), 6).alias("mean"), "score")


def null_scores(ds: SubgroupDataset, selectors: list[Selector], measure: str, rounds: int = 20, depth: int = 1, width: int = 50, grid: int = 1000) -> list[float]:
    """Best scores that chance alone gives: each round draws every row's target anew from the whole distribution.

    The draw is a hash of row and round into `grid` quantiles of the target, so it needs no shuffle and can be repeated.
    """
    at = [i / grid for i in range(grid + 1)]
    levels = quantiles(ds.rows(), "t", at)
    out = []
    for r in range(rounds):
        draw = F.element_at(constant(levels, "array<double>"), (F.pmod(F.xxhash64(F.lit(r), F.col(ds.oid)), F.lit(grid + 1)) + 1).cast("int"))
        session = Session(ds.with_target(draw), selectors, get(measure).needs == "median")
        found = beam(session, measure, 1, depth, width)
        session.close()
        out.append(found.rows[0]["score"] if found.rows else float("-inf"))
    return out
