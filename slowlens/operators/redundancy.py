"""Overlap of extents, and two ways to thin a result: greedy choice and hierarchical clustering."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from slowlens.operators.dataset import SubgroupDataset
from slowlens.operators.lattice import describe
from slowlens.operators.stats import Pattern, matches


def jaccard(ds: SubgroupDataset, patterns: list[Pattern]) -> DataFrame:
    """(p, q, both, size_p, size_q, jaccard) for p < q, places in the list: one scan, pairs counted map-side.

    Rows that match the same patterns are grouped first, so pairs are made once per distinct set of matches.
    """
    sets = matches(ds, patterns).groupBy(F.col("_m").alias("m")).agg(F.count("*").alias("n"))
    sizes = sets.select(F.explode("m").alias("p"), "n").groupBy("p").agg(F.sum("n").alias("n"))
    pairs = sets.select(F.explode("m").alias("p"), "m", "n").select("p", F.explode("m").alias("q"), "n").where("p < q").groupBy("p", "q").agg(F.sum("n").alias("shared"))
    left, right = sizes.select("p", F.col("n").alias("size_p")), sizes.select(F.col("p").alias("q"), F.col("n").alias("size_q"))
    every = left.join(right, F.col("p") < F.col("q"))  # at most the square of the result's length
    out = every.join(pairs, ["p", "q"], "left").withColumn("shared", F.coalesce("shared", F.lit(0)))
    return out.withColumn("jaccard", F.col("shared") / (F.col("size_p") + F.col("size_q") - F.col("shared")))


def named(similarities: DataFrame, patterns: list[Pattern]) -> DataFrame:
    """The same with descriptions, first in the alphabet first."""
    names = F.lit([describe(p) for p in patterns])
    a, b = F.element_at(names, F.col("p") + 1), F.element_at(names, F.col("q") + 1)
    return similarities.select(F.least(a, b).alias("p"), F.greatest(a, b).alias("q"), "shared", F.round("jaccard", 6).alias("jaccard"))


def matrix(similarities: DataFrame, n: int) -> np.ndarray:
    """The similarities of a result of n patterns, on the driver."""
    out = np.eye(n)
    for r in similarities.select("p", "q", "jaccard").collect():
        out[r["p"], r["q"]] = out[r["q"], r["p"]] = r["jaccard"]
    return out


def greedy(scores: list[float], sim: np.ndarray, threshold: float = 0.5, names: list[str] | None = None) -> list[int]:
    """Take the best, drop those that overlap it by more than the threshold, and so on."""
    names = names or [str(i).zfill(6) for i in range(len(scores))]
    left = sorted(range(len(scores)), key=lambda i: (-scores[i], names[i]))
    kept = []
    while left:
        kept.append(left[0])
        left = [i for i in left[1:] if sim[kept[-1], i] <= threshold]
    return kept


def sweep(scores: list[float], sim: np.ndarray, thresholds: list[float], names: list[str] | None = None) -> list[tuple[float, int]]:
    return [(t, len(greedy(scores, sim, t, names))) for t in thresholds]


def dendrogram(sim: np.ndarray, linkage: str = "average") -> list[tuple[int, int, float, int]]:
    """Merges (left, right, height, size); new clusters are numbered on from the patterns. Distances are 1 - Jaccard."""
    if linkage not in ("average", "complete", "single"):
        raise ValueError("linkage is average, complete or single")
    n = len(sim)
    d = {(i, j): 1 - sim[i, j] for i in range(n) for j in range(i + 1, n)}
    size, live, out = dict.fromkeys(range(n), 1), set(range(n)), []
    for step in range(n - 1):
        (a, b), h = min(((k, v) for k, v in d.items()), key=lambda x: (round(x[1], 12), x[0]))
        new = n + step
        live -= {a, b}
        for c in live:
            x, y = d.pop((min(a, c), max(a, c))), d.pop((min(b, c), max(b, c)))
            d[(c, new)] = min(x, y) if linkage == "single" else max(x, y) if linkage == "complete" else (size[a] * x + size[b] * y) / (size[a] + size[b])
        del d[(a, b)]
        size[new] = size[a] + size[b]
        live.add(new)
        out.append((a, b, float(h), size[new]))
    return out


def cut(merges: list[tuple[int, int, float, int]], n: int, n_clusters: int | None = None, height: float | None = None) -> list[int]:
    """Cluster number of each pattern, from merges up to a height or down to a number of clusters."""
    parent = list(range(n + len(merges)))

    def root(x: int) -> int:
        while parent[x] != x:
            x = parent[x]
        return x

    for step, (a, b, h, _) in enumerate(merges):
        if (n_clusters is not None and n - step <= n_clusters) or (height is not None and h > height):
            break
        parent[root(a)] = parent[root(b)] = n + step
    roots: dict[int, int] = {}
    return [roots.setdefault(root(i), len(roots)) for i in range(n)]


def representatives(clusters: list[int], scores: list[float], names: list[str]) -> list[int]:
    """The best pattern of each cluster."""
    best: dict[int, int] = {}
    for i in sorted(range(len(clusters)), key=lambda i: (-scores[i], names[i])):
        best.setdefault(clusters[i], i)
    return sorted(best.values(), key=lambda i: (-scores[i], names[i]))


def minhash(ds: SubgroupDataset, patterns: list[Pattern], hashes: int = 64) -> DataFrame:
    """(p, q, estimate): Jaccard from the least hash of each extent under several seeds, for results too large for pairs."""
    rows = matches(ds, patterns).select(F.explode("_m").alias("p"), "oid")
    mins = rows.groupBy("p").agg(F.array(*[F.min(F.xxhash64(F.lit(s), "oid")) for s in range(hashes)]).alias("h"))
    other = mins.select(F.col("p").alias("q"), F.col("h").alias("g"))
    same = F.aggregate(F.zip_with("h", "g", lambda a, b: (a == b).cast("int")), F.lit(0), lambda a, b: a + b)
    return mins.join(other, F.col("p") < F.col("q")).select("p", "q", (same / hashes).alias("estimate"))


def weighted_cover(ds: SubgroupDataset, patterns: list[Pattern], scores: list[float], k: int, decay: float = 0.5) -> list[int]:
    """k patterns one by one: a row counts decay^c once it is covered c times, so later choices cover new rows."""
    sets = [(r["m"], r["n"]) for r in matches(ds, patterns).groupBy(F.col("_m").alias("m")).agg(F.count("*").alias("n")).collect()]
    sizes = [sum(n for m, n in sets if i in m) for i in range(len(patterns))]
    covered, chosen = [0] * len(sets), []
    while len(chosen) < min(k, len(patterns)):
        def gain(i: int) -> float:
            own = sum(n * decay ** covered[j] for j, (m, n) in enumerate(sets) if i in m)
            return scores[i] * own / sizes[i] if sizes[i] else 0.0

        best = max((i for i in range(len(patterns)) if i not in chosen), key=lambda i: (gain(i), -i))
        chosen.append(best)
        for j, (m, _) in enumerate(sets):
            covered[j] += best in m
    return chosen
