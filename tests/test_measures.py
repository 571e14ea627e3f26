"""Identities of the measures, golden values of the toy data, and validity of the bounds by brute force."""

import itertools
import math
import random

import pytest
from pyspark.sql import functions as F

from slowlens.functions import bounds, measures
from slowlens.functions.measures import Norms, get, scored
from slowlens.operators import lattice, redundancy, selectors, stats
from slowlens.operators.dataset import SubgroupDataset
from slowlens.operators.selectors import Selector
from slowlens.sources import datasets

PATTERNS = {
    "date": ((Selector("where_a_date", ">", 0),), dict(n=4, precision=1.0, lift=2.2, wracc_b=0.19835, mt_b=0.32892, mean=15.1025, u=5.9752, wracc=2.1728, mt=3.6032, med=15.805, q=3.5307, t=1.3896)),
    "pair": ((Selector("where_b_key", "=", 1), Selector("soft_version", "=", "v2")), dict(n=4, precision=0.75, lift=1.65, wracc_b=0.10744, mt_b=0.17817, mean=12.83, u=3.7027, wracc=1.3464, mt=2.2328, med=12.785, q=1.7096, t=0.9031)),
    "alert": ((Selector("from_a", ">", 0), Selector("alert_sessions", "=", "Critical")), dict(n=3, precision=0.6667, lift=1.4667, wracc_b=0.05785, mt_b=0.11078, mean=14.23, u=5.1027, wracc=1.3917, mt=2.6648, med=15.81, q=3.0603, t=0.6953)),
    "site": ((Selector("from_b", ">=", 1), Selector("site", "=", "LYN")), dict(n=4, precision=0.5, lift=1.1, wracc_b=0.01653, mt_b=0.02741, mean=7.4425, u=-1.6848, wracc=-0.6126, mt=-1.016, med=6.485, q=-2.0895, t=-0.165)),
}


def toy(spark, target):
    return SubgroupDataset(datasets.toy_frame(spark).withColumn("t", F.col(target)), numeric=("from_a", "from_b", "where_a_key", "where_a_date", "where_b_key"), nominal=("soft_version", "site"), ordinal={"alert_sessions": datasets.LEVELS})


def values(spark, ds, pattern, names):
    g = ds.norms()
    t = F.col("t").cast("decimal(18,2)")
    row = ds.rows().where(lattice.to_column(pattern)).agg(F.count("*").alias("n"), F.sum(t).alias("s1"), F.sum((t.cast("double") - g.mean) * (t.cast("double") - g.mean)).alias("s2"), F.percentile(t.cast("double"), 0.5).alias("med"))
    return row.select("n", "med", (F.col("s1").cast("double") / F.col("n")).alias("mean"), *[scored(m, g).alias(f"x{i}") for i, m in enumerate(names)]).first()


@pytest.mark.parametrize("name", PATTERNS)
def test_toy_values(spark, name):
    pattern, want = PATTERNS[name]
    num = values(spark, toy(spark, "time_s"), pattern, ["average", "wracc", "mean_test", "median_0.5", "tscore"])
    assert num["n"] == want["n"]
    for got, key in zip([num["mean"], num["med"], *[num[f"x{i}"] for i in range(5)]], ["mean", "med", "u", "wracc", "mt", "q", "t"], strict=True):
        assert got == pytest.approx(want[key], abs=6e-5)
    binary = values(spark, toy(spark, "slow"), pattern, ["precision", "lift", "wracc_binary", "mean_test", "wracc"])
    for i, key in enumerate(["precision", "lift", "wracc_b", "mt_b", "wracc_b"]):
        assert binary[f"x{i}"] == pytest.approx(want[key], abs=6e-5)


def test_toy_norms_extent_and_overlap(spark):
    g = toy(spark, "time_s").norms()
    assert (g.n, round(g.mean, 4), g.median) == (11, 9.1273, 9.95) and g.std == pytest.approx(6.247813, abs=1e-5)
    ext = {r["oid"] for r in lattice.extent(toy(spark, "slow"), PATTERNS["site"][0]).collect()}
    assert ext == {"o4", "o5", "o7", "o11"}
    sim = redundancy.jaccard(toy(spark, "slow"), [(Selector("from_a", ">=", 1),), (Selector("where_a_key", ">=", 1),)]).first()
    assert sim["jaccard"] == pytest.approx(6 / 7)


def plain(rows, g, a):
    return (len(rows) / g.n) ** a * (sum(rows) / len(rows) - g.mean)


def median(rows):
    s = sorted(rows)
    return (s[(len(s) - 1) // 2] + s[len(s) // 2]) / 2


@pytest.mark.parametrize("seed", range(4))
def test_bounds_never_fall_below_a_refinement(spark, seed):
    rng = random.Random(seed)
    cases, best = [], {}
    binary = seed % 2 == 1
    g = None
    for c in range(25):
        rows = [float(rng.randint(0, 1)) if binary else round(rng.expovariate(0.2), 2) for _ in range(rng.randint(2, 7))]
        cases += [(c, x) for x in rows]
    everything = [x for _, x in cases]
    mean = sum(everything) / len(everything)
    sd = math.sqrt(sum((x - mean) ** 2 for x in everything) / len(everything))
    g = Norms(len(everything), mean, median(everything), sd, sum(x > 0 for x in everything))
    df = spark.createDataFrame(cases, "c int, t double")
    agg = df.groupBy("c").agg(F.count("*").alias("n"), *[v.alias(k) for k, v in bounds.inputs(F.col("t"), g).items()])
    for floor in (1, 2):
        names = [f"klosgen_{a:g}" for a in (0, 0.25, 0.5, 1)] + ["lift", "wracc_abs", "median_0", "median_0.5", "median_1"] + (["binomial"] if binary else [])
        got = {r["c"]: r for r in agg.select("c", *[bounds.estimate(get(m), g, floor, binary).alias(f"b{i}") for i, m in enumerate(names)]).collect()}
        fine = df.groupBy("c", F.col("t").alias("bin")).agg(F.count("*").alias("n"), F.sum("t").alias("s"), F.max("t").alias("top"))
        rough = df.groupBy("c", F.floor(F.col("t") / 4).alias("bin")).agg(F.count("*").alias("n"), F.sum("t").alias("s"), F.max("t").alias("top"))
        tight = {a: {r["c"]: r["bound"] for r in bounds.binned_family(fine, ["c"], a, g, floor).collect()} for a in (0.0, 0.5)}
        loose = {a: {r["c"]: r["bound"] for r in bounds.binned_family(rough, ["c"], a, g, floor).collect()} for a in (0.0, 0.5)}
        tight_med, loose_med = ({r["c"]: r["bound"] for r in bounds.binned_median(x, ["c"], 0.5, g, floor).collect()} for x in (fine, rough))
        for c in range(25):
            rows = [x for k, x in cases if k == c]
            subsets = [s for k in range(floor, len(rows) + 1) for s in itertools.combinations(rows, k)]
            score = {
                **{f"klosgen_{a:g}": max(plain(s, g, a) for s in subsets) for a in (0, 0.25, 0.5, 1)},
                "lift": max(sum(s) / len(s) / mean for s in subsets), "wracc_abs": max(abs(plain(s, g, 1)) for s in subsets),
                **{f"median_{a:g}": max((len(s) / g.n) ** a * (median(s) - g.median) for s in subsets) for a in (0, 0.5, 1)},
                "binomial": max(math.sqrt(len(s)) * (sum(s) / len(s) - mean) / math.sqrt(abs(mean * (1 - mean)) or 1) for s in subsets),
            }
            for i, m in enumerate(names):
                assert got[c][f"b{i}"] >= score[m] - 1e-9, (m, floor, rows)
            for a in (0.0, 0.5):
                assert tight[a][c] == pytest.approx(score[f"klosgen_{a:g}"], abs=1e-9)
                assert loose[a][c] >= score[f"klosgen_{a:g}"] - 1e-9
            assert tight_med[c] >= score["median_0.5"] - 1e-9 and loose_med[c] >= score["median_0.5"] - 1e-9
    del best


def test_orders_and_outliers(spark):
    df = spark.createDataFrame([(i, float(i % 7), "ab"[i % 2], i % 3) for i in range(60)], "oid int, t double, x string, y int")
    df2 = df.union(spark.createDataFrame([(99, 1e6, "a", 0)], df.schema))
    one, two = SubgroupDataset(df, nominal=("x",)), SubgroupDataset(df2, nominal=("x",))
    p = (Selector("x", "=", "a"),)
    a, b = values(spark, one, p, ["median_0.5", "average"]), values(spark, two, p, ["median_0.5", "average"])
    assert abs(a["x0"] - b["x0"]) < 1 and abs(a["x1"] - b["x1"]) > 1000
    assert values(spark, SubgroupDataset(df.withColumn("t", F.lit(3.0)), nominal=("x",)), p, ["tscore", "wracc"])[3] is None


def test_registry_refuses_bad_exponents_and_takes_own_measures(spark):
    for name in ("klosgen_1.5", "median_-1"):
        with pytest.raises(ValueError):
            get(name)
    with pytest.raises(KeyError):
        get("nothing")
    mine = measures.register("twice_wracc", "moments", lambda g: 2 * get("wracc").score(g))
    ds = toy(spark, "time_s")
    r = values(spark, ds, PATTERNS["date"][0], [mine, "wracc"])
    assert r["x0"] == pytest.approx(2 * r["x1"])


def test_selectors_conflicts_and_space():
    low, high, high2 = Selector("k", ">=", 1), Selector("k", "<", 5), Selector("k", "<", 7)
    assert not low.conflicts(high) and high.conflicts(high2) and Selector("k", "=", 3).conflicts(low)
    sels = [low, high, high2, *selectors.equals("c", ["a", "b"])]
    by_hand = 1 + len(sels) + sum(not x.conflicts(y) for x, y in itertools.combinations(sels, 2))
    assert lattice.space_size(sels, 2) == by_hand
    assert {lattice.describe(p) for p in lattice.refine([(low,)], sels)} == {"k<5 & k>=1", "k<7 & k>=1", "c=a & k>=1", "c=b & k>=1"}
    assert lattice.is_refinement((low, high), (low,)) and not lattice.is_refinement((low,), (low, high))


def test_dataset_checks(spark):
    df = spark.createDataFrame([(1, None, "x"), (2, 1.0, None)], "oid int, t double, a string")
    ds = SubgroupDataset(df, nominal=("a",))
    assert ds.rows().count() == 1 and ds.rows().where(Selector("a", "=", "x").column()).count() == 0
    with pytest.raises(Exception, match="target is null"):
        SubgroupDataset(df, nominal=("a",), on_null_target="error").rows().collect()
    with pytest.raises(ValueError):
        SubgroupDataset(df, nominal=("t",))
    assert stats.norms(ds).first()["n"] == 1
