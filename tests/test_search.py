"""Beam, exhaustive and naive search agree; pruning, orders and options change nothing but work."""

import itertools
import random

import pytest
from pyspark.sql import functions as F

from slowlens.operators import redundancy, selectors, stats
from slowlens.operators.counting import bitmap_sizes, bitmap_store
from slowlens.operators.dataset import SubgroupDataset
from slowlens.operators.encode import encode, encode_by_index
from slowlens.operators.lattice import describe
from slowlens.plans import search
from slowlens.plans.interactive import Exploration


@pytest.fixture(scope="module")
def session(spark):
    rng = random.Random(3)
    rows = [(i, round(rng.expovariate(0.1), 2), rng.choice("abc"), rng.choice("xy"), rng.randint(0, 9), {f"t{j}": 1 for j in range(4) if rng.random() < 0.3}) for i in range(400)]
    df = spark.createDataFrame(rows, "oid int, t double, p string, q string, k int, tok map<string,int>").withColumn("t", F.col("t").cast("decimal(18,2)"))
    ds = SubgroupDataset(df, numeric=("k",), nominal=("p", "q"), tokens="tok")
    sels = selectors.build(ds, "explicit", values={"k": [3, 6]})
    return search.Session(ds, sels)


def by_hand(session, depth, floor, score):
    rows = [(set(r["sels"]), float(r["t"]), r["oid"]) for r in session.encoded.collect()]
    out = {}
    for d in range(1, depth + 1):
        for p in itertools.combinations(range(len(session.selectors)), d):
            if any(session.selectors[a].conflicts(session.selectors[b]) for a, b in itertools.combinations(p, 2)):
                continue
            hit = [(t, o) for s, t, o in rows if s.issuperset(p)]
            if len(hit) >= floor:
                key = frozenset(o for _, o in hit)
                name = session.describe(p)
                value = score([t for t, _ in hit])
                if key not in out or (len(p), name) < out[key][:2]:
                    out[key] = (len(p), name, value)
    return sorted(((round(v, 6), n) for _, n, v in out.values()), key=lambda x: (-x[0], x[1]))


@pytest.mark.parametrize("measure", ["wracc", "mean_test", "median_0.5"])
def test_all_searches_find_the_same(spark, session, measure):
    g = session.norms

    def score(v):
        if measure.startswith("median"):
            s = sorted(v)
            return (len(v) / g.n) ** 0.5 * ((s[(len(s) - 1) // 2] + s[len(s) // 2]) / 2 - g.median)
        return (len(v) / g.n) ** (1 if measure == "wracc" else 0.5) * (sum(v) / len(v) - g.mean)

    want = by_hand(session, 2, 10, score)[:8]
    options = dict(measure=measure, k=8, depth=2, min_support=10)
    wide = search.beam(session, width=10_000, **options)
    assert [(round(r["score"], 6), r["description"]) for r in wide.rows] == want
    for order in ("depth", "level", "best"):
        for bound in ("moment", "none", "tight"):
            found = search.exhaustive(session, order=order, bound=bound, batch=7, **options)
            assert [(round(r["score"], 6), r["description"]) for r in found.rows][:8] == want and found.complete
    narrow = search.beam(session, width=2, **options)
    assert narrow.rows[0]["score"] <= wide.rows[0]["score"] and len(narrow.trace) == 2
    if measure != "median_0.5":
        naive = search.brute(session, measure, 8, 2, 10).orderBy("rank", "n_sel", "description").collect()
        assert [r["description"] for r in naive][:8] == [n for _, n in want]
        assert [r["score"] for r in naive][:8] == pytest.approx([v for v, _ in want], abs=2e-6)


def test_bounds_prune_and_depth_helps(session):
    full = search.exhaustive(session, "wracc", 3, 3, 10, bound="none")
    cut = search.exhaustive(session, "wracc", 3, 3, 10, batch=5, order="best")
    assert [r["description"] for r in full.rows] == [r["description"] for r in cut.rows]
    assert sum(t["evaluated"] for t in cut.trace) < sum(t["evaluated"] for t in full.trace)
    shallow = search.exhaustive(session, "wracc", 3, 1, 10)
    assert shallow.rows[0]["score"] <= full.rows[0]["score"]
    more = search.exhaustive(session, "wracc", 6, 2, 10)
    less = search.exhaustive(session, "wracc", 3, 2, 10)
    assert {r["description"] for r in less.rows} <= {r["description"] for r in more.rows}


def test_limits(session):
    with pytest.raises(ValueError):
        search.exhaustive(session, "average")
    assert not search.exhaustive(session, "wracc", time_limit_s=-1).complete
    assert search.beam(session, "wracc", min_support=10_000).rows == []
    assert len(search.beam(session, "wracc", k=10_000, depth=1).rows) <= len(session.selectors)


def test_encodings_and_bitmaps(spark, session):
    plain = {r["oid"]: list(r["sels"]) for r in encode(session.ds, session.selectors).collect()}
    joined = {r["oid"]: list(r["sels"]) for r in encode_by_index(session.ds, session.selectors).collect()}
    assert plain == joined
    store = bitmap_store(session.encoded)
    pairs = [(0, 0), (0, 5), (1, 1), (2, 0), (2, 4)]
    got = {r["pattern_id"]: r["size"] for r in bitmap_sizes(store, spark.createDataFrame(pairs, "pattern_id int, sel int")).collect()}
    for pid in (0, 1, 2):
        want = sum(all(s in v for p, s in pairs if p == pid) for v in plain.values())
        assert got.get(pid, 0) == want


def test_redundancy(session):
    found = search.exhaustive(session, "mean_test", 8, 2, 10)
    patterns, scores = found.patterns(), [r["score"] for r in found.rows]
    names = [describe(p) for p in patterns]
    ext = [{r["oid"] for r in session.ds.rows().where(stats.to_column(p)).collect()} for p in patterns]
    sim = redundancy.matrix(redundancy.jaccard(session.ds, patterns), len(patterns))
    for i, j in itertools.combinations(range(len(ext)), 2):
        assert sim[i, j] == pytest.approx(len(ext[i] & ext[j]) / len(ext[i] | ext[j]))
    kept = redundancy.greedy(scores, sim, 0.4, names)
    assert kept[0] == 0 and all(sim[a, b] <= 0.4 for a, b in itertools.combinations(kept, 2))
    for linkage in ("single", "complete", "average"):
        tree = redundancy.dendrogram(sim, linkage)
        heights = [round(m[2], 9) for m in tree]
        assert len(tree) == len(patterns) - 1 and heights == sorted(heights)
        for c in range(1, len(patterns) + 1):
            assert len(set(redundancy.cut(tree, len(patterns), n_clusters=c))) == c
    assert redundancy.dendrogram(sim[:1, :1]) == []
    est = {(r["p"], r["q"]): r["estimate"] for r in redundancy.minhash(session.ds, patterns, 256).collect()}
    assert max(abs(est[i, j] - sim[i, j]) for i, j in est) < 0.15
    cover = redundancy.weighted_cover(session.ds, patterns, scores, 3)
    assert len(set(cover)) == 3 and cover[0] == 0


def test_exploration(session):
    e = Exploration(session.ds, session.selectors).brush("t", "k", (0, 30), (0, 9)).paint_target("t", "k", (20, 30), (0, 9))
    rows = e.ds.rows().collect()
    assert rows and all(0 <= r["k"] <= 9 for r in rows) and {int(r["t"]) for r in rows} == {0, 1}
    mined = e.mine("wracc", k=3, min_support=10)
    assert mined.results().count() == 3 and mined.report().count() == 3
    first = mined.found.patterns()[0][:1]
    assert all(first[0].label in r["description"] for r in mined.drill(first, k=3).results().collect())
    with pytest.raises(ValueError):
        e.results()


def test_edges(spark):
    empty = SubgroupDataset(spark.createDataFrame([], "oid int, t double, a string"), nominal=("a",))
    assert selectors.nominal(empty, ["a"]) == []
    odd = spark.createDataFrame([(1, 1.0, "a&b", float("nan")), (2, 5.0, "ü'\"", 3.0), (3, 2.0, None, None), (4, 9.0, "ü'\"", float("inf"))], "oid int, t double, a string, x double")
    ds = SubgroupDataset(odd, numeric=("x",), nominal=("a",))
    sels = selectors.nominal(ds, ["a"]) + selectors.numeric("x", [2.0])
    s = search.Session(ds, sels)
    sizes = {r["description"]: r["n"] for r in search.beam(s, "support", 10, 1, min_support=1).rows}
    assert sizes["a=ü'\""] == 2 and sizes.get("x>=2", 2) == 2
    s.close()


def test_a_wide_beam_keeps_a_small_plan(session, monkeypatch):
    from slowlens.operators import counting

    want = [r["description"] for r in search.beam(session, "wracc", 8, 3, 30, 10).rows]
    monkeypatch.setattr(counting, "UNROLLED", 2)
    assert [r["description"] for r in search.beam(session, "wracc", 8, 3, 30, 10).rows] == want


def test_too_many_categories_are_refused(session):
    with pytest.raises(ValueError, match="categories"):
        selectors.nominal(session.ds, ["p", "q"], max_values=1)


def test_chance_scores(session):
    rows = search.null_scores(session.ds, session.selectors[:5], "mean_test", rounds=4)
    assert len(rows) == 4 and len(set(rows)) > 1


def test_an_unfinished_search_gives_no_frame():
    with pytest.raises(TimeoutError):
        search.Found([], complete=False).frame(None)


@pytest.mark.parametrize("few", [1, 1000])
@pytest.mark.parametrize("measure", ["wracc", "lift", "tscore"])
def test_tokens_by_name_find_the_same(session, monkeypatch, measure, few):
    from slowlens.operators import counting

    monkeypatch.setattr(counting, "UNROLLED", few)
    monkeypatch.setattr(search.TokenSession, "FEW", few)
    dense = [s for s in session.selectors if s.op != "token"]
    ds = session.ds.persisted()
    with search.TokenSession(ds, dense) as named:
        for depth, width in ((2, 4), (3, 20)):
            want = search.beam(session, measure, 8, depth, width, 10)
            got = search.beam(named, measure, 8, depth, width, 10)
            assert [(r["description"], r["n"], r["score"]) for r in got.rows] == [(r["description"], r["n"], r["score"]) for r in want.rows]
            assert {frozenset(p) for p in got.patterns()} == {frozenset(p) for p in want.patterns()}
    ds.df.unpersist()


def test_orders_are_searched_without_a_list_of_their_tokens(spark, monkeypatch):
    from slowlens.plans import registry, search_queries  # noqa: F401

    def refuse(*_):
        raise AssertionError("the tokens of orders grow with the table")

    monkeypatch.setattr(selectors, "tokens", refuse)
    assert registry.QUERIES["w_sparse_orders"](spark, "/root/testdata/sf0.001").count() == 10
