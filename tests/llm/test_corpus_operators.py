"""Line dedup, near duplicates, neighbours, mixing, sharding and the pipeline against plain versions."""

import itertools
import random
from collections import Counter, defaultdict

import numpy as np
import pytest

import corpus_pipeline
from slowlens.llm import ann, linededup, minhash, mixing, registry, sharding
from slowlens.llm.common import Scratch, components, hot_keys, salted_join, table

SF = "/root/testdata/sf0.01"
DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def docs(spark, rows):
    return spark.createDataFrame([(i, t, "en", s, 0) for i, t, s in rows], DOCS)


# ---- line dedup


def plain_removed(texts, min_words):
    """For each place the longest run found earlier, by comparing all pairs of places."""
    lines = {i: t.split("\n") for i, t in sorted(texts.items()) if t is not None}
    places = [(i, p) for i in lines for p in range(len(lines[i]))]
    gone = defaultdict(set)
    for n, (i, p) in enumerate(places):
        best = 0
        for j, q in places[:n]:
            k = 0
            while p + k < len(lines[i]) and q + k < len(lines[j]) and lines[i][p + k] == lines[j][q + k]:
                k += 1
            best = max(best, k)
        if sum(len(x.split()) for x in lines[i][p : p + best]) >= min_words:
            gone[i] |= set(range(p, p + best))
    return gone


@pytest.mark.parametrize(("seed", "size"), [(0, 24), (1, 24), (2, 24), (3, 110)])
def test_line_dedup_against_all_pairs(spark, monkeypatch, seed, size):
    dealt, plain = [], linededup.with_kin
    monkeypatch.setattr(linededup, "with_kin", lambda *a: dealt.append(1) or plain(*a))
    rng = random.Random(seed)
    pool = [" ".join(rng.choice("abcdefg") for _ in range(rng.randint(0, 4))) for _ in range(6)]
    block = [f"line {k} of a block" for k in range(9)]
    texts = {}
    for i in range(size):
        ls = [rng.choice(pool) for _ in range(rng.randint(0, 8))]
        if rng.random() < 0.6:
            a = rng.randint(0, 5)
            ls += block[a : a + rng.randint(2, 5)]
        ls += [rng.choice(pool) for _ in range(rng.randint(0, 4))]
        texts[i] = "\n".join(ls)
    texts[30], texts[31], texts[32] = None, "", texts[3]
    want = plain_removed(texts, 8)
    got = linededup.line_decisions(docs(spark, [(i, t, "s") for i, t in texts.items()]).repartition(3), Scratch(spark, "t"), 8).collect()
    assert len(got) == len(texts)
    assert bool(dealt) == (size > 100)  # only there lines hold 1/500 of enough rows
    for r in got:
        assert {x for a in r["removed"] for x in range(a["first"], a["last"] + 1)} == want.get(r["doc_id"], set()), r
        assert r["n_removed"] == len(want.get(r["doc_id"], set()))
    left = {r["doc_id"]: r["text"] for r in linededup.without_repeats(docs(spark, [(i, t, "s") for i, t in texts.items()]), Scratch(spark, "t"), 8).collect()}
    for i, t in texts.items():
        assert left[i] == (None if t is None else t if not want.get(i) else "\n".join(x for k, x in enumerate(t.split("\n")) if k not in want[i]))


def test_line_dedup_of_nothing(spark):
    assert linededup.line_decisions(docs(spark, []), Scratch(spark, "t")).count() == 0
    same = linededup.line_decisions(docs(spark, [(1, "w " * 60, "s"), (1, "w " * 60, "s")]), Scratch(spark, "t")).collect()
    assert sorted(r["n_removed"] for r in same) == [0, 1]


# ---- near duplicates


def plain_classes(texts):
    sets = {}
    for i, t in texts.items():
        w = (t or "").lower().split()
        sets[i] = {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))}
    up = {i: i for i in texts}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in itertools.combinations(sorted(texts), 2):
        n = len(sets[a] & sets[b])
        if n >= 0.8 * (len(sets[a]) + len(sets[b]) - n):
            x, y = sorted((root(a), root(b)))
            up[y] = x
    return {i: root(i) for i in texts}


@pytest.mark.parametrize("chunk", [2048, 7])
def test_near_duplicates_against_all_pairs(spark, monkeypatch, chunk):
    monkeypatch.setattr(minhash, "CHUNK", chunk)
    monkeypatch.setattr(minhash, "MEMBERS", 5 if chunk == 7 else 256)
    monkeypatch.setattr(minhash, "FEW", 2 if chunk == 7 else 8)
    rng = random.Random(6)
    texts = {1: None, 2: "", 3: " \n ", 4: "a b", 5: "A b", 6: "a b c", 7: "word " * 3000}
    for g in range(6):
        base = [f"w{rng.randint(0, 5000)}" for _ in range(120)]
        for _ in range(14):
            own = list(base)
            for _ in range(rng.randint(0, 9)):
                own[rng.randrange(len(own))] = f"v{rng.randint(0, 10**6)}"
            texts[len(texts) + 1] = " ".join(own)
    for _ in range(40):
        texts[len(texts) + 1] = " ".join(f"u{rng.randint(0, 10**6)}" for _ in range(rng.randint(1, 40)))
    rows = [(i, t, "s") for i, t in texts.items()]
    rng.shuffle(rows)
    got = {r["doc_id"]: r["class_id"] for r in minhash.near_duplicate_classes(docs(spark, rows).repartition(5), Scratch(spark, "t")).collect()}
    assert got == plain_classes(texts)
    kept = {r["doc_id"] for r in minhash.drop_near_duplicates(docs(spark, rows + rows[:5]), Scratch(spark, "t")).collect()}
    assert kept == set(got.values())
    assert minhash.drop_near_duplicates(docs(spark, rows + rows[:5]), Scratch(spark, "t")).count() == len(kept)


def test_near_duplicates_with_repeated_lines(spark):
    rng = random.Random(9)
    texts = {}
    for g in range(12):  # one set of shingles, or 0.83 of it, and parts of it many times over
        base = [f"g{g}w{rng.randint(0, 10**6)}" for _ in range(104)]
        line = [f"g{g}x{k}" for k in range(20)]
        texts[3 * g] = " ".join(base)
        texts[3 * g + 1] = " ".join(base + line[:15] * 50)
        texts[3 * g + 2] = " ".join(base[:54] * 50 + base)
    want = plain_classes(texts)
    assert len(set(want.values())) == 12
    got = {r["doc_id"]: r["class_id"] for r in minhash.near_duplicate_classes(docs(spark, [(i, t, "s") for i, t in texts.items()]), Scratch(spark, "t")).collect()}
    assert got == want


def test_signatures_estimate_weighted_likeness():
    rng = np.random.default_rng(1)
    a = {int(x): int(c) for x, c in zip(rng.integers(1, 2**60, 300), rng.integers(1, 5, 300), strict=True)}
    b = dict(list(a.items())[:220]) | {int(x): 1 for x in rng.integers(1, 2**60, 60)}
    w = lambda s: {k: 1 + np.log(c) for k, c in s.items()}
    wa, wb = w(a), w(b)
    shared = set(wa) & set(wb)
    exact = sum(1 / sum(max(wa.get(y, 0) / wa[x], wb.get(y, 0) / wb[x]) for y in set(wa) | set(wb)) for x in shared)
    est = []
    for shift in range(12):
        mark = lambda s, k=shift: np.array([x ^ (k * 7919) for x in s], np.uint64)
        keys = [mark(a), mark(b)]
        sig = minhash.signatures(np.repeat([0, 1], [len(a), len(b)]), np.concatenate(keys), minhash.weights(np.array([*a.values(), *b.values()]), True), 2)
        est.append((sig[0] == sig[1]).mean())
    assert np.mean(est) == pytest.approx(exact, abs=0.05)


def test_weighted_classes_against_all_pairs(spark):
    rng = random.Random(14)
    texts = {}
    for g in range(10):
        base = [f"g{g}w{rng.randint(0, 10**6)}" for _ in range(90)]
        for times in (1, 2, 40):  # a passage that weighs more each time
            own = list(base)
            own[rng.randrange(90)] = f"v{rng.randint(0, 10**6)}"
            texts[len(texts)] = " ".join(own + base[: rng.randint(10, 40)] * times)

    def bag(t):
        w = t.split()
        return {k: 1 + np.log(c) for k, c in Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4)).items()}

    def likeness(x, y):
        ids = set(x) | set(y)
        return sum(1 / sum(max(x.get(j, 0) / x[i], y.get(j, 0) / y[i]) for j in ids) for i in set(x) & set(y))

    bags = {i: bag(t) for i, t in texts.items()}
    parts = [(np.array(sorted(hash(k) for k in b)), np.array([v for _, v in sorted((hash(k), v) for k, v in b.items())])) for b in bags.values()]
    up = {i: i for i in texts}

    def root(x):
        return x if up[x] == x else root(up[x])

    links = 0
    for a, b in itertools.combinations(texts, 2):
        if a // 3 == b // 3:
            exact = likeness(bags[a], bags[b])
            assert minhash.probability_jaccard(*parts[a], *parts[b]) == pytest.approx(exact)
            if exact >= 0.8:
                links += 1
                x, y = sorted((root(a), root(b)))
                up[y] = x
    got = {r["doc_id"]: r["class_id"] for r in minhash.near_duplicate_classes(docs(spark, [(i, t, "s") for i, t in texts.items()]), Scratch(spark, "t"), weighted=True).collect()}
    assert links and got == {i: root(i) for i in texts} != plain_classes(texts)


def test_near_duplicates_with_a_large_group(spark):
    """One group of copies holds most rows, so that its leader, buckets and component are hot."""
    rng = random.Random(15)
    base = [f"w{i}" for i in range(70)]
    texts = {0: " ".join(base)}
    for i in range(1, 701):
        own = list(base)
        if i % 3:
            own[rng.randrange(70)] = f"v{i}"
        texts[i] = " ".join(own)
    for i in range(701, 800):
        texts[i] = " ".join(f"u{rng.randint(0, 10**6)}" for _ in range(12))
    got = {r["doc_id"]: r["class_id"] for r in minhash.near_duplicate_classes(docs(spark, [(i, t, "s") for i, t in texts.items()]), Scratch(spark, "t")).collect()}
    assert got == {i: 0 if i <= 700 else i for i in texts}


def test_salted_join(spark):
    from pyspark.sql import functions as F

    left = spark.createDataFrame([(i, 7 if i % 2 else i) for i in range(2000)], "id bigint, k bigint")
    right = spark.createDataFrame([(7, "seven"), (8, "eight"), (9, "nine")], "j bigint, name string")
    hot = hot_keys(left.groupBy("k").count(), "k", "count")
    assert hot == [7]
    for how in ("inner", "left"):
        got = salted_join(left, right, ["k"], ["j"], "k", "j", hot, F.xxhash64("id"), how, 4)
        want = left.join(right, left.k == right.j, how)
        assert got.columns == want.columns and sorted(map(str, got.collect())) == sorted(map(str, want.collect()))


def test_components(spark):
    links = spark.createDataFrame([(i, i + 1) for i in range(50)] + [(100, 101), (101, 100), (7, 7), (200, 60)], "a bigint, b bigint")
    got = {r["node"]: r["comp"] for r in components(links, Scratch(spark, "t")).collect()}
    assert all(got[i] == 0 for i in range(51)) and got[101] == 100 and got[200] == 60


# ---- neighbours


def test_neighbours(spark):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(900, 24))
    x[400:700] = x[400]
    rows = [(int(i), v.tolist(), 0) for i, v in enumerate(x)] + [(1000, None, 0), (1020, [0.0] * 24, 0), (1040, [float("nan")] * 24, 0), (1060, [None] * 24, 0), (1080, [1.0], 0), (1100, [], 0)]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<double>, label int")
    got = defaultdict(list)
    for r in ann.nearest(df, Scratch(spark, "t"), block_rows=300).orderBy("query_id", "rank").collect():
        got[r["query_id"]].append((r["vec_id"], r["score"]))
    assert sorted(got) == list(range(0, 900, 20))
    hit = 0
    for q, found in got.items():
        score = (x * x[q]).sum(axis=1)
        best = sorted((i for i in range(900) if i != q), key=lambda i: (-score[i], i))[:20]
        assert len(found) == 20 and all(s == pytest.approx(score[i], abs=1e-12) for i, s in found)
        assert found == sorted(found, key=lambda y: (-y[1], y[0]))
        hit += len(set(best) & {i for i, _ in found})
    assert hit / (20 * len(got)) >= 0.9
    twice = df.where("vec_id < 100").union(spark.createDataFrame([(0, [-9.0] * 24, 0), (3, x[3].tolist(), 0)], df.schema))
    again = ann.nearest(twice, Scratch(spark, "t")).collect()
    assert len({(r["query_id"], r["rank"]) for r in again}) == len(again) == 5 * 20
    other = spark.createDataFrame([(i, [float(i), 1.0], 0) for i in (2000, 2001, 2020)], df.schema)
    mixed = [r for r in ann.nearest(df.union(other), Scratch(spark, "t")).collect() if r["query_id"] >= 2000]
    assert sorted((r["query_id"], r["rank"], r["vec_id"]) for r in mixed) == [(2000, 1, 2020), (2000, 2, 2001), (2020, 1, 2001), (2020, 2, 2000)]
    few = ann.nearest(df.where("vec_id < 5"), Scratch(spark, "t")).collect()
    assert sorted((r["query_id"], r["rank"]) for r in few) == [(0, r) for r in range(1, 5)]
    assert ann.nearest(df.limit(0), Scratch(spark, "t")).count() == 0


@pytest.mark.parametrize("radius", [0, 3, 9, 20, 37])
def test_probes_meet_every_code_within_the_radius(radius):
    rng = np.random.default_rng(radius)
    centres = rng.normal(size=(20, 40))
    x = centres[rng.integers(0, 20, 1500)] + 0.25 * rng.normal(size=(1500, 40))
    codes = ann.Codes(x[:800])
    assert sum(a + 1 for a in ann.allowed(radius, codes.tables)) == radius + 1 or radius < codes.tables
    block = ann.Block(codes, np.arange(len(x)), x)
    for q in range(0, 1500, 150):
        within = np.bitwise_count(block.words ^ block.words[q]).sum(axis=1) <= radius
        met = block.probe(block.code[q], radius)
        assert (met | ~within).all()


def test_close_neighbours_need_few_probes():
    rng = np.random.default_rng(5)
    centres = rng.normal(size=(60, 64))
    x = centres[rng.integers(0, 60, 8000)] + 0.05 * rng.normal(size=(8000, 64))
    met, within = ann.probed_share(x)
    assert within <= met < 0.2


def test_recall_on_the_given_vectors(spark):
    rows = table(spark, SF, "embeddings").collect()
    ids, x = np.array([r["vec_id"] for r in rows]), np.array([r["embedding"] for r in rows], float)
    got = defaultdict(set)
    for r in ann.nearest(table(spark, SF, "embeddings"), Scratch(spark, "t")).collect():
        got[r["query_id"]].add(r["vec_id"])
    hits = []
    for q in np.flatnonzero(ids % 20 == 0):
        score = x @ x[q]
        score[q] = -np.inf
        hits.append(len(got[ids[q]] & set(ids[np.lexsort((ids, -score))[:20]].tolist())) / 20)
    assert np.mean(hits) >= 0.95


# ---- mixing


def order_of(out):
    """Slots in order with their sources; each slot holds one block of one source."""
    slots = defaultdict(set)
    for r in out:
        slots[r["_slw_slot"]].add((r["source"], r["_slw_block"]))
    assert all(len(x) == 1 for x in slots.values())
    return sorted((s, next(iter(x))[0]) for s, x in slots.items())


def check_deviation(order, weights):
    """Under one block from weight x slots, for every source, until the first one is used up."""
    horizon = min(max(s for s, x in order if x == source) for source in weights) + 1
    done = Counter()
    for t, (slot, source) in enumerate(order[:horizon], 1):
        assert slot == t - 1
        done[source] += 1
        assert all(abs(done[s] - w * t) < 1 for s, w in weights.items()), (t, done)
    return horizon


@pytest.mark.parametrize("shares", [[61, 23, 10, 5, 1], [1] * 40, [300, 300, 300, 60, 20, 20, *[1] * 60], [7]])
def test_period_is_pfair(spark, shares):
    from pyspark.sql import functions as F

    total = sum(shares)
    distinct = sorted(set(shares), reverse=True)
    seen = Counter()
    rows = []
    for i, p in enumerate(shares):
        rows.append((i, p, distinct.index(p), seen[p]))
        seen[p] += 1
    frame = spark.createDataFrame(rows, "stream int, share bigint, class int, member int").withColumn("source", F.col("stream"))
    got = mixing.period(frame, total, 16).collect()
    assert sorted(r["place"] for r in got) == list(range(total))
    done = Counter()
    for r in sorted(got, key=lambda r: r["place"]):
        assert r["nth"] == done[r["stream"]]
        done[r["stream"]] += 1
        assert all(abs(done[i] - p * (r["place"] + 1) / total) < 1 for i, p in enumerate(shares))


def test_mixing_keeps_all_rows_and_weights(spark):
    rows = [(i, "t", f"s{i % 3}" if i % 2 else None) for i in range(900)] + [(1, "t", "s1")]
    out = mixing.mix(docs(spark, rows), Scratch(spark, "t"), block=4).select("doc_id", "source", "_slw_stream", "_slw_block", "_slw_slot", "_slw_in_block").collect()
    assert Counter(r["doc_id"] for r in out) == Counter(i for i, _, _ in rows)
    by = defaultdict(list)
    for r in out:
        by[r["_slw_stream"]].append((r["_slw_block"], r["_slw_in_block"]))
    for v in by.values():
        assert sorted(v) == [(i // 4, i % 4) for i in range(len(v))]
    shares = {r["source"]: r["share"] for r in mixing.stream_shares(docs(spark, rows), Scratch(spark, "t")).collect()}
    check_deviation(order_of(out), {s: p / sum(shares.values()) for s, p in shares.items()})
    assert mixing.mix(docs(spark, []), Scratch(spark, "t")).count() == 0


def test_three_equal_sources_keep_thirds(spark):
    rows = [(i, "t", f"s{i % 3}") for i in range(9000)]
    out = mixing.mix(docs(spark, rows), Scratch(spark, "t"), block=2).select("source", "_slw_block", "_slw_slot").collect()
    assert check_deviation(order_of(out), {f"s{i}": 1 / 3 for i in range(3)}) > 4000


def test_given_weights(spark):
    rows = [(i, "t", f"s{i % 3}" if i % 2 else None) for i in range(900)]
    shares = mixing.stream_shares(docs(spark, rows), Scratch(spark, "t"), weights={"s0": 3.0, "s1": 1.0, "s2": 1.0, "": 5.0}).collect()
    assert {r["source"]: r["share"] for r in shares} == {"s0": 3, "s1": 1, "s2": 1, None: 5}
    # weights of 0, weights for absent sources, and no weight that fits: those sources follow after all others
    for weights, first in (({"s0": 2.0, "s1": 0.0, "other": 9.0}, {"s0"}), ({"nowhere": 1.0}, set()), ({"s0": 0.7, "s2": 0.1}, {"s0", "s2"})):
        out = mixing.mix(docs(spark, rows), Scratch(spark, "t"), weights, block=4).select("doc_id", "source", "_slw_block", "_slw_slot").collect()
        order = order_of(out)
        assert sorted(r["doc_id"] for r in out) == list(range(900))
        late = [s for s, x in order if x not in first]
        assert not first or min(late) > max(s for s, x in order if x in first)
        assert late == list(range(late[0], late[0] + len(late)))
    check_deviation(order, {"s0": 0.875, "s2": 0.125})


def test_mixing_keeps_large_sources_beside_many_small_ones(spark):
    from pyspark.sql import functions as F

    large = spark.range(20 * 3_000).select(F.col("id").alias("doc_id"), F.concat(F.lit("large"), (F.col("id") % 20).cast("string")).alias("source"))
    small = spark.range(400).select((F.col("id") + 1_000_000).alias("doc_id"), F.concat(F.lit("small"), F.col("id").cast("string")).alias("source"))
    rows = large.union(small)
    shares = {r["source"]: r["share"] for r in mixing.stream_shares(rows, Scratch(spark, "t")).collect()}
    assert len(shares) == 420 and min(shares.values()) >= 1
    out = mixing.mix(rows, Scratch(spark, "t")).select("source", "_slw_block", "_slw_slot").collect()
    assert Counter(r["source"] for r in out) == {r["source"]: r["count"] for r in rows.groupBy("source").count().collect()}
    check_deviation(order_of(out), {s: p / sum(shares.values()) for s, p in shares.items()})


# ---- sharding


def one_by_one(sizes, counts, shards):
    """Each group on its own to the least loaded shard."""
    load, out = [0] * shards, []
    for size, n in zip(sizes, counts, strict=True):
        row = [0] * shards
        for _ in range(n):
            s = min(range(shards), key=lambda s: (load[s], s))
            row[s] += 1
            load[s] += size
        out.append(row)
    return out


def test_longest_first():
    rng = random.Random(6)
    for _ in range(60):
        sizes = sorted(rng.sample(range(1, 60), rng.randint(1, 12)), reverse=True)
        counts = [rng.choice([1, 2, 9, 40, 333]) for _ in sizes]
        shards = rng.randint(1, 9)
        assert sharding.longest_first(np.array(sizes), np.array(counts), shards).tolist() == one_by_one(sizes, counts, shards)


def test_shards(spark):
    rng = random.Random(8)
    rows = [(i, rng.choice([None, "", "same text " * 40, f"text {i} " * rng.randint(1, 30)]), "s") for i in range(1200)]
    out = sharding.shard_layout(docs(spark, rows), Scratch(spark, "t"), buckets=16).collect()
    assert len(out) == len(rows)
    load, slots, where = Counter(), defaultdict(list), defaultdict(set)
    text = {i: t or "" for i, t, _ in rows}
    for r in out:
        assert r["size"] == len(text[r["doc_id"]].encode()) + 1 and r["law"] == "bytes" and r["grown_shard"] is None
        load[r["shard"]] += r["size"]
        slots[r["shard"]].append(r["slot"])
        where[text[r["doc_id"]]].add(r["shard"])
    assert all(len(s) == 1 for s in where.values()) and all(sorted(s) == list(range(len(s))) for s in slots.values())
    unique_rows = [(i, f"text {i} " * rng.randint(1, 30), "s") for i in range(3000)]
    unique = docs(spark, unique_rows)
    sums = [r["n"] for r in sharding.assign_shards(unique, Scratch(spark, "t"), 8).groupBy("shard").agg({"size": "sum"}).withColumnRenamed("sum(size)", "n").collect()]
    own = Counter(len(t.encode()) + 1 for _, t, _ in unique_rows)
    by_size = sorted(own, reverse=True)
    want = np.array(by_size) @ np.array(one_by_one(by_size, [own[s] for s in by_size], 8))
    assert sorted(sums) == sorted(want.tolist())
    assert sharding.shard_layout(docs(spark, []), Scratch(spark, "t")).count() == 0


# ---- all together


def test_pipeline_stages(spark):
    frame = table(spark, SF, "documents")
    columns, before = frame.columns, {r["doc_id"] for r in frame.select("doc_id").collect()}
    scratch = Scratch(spark, "t")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        frame = scratch.settle(stage(spark, frame, SF), name)
        assert frame.columns == columns
        after = {r["doc_id"] for r in frame.select("doc_id").collect()}
        assert after <= before and (after == before if name == "mixing" else after < before)
        before = after
    last = corpus_pipeline.STAGES[-1][1](spark, frame, SF)
    assert {r["doc_id"] for r in last.collect()} == before
    labels = {r["doc_id"]: r["quality"] for r in table(spark, SF, "labels").collect()}
    assert sum(labels.get(i) == 0 for i in before) <= 3


def test_mixed_order_reaches_the_shards(spark, monkeypatch):
    monkeypatch.setattr(corpus_pipeline, "STAGES", corpus_pipeline.STAGES[-2:])
    sources = [r["source"] for r in table(spark, SF, "documents").select("source").distinct().collect() if r["source"]]
    results = []
    for first in (min(sources), max(sources)):
        weights = {s: 50.0 if s == first else 1.0 for s in sources}
        monkeypatch.setattr(corpus_pipeline, "WEIGHTS", weights)
        got = {r["doc_id"]: (r["shard"], r["slot"]) for r in corpus_pipeline.run(spark, SF).collect()}
        mixed = mixing.mix(table(spark, SF, "documents"), Scratch(spark, "t"), weights).select("doc_id", "_slw_slot", "_slw_in_block").collect()
        by = defaultdict(list)
        for r in sorted(mixed, key=lambda r: (r["_slw_slot"], r["_slw_in_block"])):
            by[got[r["doc_id"]][0]].append(got[r["doc_id"]][1])
        assert all(v == list(range(len(v))) for v in by.values()) and len(by) == 8
        results.append(got)
    assert {i: s for i, (s, _) in results[0].items()} == {i: s for i, (s, _) in results[1].items()} and results[0] != results[1]


def test_stages_with_clashing_columns_and_nulls(spark):
    """Names that the operators use inside, nulls everywhere, and repeated rows."""
    from pyspark.sql import functions as F

    frame = table(spark, SF, "documents").where("doc_id < 60")
    for name in ("score", "_id", "slot", "share", "nth", "node", "size", "shard", "stream", "removed", "part", "_b", "_n"):
        frame = frame.withColumn(name, F.lit("clash"))
    odd = spark.createDataFrame([(None, None, None, None, None), (7001, None, None, None, None), (7002, "", "en", None, 0), (7002, "", "en", None, 0)], DOCS)
    frame = frame.unionByName(odd, allowMissingColumns=True)
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, frame, SF)
        assert out.columns == frame.columns and out.count() > 20, name
    assert corpus_pipeline.STAGES[-1][1](spark, frame, SF).count() == frame.count()
    nothing = frame.limit(0)
    for name, stage in corpus_pipeline.STAGES:
        assert stage(spark, nothing, SF).count() == 0, name


def test_registered():
    assert sorted(registry.QUERIES) == sorted(["pipeline", *(n for n in registry.QUERIES if n.startswith("op"))]) and len(registry.QUERIES) == 11
