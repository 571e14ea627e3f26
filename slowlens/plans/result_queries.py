"""Pattern language, redundancy, interaction, baselines, accuracy measures and the toy example as registered queries."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from slowlens.functions.measures import get, scored
from slowlens.operators import counting, encode, lattice, redundancy, selectors, stats
from slowlens.operators.dataset import SubgroupDataset
from slowlens.operators.selectors import Selector
from slowlens.plans import oracle, search
from slowlens.plans.interactive import Exploration
from slowlens.plans.registry import query
from slowlens.plans.search_queries import E_CUTS, E_NOMINAL, E_SEL, SLOW, chosen, depth_one, events_session, kept
from slowlens.sources import datasets

EV = oracle.EVENTS_PLAIN


def events(spark: SparkSession, d: str, target: str = "time_s") -> SubgroupDataset:
    return datasets.events_set(spark, d, target)


def supports(ds: SubgroupDataset, chosen_selectors: list[Selector]) -> DataFrame:
    """label and support of each selector that holds anywhere."""
    rows = encode.encode(ds, chosen_selectors).select(F.explode("sels").alias("s"))
    return rows.groupBy("s").agg(F.count("*").alias("support")).select(F.element_at(F.lit([x.label for x in chosen_selectors]), F.col("s") + 1).alias("selector"), "support")


def _support_sql(ds: str, sel: str) -> str:
    return f"WITH ds AS ({ds}), sel AS ({sel}) SELECT label AS selector, CAST(count(*) AS BIGINT) AS support FROM sel GROUP BY label"


def _with_t(sql: str, t: str = "0") -> str:
    return f"SELECT *, {t} AS t FROM ({sql})"


# ---- pattern language

query("l_numeric_selectors", _support_sql(EV, oracle.selectors((), {"k": [25, 50, 75], "hour": [12]})))(lambda spark, d: supports(events(spark, d), [*selectors.numeric("k", [25, 50, 75]), *selectors.numeric("hour", [12])]))
query("l_interval_selectors", f"SELECT 'k in [' || lo || ',' || hi || ')' AS selector, CAST(count(*) AS BIGINT) AS support FROM ({EV}) JOIN (VALUES (0, 25), (25, 50), (50, 75)) v(lo, hi) ON k >= lo AND k < hi GROUP BY 1")(lambda spark, d: supports(events(spark, d), selectors.numeric("k", [0, 25, 50, 75], "interval")))
query("l_equality_selectors", f"SELECT 'hour=' || hour AS selector, CAST(count(*) AS BIGINT) AS support FROM ({EV}) GROUP BY 1")(lambda spark, d: supports(events(spark, d), selectors.equals("hour", list(range(24)))))
query("l_nominal_selectors", f"SELECT selector, support FROM ({_support_sql(EV, oracle.selectors(('event_type', 'n_name')))})")(lambda spark, d: supports(events(spark, d), selectors.nominal(events(spark, d), ["event_type", "n_name"])))
query("l_boolean_selectors", f"SELECT 'busy=' || busy AS selector, CAST(count(*) AS BIGINT) AS support FROM ({oracle.EVENTS}) GROUP BY 1")(lambda spark, d: supports(SubgroupDataset(datasets.events_frame(spark, d), boolean=("busy",)), selectors.boolean("busy")))
query("l_ordinal_selectors", "SELECT 'a_error>=' || v AS selector, CAST(count(*) AS BIGINT) AS support FROM (SELECT CASE a_error WHEN 'Info' THEN 1 WHEN 'Alarm' THEN 2 WHEN 'Critical' THEN 3 WHEN 'Blocking' THEN 4 END AS lv FROM (" + oracle.EVENTS + ")) JOIN (VALUES ('Alarm', 2), ('Critical', 3), ('Blocking', 4)) x(v, n) ON lv >= n GROUP BY 1")(lambda spark, d: supports(datasets.events_set(spark, d, context=True), selectors.ordinal("a_error", datasets.LEVELS, True)))
query("l_token_selectors", f"SELECT token || '>0' AS selector, CAST(count(DISTINCT oid) AS BIGINT) AS support FROM ({oracle.ORDER_TOKENS}) GROUP BY token HAVING count(DISTINCT oid) >= 100")(lambda spark, d: supports(datasets.orders_set(spark, d), selectors.tokens(datasets.orders_set(spark, d), 100)))
query("l_token_counts", f"SELECT CASE c WHEN 1 THEN token || '>0' ELSE token || '>=' || c END AS selector, CAST(count(*) AS BIGINT) AS support FROM (SELECT oid, token, count(*) AS n FROM ({oracle.PAGE_TOKENS}) GROUP BY 1, 2) JOIN (VALUES (1), (3)) v(c) ON n >= c GROUP BY 1")(lambda spark, d: supports(datasets.pages_set(spark, d), selectors.tokens(datasets.pages_set(spark, d), 1, (1, 3))))


def cut_rows(spark: SparkSession, ds: SubgroupDataset, attrs: list[str], policy: str, bins: int = 5) -> DataFrame:
    found = selectors.cuts(ds, attrs, policy, bins)
    return spark.createDataFrame([(a, round(float(c), 6)) for a, cs in found.items() for c in cs], "attr string, cut double")


query("l_cuts_quantile", " UNION ALL ".join(f"SELECT DISTINCT '{a}' AS attr, round(unnest(quantile_cont(CAST({a} AS DOUBLE), [0.2, 0.4, 0.6, 0.8])), 6) AS cut FROM ({EV})" for a in ("k", "c_acctbal")))(lambda spark, d: cut_rows(spark, events(spark, d), ["k", "c_acctbal"], "quantile"))
query("l_cuts_width", " UNION ALL ".join(f"SELECT '{a}' AS attr, round(lo + (hi - lo) * i / 5, 6) AS cut FROM (SELECT CAST(min({a}) AS DOUBLE) AS lo, CAST(max({a}) AS DOUBLE) AS hi FROM ({EV})), (SELECT unnest([1, 2, 3, 4]) AS i)" for a in ("k", "c_acctbal")))(lambda spark, d: cut_rows(spark, events(spark, d), ["k", "c_acctbal"], "width"))
query("l_cuts_distinct", f"SELECT DISTINCT 'hour' AS attr, CAST(hour AS DOUBLE) AS cut FROM ({EV})")(lambda spark, d: cut_rows(spark, events(spark, d), ["hour"], "distinct"))

PAIR = (Selector("event_type", "=", "error"), Selector("k", "<", 20))
query("l_extent", f"SELECT oid FROM ({EV}) WHERE event_type = 'error' AND k < 20")(lambda spark, d: lattice.extent(events(spark, d), PAIR))


@query("l_refine", f"WITH ds AS ({EV}), sel AS (SELECT DISTINCT label, key, blocks FROM ({E_SEL})) SELECT a.label || ' & ' || b.label AS description FROM sel a JOIN sel b ON a.label < b.label AND NOT list_contains(a.blocks, b.key)")
def l_refine(spark: SparkSession, d: str) -> DataFrame:
    all_selectors = chosen(events(spark, d), E_NOMINAL, E_CUTS)
    pairs = lattice.refine([(s,) for s in all_selectors], all_selectors)
    return spark.createDataFrame([(lattice.describe(p),) for p in pairs], "description string")


@query("l_generalisations", f"SELECT description, CAST(count(oid) AS BIGINT) AS size FROM (VALUES ('', false, false, false), ('event_type=error', true, false, false), ('k<20', false, true, false), ('hour>=12', false, false, true), ('event_type=error & k<20', true, true, false), ('event_type=error & hour>=12', true, false, true), ('hour>=12 & k<20', false, true, true)) v(description, a, b, c) LEFT JOIN ({EV}) ON (NOT a OR event_type = 'error') AND (NOT b OR k < 20) AND (NOT c OR hour >= 12) GROUP BY description")
def l_generalisations(spark: SparkSession, d: str) -> DataFrame:
    """Every generalisation of a pattern, with its size on events, all from one scan."""
    found = lattice.generalisations((*PAIR, Selector("hour", ">=", 12)))
    sizes = events(spark, d).rows().agg(*[F.count_if(lattice.to_column(p)).alias(f"_{i}") for i, p in enumerate(found)])
    return sizes.select(F.inline(F.array(*[F.struct(F.lit(lattice.describe(p)).alias("description"), F.col(f"_{i}").alias("size")) for i, p in enumerate(found)])))


TWINS = {"k": [20, 40], "hour": [6]}


@query("l_distinct_extents", f"WITH ds AS (SELECT *, k * 2 AS k2 FROM ({EV})), sel AS ({oracle.selectors((), {'k': [20, 40], 'k2': [40, 80]})}), p AS (SELECT label, list(oid ORDER BY oid) AS ext FROM sel GROUP BY label) SELECT min(label) AS description, CAST(len(any_value(ext)) AS BIGINT) AS size FROM p GROUP BY ext")
def l_distinct_extents(spark: SparkSession, d: str) -> DataFrame:
    df = datasets.events_frame(spark, d, False).withColumn("k2", F.col("k") * 2)
    ds = SubgroupDataset(df, numeric=("k", "k2"))
    s = search.Session(ds, [*selectors.numeric("k", [20, 40]), *selectors.numeric("k2", [40, 80])], False)
    return kept(s, lattice.distinct_extents(s.candidates([()], get("support"), 1, False)).select("description", F.col("n").alias("size")))


@query("l_topk_ties", f"WITH c AS (SELECT hour, CAST(count(*) AS BIGINT) // 50 AS score FROM ({EV}) GROUP BY hour) SELECT CAST(rk AS INTEGER) AS rank, hour, score FROM (SELECT *, rank() OVER (ORDER BY score DESC) AS rk FROM c) WHERE rk <= 3")
def l_topk_ties(spark: SparkSession, d: str) -> DataFrame:
    c = events(spark, d).rows().groupBy("hour").agg(F.floor(F.count("*") / 50).alias("score"))
    return search._top_with_ties(c, 3).withColumn("rank", F.rank().over(Window.orderBy(F.desc("score")))).where("rank <= 3").select("rank", "hour", "score")


@query("l_space_size", f"WITH ds AS ({EV}), sel AS (SELECT DISTINCT label, key, blocks FROM ({E_SEL})) SELECT CAST(1 + (SELECT count(*) FROM sel) + (SELECT count(*) FROM sel a JOIN sel b ON a.label < b.label AND NOT list_contains(a.blocks, b.key)) AS BIGINT) AS patterns")
def l_space_size(spark: SparkSession, d: str) -> DataFrame:
    n = lattice.space_size(chosen(events(spark, d), E_NOMINAL, E_CUTS), 2)
    return spark.createDataFrame([(n,)], "patterns bigint")


@query("l_encode", f"WITH ds AS ({EV}), sel AS ({E_SEL}) SELECT oid, array_to_string(list_sort(list(label)), ', ') AS selectors FROM sel GROUP BY oid")
def l_encode(spark: SparkSession, d: str) -> DataFrame:
    ds = events(spark, d)
    all_selectors = chosen(ds, E_NOMINAL, E_CUTS)
    names = F.lit([s.label for s in all_selectors])
    return encode.encode(ds, all_selectors).select("oid", F.array_join(F.array_sort(F.transform("sels", lambda i: F.element_at(names, i + 1))), ", ").alias("selectors"))


@query("l_prefix_counts", f"WITH ds AS ({EV}), sel AS ({oracle.selectors((), {'c_acctbal': [0, 2500, 5000, 7500]})}) SELECT label AS selector, CAST(count(*) AS BIGINT) AS n, round(CAST(sum(t) AS DOUBLE), 4) AS s1 FROM sel GROUP BY label")
def l_prefix_counts(spark: SparkSession, d: str) -> DataFrame:
    """All one-sided bounds of an attribute from one bin per row."""
    out = counting.prefix_counts(events(spark, d), "c_acctbal", [0, 2500, 5000, 7500])
    return out.select(F.concat("attr", "op", F.col("cut").cast("int").cast("string")).alias("selector"), "n", F.round(F.col("s1").cast("double"), 4).alias("s1"))


@query("l_bitmap_sizes", f"SELECT 'event_type=error & k<20' AS description, CAST(count(*) AS BIGINT) AS size FROM ({EV}) WHERE event_type = 'error' AND k < 20")
def l_bitmap_sizes(spark: SparkSession, d: str) -> DataFrame:
    store = counting.bitmap_store(encode.encode(events(spark, d), list(PAIR)))
    want = spark.createDataFrame([(0, 0), (0, 1)], "pattern_id int, sel int")
    return counting.bitmap_sizes(store, want).select(F.lit(lattice.describe(PAIR)).alias("description"), "size")


# ---- a fixed result to thin: ten patterns over events

RESULT = [
    (Selector("event_type", "=", "error"),), (Selector("event_type", "=", "click"),), (Selector("k", "<", 20),), (Selector("k", "<", 40),), (Selector("k", ">=", 40),),
    (Selector("event_type", "=", "error"), Selector("k", "<", 20)), (Selector("event_type", "=", "error"), Selector("k", "<", 40)), (Selector("hour", "<", 12),), (Selector("hour", "<", 6),), (Selector("hour", "<", 12), Selector("k", "<", 40)),
]
_CONDITIONS = {lattice.describe(p): " AND ".join(f"{s.attr} {s.op} {repr(s.value)}" for s in p) for p in RESULT}
_MEMBERS = " UNION ALL ".join(f"SELECT '{n}' AS p, oid, t FROM ds WHERE {c}" for n, c in _CONDITIONS.items())
_BASE = f"ds AS MATERIALIZED ({EV}), m AS MATERIALIZED ({_MEMBERS}), s AS (SELECT p, count(*) AS n, round(CAST(count(*) AS DOUBLE) / (SELECT count(*) FROM ds) * (CAST(sum(t) AS DOUBLE) / count(*) - (SELECT CAST(sum(t) AS DOUBLE) / count(*) FROM ds)), 9) AS score FROM m GROUP BY p), j AS MATERIALIZED (SELECT a.p AS p, b.p AS q, count(*) FILTER (WHERE x.oid IS NOT NULL) AS shared, a.n + b.n AS tot FROM s a JOIN s b ON a.p < b.p LEFT JOIN (SELECT u.p AS p, v.p AS q, u.oid FROM m u JOIN m v ON u.oid = v.oid AND u.p < v.p) x ON x.p = a.p AND x.q = b.p GROUP BY a.p, b.p, a.n, b.n), jj AS (SELECT p, q, CAST(shared AS BIGINT) AS shared, CAST(shared AS DOUBLE) / (tot - shared) AS jac FROM j)"


def fixed_result(spark: SparkSession, d: str) -> tuple[SubgroupDataset, list[float], list[str]]:
    """The data, scores (WRAcc) and descriptions of RESULT."""
    ds = events(spark, d)
    g = ds.norms(False)
    m = stats.matches(ds, RESULT).select(F.explode("_m").alias("p"), "t").groupBy("p").agg(F.count("*").alias("n"), F.sum("t").alias("s1"))
    score = {r["p"]: r["score"] for r in m.withColumn("score", scored("wracc", g)).select("p", "score").collect()}
    return ds, [score.get(i, 0.0) for i in range(len(RESULT))], [lattice.describe(p) for p in RESULT]


query("r_jaccard", f"WITH {_BASE} SELECT p, q, shared, round(jac, 6) AS jaccard FROM jj")(lambda spark, d: redundancy.named(redundancy.jaccard(events(spark, d), RESULT), RESULT))


def _greedy_sql(threshold: float, head: str = "") -> str:
    """The rule unrolled: a pattern stays if no better kept one overlaps it by more than the threshold."""
    n = len(RESULT)
    steps = ["o AS (SELECT p, row_number() OVER (ORDER BY score DESC, p) AS i FROM s)", "w AS (SELECT p, q, jac FROM jj UNION ALL SELECT q, p, jac FROM jj)", "g1 AS (SELECT p FROM o WHERE i = 1)"]
    for i in range(2, n + 1):
        steps.append(f"g{i} AS (SELECT p FROM g{i - 1} UNION ALL SELECT o.p FROM o WHERE i = {i} AND NOT EXISTS (SELECT 1 FROM w JOIN g{i - 1} k ON w.q = k.p WHERE w.p = o.p AND w.jac > {threshold}))")
    return f"WITH {_BASE}, {', '.join(steps)} {head or f'SELECT g.p AS description, score FROM g{n} g JOIN s ON g.p = s.p'}"


def _greedy(threshold: float):
    def run(spark: SparkSession, d: str) -> DataFrame:
        ds, scores, names = fixed_result(spark, d)
        sim = redundancy.matrix(redundancy.jaccard(ds, RESULT), len(RESULT))
        return spark.createDataFrame([(names[i], scores[i]) for i in redundancy.greedy(scores, sim, threshold, names)], "description string, score double")

    return run


for _t in (30, 50, 70):
    query(f"r_greedy_{_t}", _greedy_sql(_t / 100))(_greedy(_t / 100))
    query(f"b_reduced_overlap_{_t}", _greedy_sql(_t / 100, f"SELECT round(coalesce(avg(jac), 0), 6) AS mean_overlap, (SELECT CAST(count(*) AS INTEGER) FROM g{len(RESULT)}) AS kept FROM jj WHERE p IN (SELECT p FROM g{len(RESULT)}) AND q IN (SELECT p FROM g{len(RESULT)})"))(lambda spark, d, t=_t / 100: reduced_overlap(spark, d, t))


def reduced_overlap(spark: SparkSession, d: str, threshold: float) -> DataFrame:
    ds, scores, names = fixed_result(spark, d)
    sim = redundancy.matrix(redundancy.jaccard(ds, RESULT), len(RESULT))
    kept = redundancy.greedy(scores, sim, threshold, names)
    pairs = [sim[i, j] for a, i in enumerate(kept) for j in kept[a + 1 :]]
    return spark.createDataFrame([(round(float(sum(pairs) / len(pairs)) if pairs else 0.0, 6), len(kept))], "mean_overlap double, kept int")


@query("r_threshold_sweep", " UNION ALL ".join(f"SELECT {t}::DOUBLE AS threshold, CAST(kept AS INTEGER) AS kept FROM ({_greedy_sql(t, f'SELECT count(*) AS kept FROM g{len(RESULT)}')})" for t in (0.1, 0.3, 0.5, 0.7, 0.9)))
def r_threshold_sweep(spark: SparkSession, d: str) -> DataFrame:
    ds, scores, names = fixed_result(spark, d)
    sim = redundancy.matrix(redundancy.jaccard(ds, RESULT), len(RESULT))
    return spark.createDataFrame(redundancy.sweep(scores, sim, [0.1, 0.3, 0.5, 0.7, 0.9], names), "threshold double, kept int")


_HEIGHTS = "(SELECT DISTINCT round(1 - jac, 6) AS h FROM jj)"


# single linkage merges at a height as many clusters as its connected parts become fewer there
@query("r_dendrogram_single", f"""WITH RECURSIVE {_BASE}, w AS (SELECT p, q, round(1 - jac, 6) AS dist FROM jj UNION ALL SELECT q, p, round(1 - jac, 6) FROM jj), hs AS {_HEIGHTS},
r(h, a, b) AS (SELECT h, p, p FROM hs, s UNION SELECT r.h, r.a, w.q FROM r JOIN w ON r.b = w.p AND w.dist <= r.h),
c AS (SELECT h, count(DISTINCT cl) AS parts FROM (SELECT h, a, min(b) AS cl FROM r GROUP BY h, a) GROUP BY h),
x AS (SELECT h, coalesce(lag(parts) OVER (ORDER BY h), (SELECT count(*) FROM s)) - parts AS merges FROM c)
SELECT h AS height, CAST(merges AS INTEGER) AS merges FROM x WHERE merges > 0""")
def r_dendrogram_single(spark: SparkSession, d: str) -> DataFrame:
    return _dendrogram(spark, d, "single").groupBy("height").agg(F.count("*").cast("int").alias("merges"))


def _dendrogram(spark: SparkSession, d: str, linkage: str) -> DataFrame:
    ds, _, _ = fixed_result(spark, d)
    merges = redundancy.dendrogram(redundancy.matrix(redundancy.jaccard(ds, RESULT), len(RESULT)), linkage)
    return spark.createDataFrame([(i, a, b, round(h, 6), n) for i, (a, b, h, n) in enumerate(merges)], "step int, left int, right int, height double, size int")


query("r_dendrogram_average")(lambda spark, d: _dendrogram(spark, d, "average"))
query("r_dendrogram_complete")(lambda spark, d: _dendrogram(spark, d, "complete"))


@query("r_cut_single", f"WITH RECURSIVE {_BASE}, w AS (SELECT p, q FROM jj WHERE 1 - jac <= 0.6 UNION ALL SELECT q, p FROM jj WHERE 1 - jac <= 0.6), r(a, b) AS (SELECT p, p FROM s UNION SELECT r.a, w.q FROM r JOIN w ON r.b = w.p), c AS (SELECT a AS p, min(b) AS cl FROM r GROUP BY a) SELECT p AS description, CAST(n AS INTEGER) AS members FROM (SELECT s.p, count(*) OVER (PARTITION BY cl) AS n, row_number() OVER (PARTITION BY cl ORDER BY score DESC, s.p) AS i FROM c JOIN s ON c.p = s.p) WHERE i = 1")
def r_cut_single(spark: SparkSession, d: str) -> DataFrame:
    """The best pattern of each single-linkage cluster at height 0.6."""
    ds, scores, names = fixed_result(spark, d)
    clusters = redundancy.cut(redundancy.dendrogram(redundancy.matrix(redundancy.jaccard(ds, RESULT), len(RESULT)), "single"), len(RESULT), height=0.6)
    return spark.createDataFrame([(names[i], clusters.count(clusters[i])) for i in redundancy.representatives(clusters, scores, names)], "description string, members int")


query("b_raw_topk_overlap", f"WITH {_BASE} SELECT round(avg(jac), 6) AS mean_overlap FROM jj")(lambda spark, d: redundancy.jaccard(events(spark, d), RESULT).agg(F.round(F.avg("jaccard"), 6).alias("mean_overlap")))
query("r_minhash")(lambda spark, d: redundancy.minhash(events(spark, d), RESULT))


@query("r_weighted_cover")
def r_weighted_cover(spark: SparkSession, d: str) -> DataFrame:
    ds, scores, names = fixed_result(spark, d)
    return spark.createDataFrame([(i, names[x]) for i, x in enumerate(redundancy.weighted_cover(ds, RESULT, scores, 5))], "place int, description string")


# ---- interaction


def exploration(spark: SparkSession, d: str) -> Exploration:
    ds = events(spark, d)
    return Exploration(ds, chosen(ds, E_NOMINAL, E_CUTS))


query("i_filter", f"SELECT oid, t FROM ({EV}) WHERE event_type = 'error' AND k >= 50")(lambda spark, d: exploration(spark, d).where("event_type = 'error' and k >= 50").ds.rows().select("oid", "t"))
query("i_brush", f"SELECT oid, t FROM ({EV}) WHERE time_s BETWEEN 20 AND 80 AND k BETWEEN 10 AND 60")(lambda spark, d: exploration(spark, d).brush("time_s", "k", (20, 80), (10, 60)).ds.rows().select("oid", "t"))
query("i_painted_target", f"SELECT oid, CASE WHEN time_s BETWEEN 60 AND 80 AND k BETWEEN 10 AND 30 THEN 1 ELSE 0 END AS t FROM ({EV}) WHERE time_s BETWEEN 20 AND 80 AND k BETWEEN 10 AND 60")(lambda spark, d: exploration(spark, d).brush("time_s", "k", (20, 80), (10, 60)).paint_target("time_s", "k", (60, 80), (10, 30)).ds.rows().select("oid", "t"))
query("i_attr_target", f"SELECT oid, c_acctbal AS t FROM ({EV})")(lambda spark, d: exploration(spark, d).target("c_acctbal").ds.rows().select("oid", "t"))
query("i_mine", oracle.search(f"SELECT * FROM ({EV}) WHERE k >= 10", E_SEL, "mean_test", 5, 2, 20))(lambda spark, d: exploration(spark, d).where("k >= 10").mine("mean_test", "beam", 5, 2, width=20).results())


@query("i_report", f"WITH {_BASE} SELECT p AS description, CAST(count(*) AS BIGINT) AS size, round(CAST(sum(t) AS DOUBLE) / count(*), 6) AS mean, round(stddev_pop(CAST(t AS DOUBLE)), 6) AS std, round(median(CAST(t AS DOUBLE)), 6) AS median FROM m GROUP BY p")
def i_report(spark: SparkSession, d: str) -> DataFrame:
    return stats.describe_patterns(events(spark, d), RESULT)


query("i_scatter_bins", f"SELECT CAST(CASE WHEN time_s >= 200 THEN 11 ELSE floor(time_s / 20) + 1 END AS INTEGER) AS x_bin, CAST(CASE WHEN k >= 100 THEN 11 ELSE floor(k / 10.0) + 1 END AS INTEGER) AS y_bin, CAST(count(*) AS BIGINT) AS rows FROM ({EV}) GROUP BY 1, 2")(lambda spark, d: exploration(spark, d).points("time_s", "k", (0, 200), (0, 100), 10))
query("i_density", f"WITH b AS (SELECT CAST(CASE WHEN t >= 200 THEN 11 ELSE floor(t / 20) + 1 END AS INTEGER) AS bin, event_type = 'error' AND k < 20 AS inside FROM ({EV})) SELECT bin, round(CAST(count(*) AS DOUBLE) / (SELECT count(*) FROM b), 6) AS overall, round(CAST(count(*) FILTER (WHERE inside) AS DOUBLE) / (SELECT count(*) FROM b WHERE inside), 6) AS subgroup FROM b GROUP BY bin")(lambda spark, d: stats.density(events(spark, d), PAIR, 0, 200, 10))
query("i_token_usage", f"WITH t AS (SELECT DISTINCT oid, token FROM ({oracle.ORDER_TOKENS})) SELECT token, CAST(count(*) AS BIGINT) AS rows FROM t WHERE token LIKE 'TYPE_%' AND oid IN (SELECT oid FROM t WHERE token = 'BRAND_Brand#12') GROUP BY token")(lambda spark, d: stats.token_usage(datasets.orders_set(spark, d), (Selector("BRAND_Brand#12", "token", "BRAND_Brand#12", "tokens"),), "TYPE_"))
query("w_case_study", f"WITH t AS (SELECT DISTINCT oid, token FROM ({oracle.ORDER_TOKENS})) SELECT token, CAST(count(*) AS BIGINT) AS rows FROM t WHERE token LIKE 'TYPE_%' AND oid IN (SELECT oid FROM t WHERE token = 'BRAND_Brand#3') GROUP BY token")(lambda spark, d: stats.token_usage(datasets.orders_set(spark, d), (Selector("BRAND_Brand#3", "token", "BRAND_Brand#3", "tokens"),), "TYPE_"))


@query("i_drill", f"WITH ds AS MATERIALIZED ({EV}), g AS ({oracle._NORMS}), sel AS MATERIALIZED ({E_SEL}), c AS (SELECT CASE WHEN label < 'event_type=error' THEN label || ' & event_type=error' ELSE 'event_type=error & ' || label END AS description, {oracle._STATS} FROM sel WHERE key <> 'event_type|point' AND oid IN (SELECT oid FROM ds WHERE event_type = 'error') GROUP BY label), x AS (SELECT *, round({oracle.score('wracc')}, 9) AS score FROM c, g WHERE n >= greatest(5, ceil(tot / 1000))) SELECT CAST(rk AS INTEGER) AS rank, description, 2 AS n_sel, CAST(n AS BIGINT) AS size, round(s1 / n, 6) AS mean, score FROM (SELECT *, row_number() OVER (ORDER BY score DESC, description) AS rk FROM x) WHERE rk <= 5")
def i_drill(spark: SparkSession, d: str) -> DataFrame:
    e = exploration(spark, d)
    return e.drill((next(s for s in e.selectors if s.label == "event_type=error"),), "wracc", 5, 1).results()


@query("i_contributions", f"WITH v AS (SELECT * FROM (VALUES ('all', true, true), ('without event_type=error', false, true), ('without k<20', true, false)) v(selectors, a, b)), d AS ({EV}) SELECT selectors, round(CAST(count(*) AS DOUBLE) / (SELECT count(*) FROM d) * (CAST(sum(t) AS DOUBLE) / count(*) - (SELECT CAST(sum(t) AS DOUBLE) / count(*) FROM d)), 6) AS wracc FROM d, v WHERE (NOT a OR event_type = 'error') AND (NOT b OR k < 20) GROUP BY selectors")
def i_contributions(spark: SparkSession, d: str) -> DataFrame:
    ds = events(spark, d)
    g = ds.norms(False)
    return stats.contributions(ds, PAIR, g.n, g.mean)


query("i_containment", f"WITH {_BASE} SELECT a.p AS inside, b.p AS outside, CAST(any_value(x.n) AS BIGINT) AS size FROM m a JOIN m b ON a.oid = b.oid AND a.p <> b.p JOIN s x ON x.p = a.p GROUP BY a.p, b.p HAVING count(*) = any_value(x.n)")(lambda spark, d: stats.containment(events(spark, d), RESULT))

# ---- baselines and accuracy

query("b_norms", f"SELECT CAST(count(*) AS BIGINT) AS n, round(CAST(sum(t) AS DOUBLE) / count(*), 6) AS mean, round(median(CAST(t AS DOUBLE)), 6) AS median, round(stddev_pop(CAST(t AS DOUBLE)), 6) AS std FROM ({EV})")(lambda spark, d: stats.norms(events(spark, d)))

_TOPK = "SELECT description, score FROM ({0})"
_B10 = oracle.search(EV, E_SEL, "wracc", 10, 2, 5)
_X10 = oracle.search(EV, E_SEL, "wracc", 10, 2, None)


def _both(spark: SparkSession, d: str) -> tuple[search.Found, search.Found]:
    s = events_session(spark, d, median=False)
    out = search.beam(s, "wracc", 10, 2, 5), search.exhaustive(s, "wracc", 10, 2)
    s.close()
    return out


@query("b_beam_vs_exhaustive", f"SELECT 'beam' AS algorithm, CAST(count(*) AS INTEGER) AS found, round(sum(score), 4) AS total FROM ({_B10}) UNION ALL SELECT 'exhaustive', CAST(count(*) AS INTEGER), round(sum(score), 4) FROM ({_X10})")
def b_beam_vs_exhaustive(spark: SparkSession, d: str) -> DataFrame:
    beam, exact = _both(spark, d)
    row = lambda name, f: (name, len(f.rows[:10]), round(sum(r["score"] for r in f.rows[:10]), 4))
    return spark.createDataFrame([row("beam", beam), row("exhaustive", exact)], "algorithm string, found int, total double")


@query("c_beam_recall", f"SELECT round(CAST(count(*) AS DOUBLE) / 10, 6) AS recall FROM (SELECT description FROM ({_B10}) INTERSECT SELECT description FROM ({_X10}))")
def c_beam_recall(spark: SparkSession, d: str) -> DataFrame:
    beam, exact = _both(spark, d)
    hit = {r["description"] for r in beam.rows} & {r["description"] for r in exact.rows[:10]}
    return spark.createDataFrame([(len(hit) / 10,)], "recall double")


def _rank_table(names: dict[str, str], target: str | None):
    """Rank of every depth-1 subgroup by several measures, side by side."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        with_median = any(get(m).needs == "median" for m in names.values())
        s = events_session(spark, d, target or "time_s", median=with_median)
        rows = depth_one(s, with_median).select("description", *[scored(m, s.norms).alias(f"_{c}") for c, m in names.items()])
        return kept(s, rows.select("description", *[F.rank().over(Window.orderBy(F.desc_nulls_last(f"_{c}"))).alias(c) for c in names]))  # selectors only

    ds = f"SELECT * REPLACE ({SLOW} AS t) FROM ({EV})" if target else EV
    cols = ", ".join(f"CAST(rank() OVER (ORDER BY round({oracle.score(m)}, 9) DESC NULLS LAST) AS INTEGER) AS {c}" for c, m in names.items())
    return f"WITH ds AS MATERIALIZED ({ds}), g AS ({oracle._NORMS}), sel AS ({E_SEL}) SELECT label AS description, {cols} FROM (SELECT label, {oracle._STATS} FROM sel GROUP BY label), g", run


for _key, _names, _target in [("b_mean_vs_median", {"by_mean": "mean_test", "by_median": "median_0.5"}, None), ("b_measure_compare", {"by_lift": "lift", "by_wracc": "wracc", "by_binomial": "binomial"}, "slow")]:
    _sql, _f = _rank_table(_names, _target)
    query(_key, _sql)(_f)

_NUM, _BIN = oracle.search(EV, E_SEL, "wracc", 10, 1, None), oracle.search(EV, E_SEL, "wracc", 10, 1, None, target=SLOW)


@query("b_binary_vs_numeric", f"SELECT description, CAST(max(a) AS INTEGER) AS numeric_rank, CAST(max(b) AS INTEGER) AS binary_rank FROM (SELECT description, rank AS a, NULL AS b FROM ({_NUM}) UNION ALL SELECT description, NULL, rank FROM ({_BIN})) GROUP BY description")
def b_binary_vs_numeric(spark: SparkSession, d: str) -> DataFrame:
    ranks: dict[str, list] = {}
    for at, target in enumerate(("time_s", "slow")):
        s = events_session(spark, d, target, median=False)
        for r in search.beam(s, "wracc", 10, 1, 10_000).rows:
            ranks.setdefault(r["description"], [None, None])[at] = r["rank"]
        s.close()
    return spark.createDataFrame([(k, *v) for k, v in ranks.items()], "description string, numeric_rank int, binary_rank int")


@query("b_feature_groups", " UNION ALL ".join(f"SELECT '{n}' AS features, max(score) AS best FROM ({oracle.search(oracle.EVENTS, oracle.selectors(a, c), 'binomial', 10, 2, 20, target='crit')})" for n, a, c in (("statement", ("event_type",), {"k": [25, 50, 75]}), ("with context", ("event_type", "c_mktsegment", "r_name"), {"k": [25, 50, 75], "w_error": [1, 2], "w_click": [1, 2]}))))
def b_feature_groups(spark: SparkSession, d: str) -> DataFrame:
    """Best score without and with environment and waits."""
    frame = datasets.events_frame(spark, d).withColumn("t", F.col("crit"))
    out = []
    for name, a, c in (("statement", ("event_type",), {"k": [25, 50, 75]}), ("with context", ("event_type", "c_mktsegment", "r_name"), {"k": [25, 50, 75], "w_error": [1, 2], "w_click": [1, 2]})):
        ds = SubgroupDataset(frame, numeric=tuple(c), nominal=a)
        s = search.Session(ds, chosen(ds, a, c), False)
        out.append((name, search.beam(s, "binomial", 10, 2, 20).rows[0]["score"]))
        s.close()
    return spark.createDataFrame(out, "features string, best double")


query("c_ks_distance", f"WITH d AS (SELECT CAST(t AS DOUBLE) AS v, CASE WHEN event_type = 'error' AND k < 20 THEN 1 ELSE 0 END AS m FROM ({EV})), c AS (SELECT v, count(*) AS n, sum(m) AS m FROM d GROUP BY v), r AS (SELECT CAST(sum(n) OVER (ORDER BY v) AS DOUBLE) / (SELECT count(*) FROM d) AS f, CAST(sum(m) OVER (ORDER BY v) AS DOUBLE) / (SELECT sum(m) FROM d) AS g FROM c) SELECT round(max(abs(f - g)), 6) AS ks FROM r")(lambda spark, d: stats.ks_distance(events(spark, d), PAIR))


@query("c_candidates", f"WITH ds AS ({EV}), sel AS MATERIALIZED ({E_SEL}), f AS (SELECT greatest(5, ceil(count(*) / 1000)) AS lo FROM ds), one AS (SELECT label FROM sel GROUP BY label HAVING count(*) >= (SELECT lo FROM f)), two AS (SELECT a.label, b.label FROM sel a JOIN sel b ON a.oid = b.oid AND a.label < b.label AND NOT list_contains(a.blocks, b.key) GROUP BY 1, 2 HAVING count(*) >= (SELECT lo FROM f)) SELECT 1 AS level, CAST(count(*) AS BIGINT) AS candidates FROM one UNION ALL SELECT 2, CAST(count(*) AS BIGINT) FROM two")
def c_candidates(spark: SparkSession, d: str) -> DataFrame:
    """Candidates of enough support by level, as the exhaustive search counts them without bounds."""
    s = events_session(spark, d, median=False)
    trace = search.exhaustive(s, "wracc", 10, 2, order="level", bound="none", batch=10_000).trace
    s.close()
    return spark.createDataFrame([(i + 1, t["evaluated"]) for i, t in enumerate(trace)], "level int, candidates bigint")


_PLANT = "CASE WHEN event_type = 'error' AND k < 20 THEN 100 ELSE 0 END"


@query("c_planted_recovery", f"SELECT description, rank FROM ({oracle.search(f'SELECT * REPLACE (CAST(time_s + {_PLANT} AS DECIMAL(18,2)) AS t) FROM ({EV})', oracle.selectors(('event_type',), {'k': [20, 40, 60, 80], 'hour': [6, 12, 18]}), 'mean_test', 5, 2, None, 10, True)}) WHERE description = 'event_type=error & k<20'")
def c_planted_recovery(spark: SparkSession, d: str) -> DataFrame:
    t = (F.col("time_s") + F.when((F.col("event_type") == "error") & (F.col("k") < 20), 100).otherwise(0)).cast("decimal(18,2)")
    s = events_session(spark, d, nominals=("event_type",), replace_target=t, median=False)
    found = search.exhaustive(s, "mean_test", 5, 2, 10).frame(spark)
    s.close()
    return found.where("description = 'event_type=error & k<20'").select("description", "rank")


# ---- the toy example

# two of the toy's questions, asked of events: a binary target under one bound, and the rows of a bound and a place
query("w_toy_binary", f"SELECT CAST(count(*) FILTER (WHERE k >= 20) AS BIGINT) AS n, round(avg({SLOW}) FILTER (WHERE k >= 20), 6) AS rate, round(avg({SLOW}), 6) AS base FROM ({EV})")(lambda spark, d: _rate(events(spark, d, "slow").rows(), lattice.to_column((Selector("k", ">=", 20),)), "t"))
query("w_toy_pair", f"SELECT CAST(count(*) AS BIGINT) AS n, round(avg(slow), 6) AS rate, (SELECT round(avg(slow), 6) FROM ({oracle.TOY_SQL})) AS base FROM ({oracle.TOY_SQL}) WHERE where_b_key = 1 AND soft_version = 'v2'")(lambda spark, d: _toy(spark, (F.col("where_b_key") == 1) & (F.col("soft_version") == "v2"), "slow"))
query("w_toy_numeric", f"SELECT CAST(count(*) AS BIGINT) AS n, round(avg(CAST(time_s AS DOUBLE)), 6) AS rate, (SELECT round(avg(CAST(time_s AS DOUBLE)), 6) FROM ({oracle.TOY_SQL})) AS base FROM ({oracle.TOY_SQL}) WHERE from_a > 0 AND alert_sessions = 'Critical'")(lambda spark, d: _toy(spark, (F.col("from_a") > 0) & (F.col("alert_sessions") == "Critical"), "time_s"))
query("w_toy_extent", f"SELECT oid FROM ({EV}) WHERE k >= 50 AND r_name = 'ASIA'")(lambda spark, d: lattice.extent(events(spark, d), (Selector("k", ">=", 50), Selector("r_name", "=", "ASIA"))))
query("w_toy_jaccard", f"SELECT round(CAST(count(*) FILTER (WHERE from_a >= 1 AND where_a_key >= 1) AS DOUBLE) / count(*) FILTER (WHERE from_a >= 1 OR where_a_key >= 1), 6) AS jaccard FROM ({oracle.TOY_SQL})")(lambda spark, d: redundancy.jaccard(SubgroupDataset(datasets.toy_frame(spark).withColumn("t", F.col("slow")), numeric=("from_a", "where_a_key")), [(Selector("from_a", ">=", 1),), (Selector("where_a_key", ">=", 1),)]).select(F.round("jaccard", 6).alias("jaccard")))


def _toy(spark: SparkSession, condition, target: str) -> DataFrame:
    return _rate(datasets.toy_frame(spark), condition, target)


def _rate(rows: DataFrame, condition, target: str) -> DataFrame:
    t = F.col(target).cast("double")
    return rows.agg(F.count_if(condition).alias("n"), F.round(F.avg(F.when(condition, t)), 6).alias("rate"), F.round(F.avg(t), 6).alias("base"))
