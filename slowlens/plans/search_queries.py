"""Measures, searches and experiment workloads as registered queries."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from slowlens.functions import bounds
from slowlens.functions.quantiles import median
from slowlens.functions.measures import get, scored, tscore
from slowlens.operators import counting, selectors, stats
from slowlens.operators.dataset import SubgroupDataset
from slowlens.operators.selectors import Selector
from slowlens.plans import oracle, search
from slowlens.plans.registry import query
from slowlens.sources import datasets

#: The selectors of the experiments on events: categories, and cut points of the numeric attributes.
E_NOMINAL = ("event_type", "c_mktsegment", "r_name")
E_CUTS = {"k": [20, 40, 60, 80], "hour": [6, 12, 18]}
L_NOMINAL = ("l_returnflag", "l_linestatus", "p_type", "c_mktsegment", "o_orderpriority")
L_CUTS = {"l_quantity": [10, 20, 30, 40]}


def chosen(ds: SubgroupDataset, nominals: tuple[str, ...], cuts: dict[str, list], min_support: int = 1) -> list[Selector]:
    out = selectors.nominal(ds, list(nominals), min_support)
    return out + [s for a, c in cuts.items() for s in selectors.numeric(a, c)]


def events_session(spark: SparkSession, sf_dir: str, target: str = "time_s", nominals=E_NOMINAL, cuts=E_CUTS, where: str | None = None, replace_target=None, median: bool = True) -> search.Session:
    ds = datasets.events_set(spark, sf_dir, target)
    ds = ds.where(where) if where else ds
    ds = ds.with_target(replace_target) if replace_target is not None else ds
    return search.Session(ds, chosen(ds, nominals, cuts), median)


E_SEL = oracle.selectors(E_NOMINAL, E_CUTS)
SLOW = "CASE WHEN time_s > 25 THEN 1 ELSE 0 END"


def _run(session: search.Session, how: str, spark: SparkSession, **options) -> DataFrame:
    try:
        return getattr(search, how)(session, **options).frame(spark)
    finally:
        session.close()


# ---- measures over the depth-1 subgroups of events


def kept(session: search.Session, rows: DataFrame) -> DataFrame:
    """`rows`, few by construction (a row for each selector), taken from a session that is then closed."""
    with session:
        return session.ds.df.sparkSession.createDataFrame(rows.collect(), rows.schema)


def depth_one(session: search.Session, with_median: bool = False) -> DataFrame:
    """Statistics of every single selector, with its label."""
    cands = counting.level_counts(session.cells, session.norms.form, [()], session.blocked)
    if with_median:
        cands = counting.with_medians(cands, session.encoded, *session.bins(), [()], session.blocked)
    return cands.withColumn("description", F.element_at(F.lit(session.labels), F.element_at("p", 1) + 1))


def measure_rows(session: search.Session, names: dict[str, str]) -> DataFrame:
    """Every depth-1 subgroup with the asked measures, one column each."""
    cands = depth_one(session, _medians(names))
    return kept(session, cands.select("description", F.col("n").alias("size"), *[scored(m, session.norms).alias(c) for c, m in names.items()]))


def _medians(names: dict[str, str]) -> bool:
    return any(get(m).needs == "median" for m in names.values())


def measure_sql(names: dict[str, str], target: str | None = None) -> str:
    ds = f"SELECT * REPLACE ({target} AS t) FROM ({oracle.EVENTS_PLAIN})" if target else oracle.EVENTS_PLAIN
    cols = ", ".join(f"round({oracle.score(m)}, 9) AS {c}" for c, m in names.items())
    return f"WITH ds AS MATERIALIZED ({ds}), g AS ({oracle._NORMS}), sel AS ({E_SEL}) SELECT label AS description, CAST(n AS BIGINT) AS size, {cols} FROM (SELECT label, {oracle._STATS} FROM sel GROUP BY label), g"


for _key, _names, _target in [
    ("q_support", {"support": "support"}, None),
    ("q_klosgen", {f"a{int(a * 100):03d}": f"klosgen_{a:g}" for a in (0, 0.25, 0.5, 0.75, 1)}, None),
    ("q_average", {"average": "average"}, None),
    ("q_lift", {"lift": "lift"}, None),
    ("q_lift_binary", {"lift": "lift", "precision": "precision"}, "slow"),
    ("q_wracc_numeric", {"wracc": "wracc"}, None),
    ("q_wracc_binary", {"wracc": "wracc_binary", "numeric_form": "wracc"}, "slow"),
    ("q_wracc_abs", {"wracc": "wracc_abs"}, "slow"),
    ("q_mean_test", {"mean_test": "mean_test"}, None),
    ("q_binomial", {"binomial": "binomial", "mean_test": "mean_test"}, "slow"),
    ("q_tscore", {"tscore": "tscore"}, None),
    ("q_median", {"a000": "median_0", "a050": "median_0.5", "a100": "median_1"}, None),
    ("q_precision", {"precision": "precision"}, "slow"),
    ("q_median_ratio", {"median_ratio": "median_ratio"}, None),
    ("q_low_direction", {"low_wracc": "low_wracc", "low_median": "low_median_0.5"}, None),
]:
    query(_key, measure_sql(_names, SLOW if _target else None))(lambda spark, d, n=_names, t=_target: measure_rows(events_session(spark, d, t or "time_s", median=_medians(n)), n))


@query("q_coverage", f"WITH ds AS MATERIALIZED (SELECT * REPLACE ({SLOW} AS t) FROM ({oracle.EVENTS_PLAIN})), sel AS ({E_SEL}) SELECT label AS description, round(CAST(count(*) AS DOUBLE) / (SELECT count(*) FROM ds), 6) AS of_rows, round(CAST(sum(t) AS DOUBLE) / (SELECT sum(t) FROM ds), 6) AS of_positives FROM sel GROUP BY label")
def q_coverage(spark: SparkSession, d: str) -> DataFrame:
    s = events_session(spark, d, "slow", median=False)
    rows = depth_one(s).select("description", F.round(F.col("n") / s.norms.n, 6).alias("of_rows"), F.round(F.col("s1").cast("double") / s.norms.positives, 6).alias("of_positives"))
    return kept(s, rows)


@query("q_report_stats", f"WITH ds AS MATERIALIZED ({oracle.EVENTS_PLAIN}), sel AS ({E_SEL}) SELECT label AS description, CAST(count(*) AS BIGINT) AS size, round(CAST(sum(t) AS DOUBLE) / count(*), 6) AS mean, round(stddev_pop(CAST(t AS DOUBLE)), 6) AS std, round(median(CAST(t AS DOUBLE)), 6) AS median FROM sel GROUP BY label")
def q_report_stats(spark: SparkSession, d: str) -> DataFrame:
    s = events_session(spark, d, median=False)
    return kept(s, stats.describe_selectors(s))


@query("q_multi_target", measure_sql({"wracc": "wracc"}, "CASE WHEN time_s > 25 AND k < 50 THEN 1 ELSE 0 END"))
def q_multi_target(spark: SparkSession, d: str) -> DataFrame:
    """Slow and few rows at once."""
    both = F.least((F.col("time_s") > 25).cast("int"), (F.col("k") < 50).cast("int"))
    return measure_rows(events_session(spark, d, replace_target=both, median=False), {"wracc": "wracc"})


@query("q_tscore_sample", measure_sql({"tscore": "tscore"}).replace(oracle.SCORES["tscore"], "CASE WHEN n >= 2 THEN sqrt(n / tot) / (sqrt(greatest(s2 / n - s1 / n * (s1 / n), 0)) * sqrt(n / (n - 1))) * (s1 / n - mu0) END"))
def q_tscore_sample(spark: SparkSession, d: str) -> DataFrame:
    s = events_session(spark, d, median=False)
    return kept(s, depth_one(s).select("description", F.col("n").alias("size"), scored(tscore(1), s.norms).alias("tscore")))


# times of milliseconds, and amounts beyond a hundred billion: no target is rounded before it is summed
_SCALED = {"average": "average", "wracc": "wracc", "tscore": "tscore", "median": "median_0.5"}
FINE, LARGE = "CAST(time_s AS DOUBLE) / 100000", "CAST(CAST(time_s AS DECIMAL(38,2)) * 100000000 AS DECIMAL(30,2))"
query("q_fine_target", measure_sql(_SCALED, FINE))(lambda spark, d: measure_rows(events_session(spark, d, replace_target=F.col("time_s").cast("double") / 100000), _SCALED))
query("q_large_target", measure_sql({"lift": "lift", "tscore": "tscore"}, LARGE))(lambda spark, d: measure_rows(events_session(spark, d, replace_target=F.expr(LARGE), median=False), {"lift": "lift", "tscore": "tscore"}))


# ---- searches


def _beam(key: str, depth: int, measure: str = "wracc", width: int = 10, k: int = 10, target: str | None = None, **sql) -> None:
    sql_text = oracle.search(oracle.EVENTS_PLAIN, E_SEL, measure, k, depth, width, target=SLOW if target else None, **sql)
    query(key, sql_text)(lambda spark, d: _run(events_session(spark, d, target or "time_s", median=measure.startswith("med")), "beam", spark, measure=measure, k=k, depth=depth, width=width))


_beam("a_beam_d1", 1)
_beam("a_beam_d2", 2)
_beam("a_beam_d3", 3)
_beam("a_beam_median", 2, "median_0.5")
_beam("a_beam_tscore", 2, "tscore")
_beam("a_beam_lift", 2, "lift", target="slow")


def _exhaustive(key: str, depth: int, measure: str, target: str | None = None, nominals=E_NOMINAL, cuts=E_CUTS, min_support: int | None = None, **options) -> None:
    sel = oracle.selectors(nominals, cuts)
    text = oracle.search(oracle.EVENTS_PLAIN, sel, measure, 10, depth, None, min_support, True, SLOW if target else None)
    query(key, text)(lambda spark, d: _run(events_session(spark, d, target or "time_s", nominals, cuts, median=measure.startswith("med")), "exhaustive", spark, measure=measure, k=10, depth=depth, min_support=min_support, binary=bool(target), **options))


_exhaustive("a_exhaustive_d1", 1, "wracc")
_exhaustive("a_exhaustive_d2", 2, "wracc")
_exhaustive("a_exhaustive_d3", 3, "mean_test", nominals=("event_type",), cuts={"k": [25, 50, 75], "hour": [12]})
_exhaustive("a_exhaustive_binary", 2, "binomial", "slow")
_exhaustive("a_exhaustive_best_first", 2, "mean_test", order="best", batch=12)
_exhaustive("a_exhaustive_level_wise", 2, "mean_test", order="level", batch=12)
_exhaustive("a_exhaustive_tight", 2, "mean_test", bound="tight", batch=12)
_exhaustive("a_exhaustive_no_bound", 2, "mean_test", bound="none")
_exhaustive("a_average_min_size", 2, "average", min_support=100)
_exhaustive("a_two_sided", 2, "wracc_abs", "slow")


@query("a_beam_levels", oracle.search(oracle.EVENTS_PLAIN, E_SEL, "wracc", 10, 2, 10, levels=True))
def a_beam_levels(spark: SparkSession, d: str) -> DataFrame:
    with events_session(spark, d, median=False) as s:
        rows = search.beam_levels(s, "wracc", 2, 10)
    return spark.createDataFrame([(r["level"], r["description"], r["n"], r["score"]) for r in rows], "level int, description string, size bigint, score double")


@query("a_min_support", f"WITH ds AS MATERIALIZED ({oracle.EVENTS_PLAIN}), sel AS MATERIALIZED ({E_SEL}) SELECT label AS description, CAST(count(*) AS BIGINT) AS size FROM sel GROUP BY label HAVING count(*) >= 2500")
def a_min_support(spark: SparkSession, d: str) -> DataFrame:
    s = events_session(spark, d, median=False)
    return kept(s, s.candidates([()], get("wracc"), 2500, False).select("description", F.col("n").alias("size")))


_POS = "sum(greatest(CAST(t AS DOUBLE) - mu0, 0))"


@query("a_bounds", f"""WITH ds AS MATERIALIZED ({oracle.EVENTS_PLAIN}), g AS ({oracle._NORMS}), sel AS MATERIALIZED ({E_SEL}),
x AS (SELECT label, count(*) AS n, {_POS} AS pos, max(CAST(t AS DOUBLE)) AS tmax, any_value(tot) AS tot, any_value(mu0) AS mu0, any_value(med0) AS med0 FROM sel, g GROUP BY label)
SELECT label AS description, round(pos / tot, 5) AS wracc, round(CASE WHEN pos / (tmax - mu0) >= 10 THEN pow(tot, -0.5) * pow(pos / (tmax - mu0), 0.5) * (tmax - mu0) ELSE pow(tot, -0.5) * pow(10, -0.5) * pos END, 5) AS mean_test,
round(greatest(pow(n / tot, 0.5) * (tmax - med0), 0), 5) AS median FROM x""")
def a_bounds(spark: SparkSession, d: str) -> DataFrame:
    s = events_session(spark, d)
    return kept(s, depth_one(s).select("description", *[F.round(bounds.estimate(get(m), s.norms, 10), 5).alias(c) for c, m in (("wracc", "wracc"), ("mean_test", "mean_test"), ("median", "median_0.5"))]))


@query("b_brute_d2", oracle.search(oracle.EVENTS_PLAIN, E_SEL, "wracc", 10, 2, None, ties=True))
def b_brute_d2(spark: SparkSession, d: str) -> DataFrame:
    s = events_session(spark, d, median=False)
    return kept(s, search.brute(s, "wracc", 10, 2))


# ---- experiment workloads

TOP_BRAND = "p_brand = (SELECT p_brand FROM ({0}) GROUP BY 1 ORDER BY count(*) DESC, p_brand LIMIT 1)"
WIDE_SUPPLIERS = "SELECT l_suppkey FROM (SELECT l_suppkey, count(DISTINCT o_custkey) AS c FROM ({0}) GROUP BY 1) WHERE c >= (SELECT median(c) FROM (SELECT count(DISTINCT o_custkey) AS c FROM ({0}) GROUP BY l_suppkey))"


def slice_d1(spark: SparkSession, d: str, region: int | None = None) -> DataFrame:
    """Lines of suppliers with at least the median number of distinct customers."""
    lines = datasets.lineitem_frame(spark, d)
    wide = lines.groupBy("l_suppkey").agg(F.count_distinct("o_custkey").alias("c"))
    keep = wide.where(F.col("c") >= median(wide, "c")).select("l_suppkey")
    out = lines.join(keep, "l_suppkey", "left_semi")
    return out.where(F.col("s_regionkey") == region) if region is not None else out


def slice_d2(spark: SparkSession, d: str) -> DataFrame:
    """Lines of the most frequent brand."""
    lines = datasets.lineitem_frame(spark, d)
    top = lines.groupBy("p_brand").count().orderBy(F.desc("count"), "p_brand").limit(1).select("p_brand")
    return lines.join(F.broadcast(top), "p_brand", "left_semi")


def slice_d3(spark: SparkSession, d: str) -> DataFrame:
    """Statements of one software version."""
    return datasets.events_frame(spark, d).where("server % 3 = 1")


def slice_d4(spark: SparkSession, d: str) -> DataFrame:
    """Statements of servers with an abnormal share of errors."""
    events = datasets.events_frame(spark, d)
    share = events.groupBy("server").agg(F.avg((F.col("event_type") == "error").cast("double")).alias("x"))
    limit = share.agg((F.avg("x") + F.stddev_pop("x")).alias("m"))
    keep = share.join(F.broadcast(limit)).where("x > m").select("server")
    return events.join(keep, "server", "left_semi")


D1_SQL = f"SELECT * FROM ({oracle.LINES}) WHERE l_suppkey IN ({WIDE_SUPPLIERS.format(oracle.LINES)})"
D2_SQL = f"SELECT * FROM ({oracle.LINES}) WHERE {TOP_BRAND.format(oracle.LINES)}"
D3_SQL = f"SELECT * FROM ({oracle.EVENTS}) WHERE server % 3 = 1"
_SHARE = "SELECT server, avg(CASE WHEN event_type = 'error' THEN 1.0::DOUBLE ELSE 0 END) AS x FROM ({0}) GROUP BY 1"
D4_SQL = f"SELECT * FROM ({oracle.EVENTS}) WHERE server IN (SELECT server FROM ({_SHARE.format(oracle.EVENTS_PLAIN)}) WHERE x > (SELECT avg(x) + stddev_pop(x) FROM ({_SHARE.format(oracle.EVENTS_PLAIN)})))"


def _slice_query(key: str, make, sql: str, target: str) -> None:
    text = f"SELECT CAST(count(*) AS BIGINT) AS n, round(CAST(sum({target}) AS DOUBLE) / count(*), 6) AS mean, round(median(CAST({target} AS DOUBLE)), 6) AS median FROM ({sql})"

    def run(spark: SparkSession, d: str) -> DataFrame:
        ds = SubgroupDataset(make(spark, d).withColumn("t", F.col(target)))
        return stats.norms(ds).select("n", "mean", "median")

    query(key, text)(run)


_slice_query("w_slice_d1", slice_d1, D1_SQL, "price")
_slice_query("w_slice_d2", slice_d2, D2_SQL, "dear")
_slice_query("w_slice_d3", slice_d3, D3_SQL, "busy")
_slice_query("w_slice_d4", slice_d4, D4_SQL, "crit")


def _workload(key: str, make, sql: str, target: str, measure: str, nominals: tuple[str, ...], cuts: dict[str, list], width: int | None, min_support: int | None = None, depth: int = 2) -> None:
    text = oracle.search(sql, oracle.selectors(nominals, cuts), measure, 10, depth, width, min_support, width is None, target)

    def run(spark: SparkSession, d: str) -> DataFrame:
        ds = SubgroupDataset(make(spark, d).withColumn("t", F.col(target)), numeric=tuple(cuts), nominal=nominals)
        s = search.Session(ds, chosen(ds, nominals, cuts), measure.startswith("med"))
        if width is None:
            return _run(s, "exhaustive", spark, measure=measure, k=10, depth=depth, min_support=min_support, binary=target != "price" and target != "time_s")
        return _run(s, "beam", spark, measure=measure, k=10, depth=depth, width=width, min_support=min_support)

    query(key, text)(run)


D3_NOMINAL, D3_CUTS = ("event_type", "c_mktsegment", "r_name"), {"k": [25, 50, 75], "hour": [8, 16]}
_workload("w_rq1_median_lineitem", lambda s, d: slice_d1(s, d, 1), D1_SQL + " AND s_regionkey = 1", "price", "median_0.5", L_NOMINAL, L_CUTS, 50)
_workload("w_rq1_median_events", datasets.events_frame, oracle.EVENTS_PLAIN, "time_s", "median_0.5", ("event_type", "r_name"), {"k": [25, 50, 75]}, 50)
_workload("w_rq1_lift", slice_d2, D2_SQL, "dear", "lift", L_NOMINAL, L_CUTS, None, 20)
_workload("w_rq1_wracc", slice_d2, D2_SQL, "dear", "wracc", L_NOMINAL, L_CUTS, None)
_workload("w_rq2_lift", slice_d3, D3_SQL, "busy", "lift", D3_NOMINAL, D3_CUTS, None, 8)
_workload("w_rq2_binomial", slice_d3, D3_SQL, "busy", "binomial", D3_NOMINAL, D3_CUTS, None)
_workload("w_rq3_lift", slice_d4, D4_SQL, "crit", "lift", D3_NOMINAL, D3_CUTS, 50, 7)
_workload("w_rq3_binomial", slice_d4, D4_SQL, "crit", "binomial", D3_NOMINAL, D3_CUTS, 50)
_workload("w_conversations", lambda s, d: datasets.conversations_set(s, d, "answers").df, oracle.TURNS, "answers", "lift", ("prev_role",), {"turn": [1, 2, 3], "n_chars": [200, 500]}, 50, 10)

PLANTED = "time_s + CASE WHEN event_type = 'error' AND k < 20 THEN 100 ELSE 0 END"
for _m in ("lift", "wracc", "mean_test", "tscore", "median_0", "median_0.5", "median_1"):
    _text = oracle.search(f"SELECT * REPLACE (CAST({PLANTED} AS DECIMAL(18,2)) AS t) FROM ({oracle.EVENTS_PLAIN})", oracle.selectors(("event_type",), {"k": [20, 40, 60, 80], "hour": [6, 12, 18]}), _m, 10, 2, None, 10, True)

    def _planted(spark: SparkSession, d: str, m: str = _m) -> DataFrame:
        t = (F.col("time_s") + F.when((F.col("event_type") == "error") & (F.col("k") < 20), 100).otherwise(0)).cast("decimal(18,2)")
        return _run(events_session(spark, d, nominals=("event_type",), replace_target=t), "exhaustive", spark, measure=m, k=10, depth=2, min_support=10)

    query(f"w_planted_{_m.replace('.', '')}", _text)(_planted)


def _tokens(key: str, make, sql: str, tokens: str, target: str, measure: str, nominals: tuple[str, ...], cuts: dict[str, list], width: int = 20, floor: int | None = None, growing: bool = False) -> None:
    """A search over sparse token attributes: those of `floor` rows or more, the support that the search asks for anyway.

    `growing` says that the tokens become more with the table, so that no list of them is made.
    """
    base = oracle.selectors(nominals, cuts) if nominals or cuts else ""
    least = str(floor) if floor else f"greatest(5, (SELECT ceil(count(*) / 1000) FROM ({sql})))"
    frequent = f"SELECT oid, token FROM ({tokens}) WHERE token IN (SELECT token FROM ({tokens}) WHERE oid IN (SELECT oid FROM ({sql})) GROUP BY token HAVING count(DISTINCT oid) >= {least})"
    text = oracle.search(sql, base + " UNION ALL " + oracle.token_counts(frequent), measure, 10, 2, width, floor, target=target)

    def run(spark: SparkSession, d: str) -> DataFrame:
        ds = make(spark, d)
        if growing:
            ds = ds.persisted()
            try:
                return _run(search.TokenSession(ds, chosen(ds, nominals, cuts)), "beam", spark, measure=measure, k=10, depth=2, width=width, min_support=floor)
            finally:
                ds.df.unpersist()
        sels = chosen(ds, nominals, cuts) + selectors.tokens(ds, floor or max(5, -(-ds.df.count() // 1000)))
        return _run(search.Session(ds, sels, measure.startswith("med")), "beam", spark, measure=measure, k=10, depth=2, width=width, min_support=floor)

    query(key, text)(run)


_tokens("w_sparse_quality", lambda s, d: datasets.documents_set(s, d, "bad"), oracle.DOCS, oracle.DOC_TOKENS, "bad", "wracc", ("lang",), {"n_words": [100, 500], "n_lines": [5, 20]})
_tokens("w_sparse_toxic", lambda s, d: datasets.documents_set(s, d, "toxic"), oracle.DOCS, oracle.DOC_TOKENS, "toxic", "wracc", ("lang",), {"n_words": [100, 500]})
_tokens("w_sparse_orders", lambda s, d: datasets.orders_set(s, d, "finished"), oracle.ORDERS, oracle.ORDER_TOKENS, "finished", "wracc", ("c_mktsegment",), {}, floor=5, growing=True)
_tokens("w_pages", datasets.pages_set, oracle.PAGES, oracle.PAGE_TOKENS, "t", "median_0.5", ("scheme", "domain"), {}, 10)


COMPONENTS = 64
_LABEL_SQL = oracle.search(oracle.vectors(COMPONENTS), oracle.selectors((), {f"e{i}": [-0.1, 0, 0.1] for i in range(COMPONENTS)}), "wracc", 10, 2, 20, target="CASE WHEN label = {label} THEN 1 ELSE 0 END")


@query("w_nominal_embeddings", " UNION ALL ".join(f"SELECT * FROM (SELECT CAST({v} AS INTEGER) AS value, * FROM ({_LABEL_SQL.replace('{label}', str(v))})) WHERE {v} IN (SELECT label FROM embeddings)" for v in range(10)))
def w_nominal_embeddings(spark: SparkSession, d: str) -> DataFrame:
    """Each value of a nominal target against the rest, on all components; the given labels are 0 to 9."""
    sels = [x for i in range(COMPONENTS) for x in selectors.numeric(f"e{i}", [-0.1, 0, 0.1])]
    out = []
    for value in datasets.categories(datasets.load(spark, d, "embeddings"), "label"):
        s = search.Session(datasets.embeddings_set(spark, d, value, COMPONENTS), sels, False)
        out.append(_run(s, "beam", spark, measure="wracc", k=10, depth=2, width=20).select(F.lit(value).cast("int").alias("value"), "*"))
    return reduce(DataFrame.unionByName, out)
