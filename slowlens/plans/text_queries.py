"""Ingestion, parsing and enrichment as registered queries. Their oracles know each template's tokens by heart."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from slowlens.functions import sqltext
from slowlens.operators import enrich, selectors, stats, targets
from slowlens.operators.dataset import SubgroupDataset
from slowlens.plans import oracle, search, search_queries
from slowlens.plans.registry import query
from slowlens.sources import datasets
from slowlens.session import load

#: The six statement templates (k modulo 6 chooses one), {k} and {v} filled from the row, and their tokens.
TEMPLATES = [
    "select p.p_name from part p where p.p_size = {k}",
    "select count(*) from orders where o_totalprice > {v} and o_totalprice < :w",
    "select o.o_orderkey from orders o join lineitem l on o.o_orderkey = l.l_orderkey where l.l_quantity > {k} order by o.o_orderkey",
    "select s.s_name from supplier s where s.s_suppkey in (select l.l_suppkey from lineitem l where l.l_discount > :d and l.l_suppkey = s.s_suppkey)",
    "SELECT c.c_mktsegment, SUM(c.c_acctbal) FROM customer c GROUP BY c.c_mktsegment HAVING COUNT(DISTINCT c.c_nationkey) > {k}",
    "from sales.model.Invoice i join fetch i.lines x where i.state = :p1 and x.price > :p2",
]
TOKENS = [
    {"SELECT_part.p_name": 1, "FROM_part": 1, "WHERE_part.p_size": 1},
    {"FROM_orders": 1, "WHERE_orders.o_totalprice": 2},
    {"SELECT_orders.o_orderkey": 1, "FROM_orders": 1, "JOIN_lineitem": 1, "WHERE_orders.o_orderkey": 1, "WHERE_lineitem.l_orderkey": 1, "WHERE_lineitem.l_quantity": 1, "ORDERBY_orders.o_orderkey": 1},
    {"SELECT_supplier.s_name": 1, "FROM_supplier": 1, "WHERE_supplier.s_suppkey": 2, "SELECT_lineitem.l_suppkey": 1, "FROM_lineitem": 1, "WHERE_lineitem.l_discount": 1, "WHERE_lineitem.l_suppkey": 1},
    {"SELECT_customer.c_mktsegment": 1, "SELECT_customer.c_acctbal": 1, "SUM_customer.c_acctbal": 1, "FROM_customer": 1, "GROUPBY_customer.c_mktsegment": 1, "HAVING_customer.c_nationkey": 1, "COUNT_customer.c_nationkey": 1},
    {"FROM_sales.model.invoice": 1, "JOIN_sales.model.invoice.lines": 1, "WHERE_sales.model.invoice.state": 1, "WHERE_sales.model.invoice.lines.price": 1},
]
_VALUES = ", ".join(f"({i}, '{token}', {n})" for i, t in enumerate(TOKENS) for token, n in t.items())
TOKEN_SQL = f"SELECT l.oid, v.token, v.n FROM ({oracle.LOG}) l JOIN (VALUES {_VALUES}) v(template, token, n) ON l.k % 6 = v.template"


def statements(spark: SparkSession, d: str) -> DataFrame:
    """DS-Q: the log with a statement text for each row."""
    log = datasets.query_log(spark, d)
    text = F.element_at(F.lit(TEMPLATES), (F.col("nrows") % 6 + 1).cast("int"))
    return log.withColumn("sql_text", F.replace(F.replace(text, F.lit("{k}"), F.col("nrows").cast("string")), F.lit("{v}"), F.col("time_s").cast("string")))


def statements_set(spark: SparkSession, d: str) -> SubgroupDataset:
    df = sqltext.with_tokens(statements(spark, d)).withColumn("t", (F.col("time_s") > 25).cast("int"))
    return SubgroupDataset(df, nominal=("kind",), tokens="tokens")


def _long(df: DataFrame, where: str | None = None) -> DataFrame:
    out = df.select("oid", F.explode("tokens").alias("token", "n"))
    return (out.where(where) if where else out).select("oid", "token", F.col("n").cast("int").alias("n"))


def _tokens(key: str, templates: str | None = None, token: str | None = None, spark_where: str | None = None) -> None:
    conditions = " AND ".join(c for c in (f"l.k % 6 IN ({templates})" if templates else "", token or "") if c)
    text = f"{TOKEN_SQL} WHERE {conditions}" if conditions else TOKEN_SQL

    def run(spark: SparkSession, d: str) -> DataFrame:
        rows = statements(spark, d)
        return _long(sqltext.with_tokens(rows.where(f"nrows % 6 IN ({templates})") if templates else rows), spark_where)

    query(key, text.replace("v.n FROM", "CAST(v.n AS INTEGER) AS n FROM"))(run)


_tokens("p_parse_tokens")
_tokens("p_function_tokens", None, "regexp_matches(v.token, '^(SUM|COUNT|MIN|MAX|AVG)_')", "token rlike '^(SUM|COUNT|MIN|MAX|AVG)_'")
_tokens("p_alias_tokens", "0, 2")
_tokens("p_nested_tokens", "3")
_tokens("p_orm_tokens", "5")
_tokens("p_normalised_tokens", "4")


@query("p_query_log", f"SELECT oid, server, started, time_s, k AS nrows FROM ({oracle.LOG})")
def p_query_log(spark: SparkSession, d: str) -> DataFrame:
    is_select = F.lower(F.trim("sql_text")).rlike("^(select|with|from)\\b")
    return statements(spark, d).where(is_select).select("oid", "server", "started", "time_s", "nrows")


@query("p_record_threshold", f"SELECT oid, time_s FROM ({oracle.LOG}) WHERE time_s > 5")
def p_record_threshold(spark: SparkSession, d: str) -> DataFrame:
    """The filter stands before any Python node and is pushed to the scan as a bound on the raw value."""
    e = load(spark, d, "events").where("value > 5").select(F.col("event_id").alias("oid"), F.col("value").cast("decimal(18,2)").alias("time_s"))
    return e.where("time_s > 5")


@query("p_token_counts", f"SELECT token, CAST(count(DISTINCT oid) AS BIGINT) AS rows, CAST(count(*) AS BIGINT) AS uses FROM ({oracle.ORDER_TOKENS}) GROUP BY token")
def p_token_counts(spark: SparkSession, d: str) -> DataFrame:
    return datasets.orders_set(spark, d).rows().select(F.explode("tokens").alias("token", "n")).groupBy("token").agg(F.count("*").alias("rows"), F.sum("n").alias("uses"))


@query("p_env", f"SELECT oid, c_mktsegment, c_acctbal, n_name, r_name FROM ({oracle.EVENTS_PLAIN})")
def p_env(spark: SparkSession, d: str) -> DataFrame:
    return enrich.with_env(datasets.query_log(spark, d), datasets.environment(spark, d), "server").select("oid", "c_mktsegment", "c_acctbal", "n_name", "r_name")


@query("p_waits", f"SELECT oid, w_click, w_error, w_purchase, w_signup, w_view FROM ({oracle.EVENTS})")
def p_waits(spark: SparkSession, d: str) -> DataFrame:
    log = datasets.query_log(spark, d)
    return enrich.with_waits(log, datasets.waiting_sessions(spark, d), list(datasets.TYPES)).select("oid", *[f"w_{c}" for c in datasets.TYPES])


@query("p_alerts", f"SELECT oid, a_error FROM ({oracle.EVENTS})")
def p_alerts(spark: SparkSession, d: str) -> DataFrame:
    log = datasets.query_log(spark, d).select("oid", "server", "started", "ended")
    return enrich.with_alerts(log, datasets.alert_intervals(spark, d), ["error"], datasets.LEVELS).select("oid", "a_error")


@query("p_clock", f"SELECT oid, CAST(hour(started) AS INTEGER) AS hour, CAST(isodow(started) AS INTEGER) AS dow FROM ({oracle.LOG})")
def p_clock(spark: SparkSession, d: str) -> DataFrame:
    return enrich.with_clock(datasets.query_log(spark, d)).select("oid", "hour", "dow")


@query("p_concurrence", f"SELECT bo AS oid, busy AS concurrence FROM ({oracle.BUSY_SQL})")
def p_concurrence(spark: SparkSession, d: str) -> DataFrame:
    log = datasets.query_log(spark, d)
    return targets.concurrence(log, datasets.waiting_sessions(spark, d), datasets.BUSY).select("oid", "concurrence")


@query("p_slow", f"SELECT oid, CASE WHEN time_s > 10 THEN 1 ELSE 0 END AS slow FROM ({oracle.LOG})")
def p_slow(spark: SparkSession, d: str) -> DataFrame:
    return datasets.query_log(spark, d).select("oid", targets.threshold("time_s", ">", 10).alias("slow"))


@query("p_level_target", f"SELECT oid, CASE WHEN a_error IN ('Critical', 'Blocking') THEN 1 ELSE 0 END AS t FROM ({oracle.EVENTS})")
def p_level_target(spark: SparkSession, d: str) -> DataFrame:
    return datasets.events_frame(spark, d).select("oid", targets.in_levels("a_error", ["Critical", "Blocking"]).alias("t"))


@query("p_nominal_target", "SELECT vec_id AS oid, v AS value, CASE WHEN label = v THEN 1 ELSE 0 END AS t FROM embeddings, (SELECT DISTINCT label AS v FROM embeddings WHERE label IS NOT NULL)")
def p_nominal_target(spark: SparkSession, d: str) -> DataFrame:
    vectors = load(spark, d, "embeddings")
    values = F.explode(F.lit(datasets.categories(vectors, "label")))
    return vectors.select(F.col("vec_id").alias("oid"), "label", values.alias("value")).select("oid", "value", (F.col("label") == F.col("value")).cast("int").alias("t"))


@query("p_dataset", f"SELECT oid, t, k, hour, dow, c_acctbal, event_type, c_mktsegment, r_name, n_name FROM ({oracle.EVENTS_PLAIN})")
def p_dataset(spark: SparkSession, d: str) -> DataFrame:
    return datasets.events_set(spark, d).rows()


def _stats_sql(ds: str, dense: list[str], tokens: str | None) -> str:
    filled = " + ".join(f"CASE WHEN CAST({c} AS VARCHAR) <> '0' THEN 1 ELSE 0 END" for c in dense)
    tok = f"(SELECT count(*) FROM (SELECT DISTINCT oid, token FROM ({tokens}) WHERE oid IN (SELECT oid FROM ds)))" if tokens else "0"
    n_tok = f"(SELECT count(DISTINCT token) FROM ({tokens}) WHERE oid IN (SELECT oid FROM ds))" if tokens else "0"
    return f"WITH ds AS ({ds}) SELECT CAST(count(*) AS BIGINT) AS n_rows, CAST({n_tok} + {len(dense)} AS BIGINT) AS n_features, CAST({n_tok} AS BIGINT) AS n_tokens, round(1 - CAST(sum({filled}) + {tok} AS DOUBLE) / (count(*) * ({n_tok} + {len(dense)})), 6) AS sparsity FROM ds"


query("p_dataset_stats", _stats_sql(oracle.ORDERS, ["c_mktsegment", "o_orderstatus", "o_orderpriority"], oracle.ORDER_TOKENS))(lambda spark, d: stats.dataset_stats(datasets.orders_set(spark, d)))
query("w_dataset_stats_documents", _stats_sql(oracle.DOCS, ["n_chars", "n_words", "n_lines", "lang", "source"], oracle.DOC_TOKENS))(lambda spark, d: stats.dataset_stats(datasets.documents_set(spark, d)))

L_DENSE = ["l_quantity", "p_size", "l_returnflag", "l_linestatus", "p_brand", "p_type", "c_mktsegment"]
E_DENSE = ["k", "hour", "dow", "event_type", "c_mktsegment", "r_name", "n_name"]


def _slices() -> list[tuple]:
    """Name, maker, SQL and dense columns of the whole log and of the four slices."""
    q = search_queries
    return [("All", datasets.events_frame, oracle.EVENTS, E_DENSE), ("D1", q.slice_d1, q.D1_SQL, L_DENSE), ("D2", q.slice_d2, q.D2_SQL, L_DENSE), ("D3", q.slice_d3, q.D3_SQL, E_DENSE), ("D4", q.slice_d4, q.D4_SQL, E_DENSE)]


@query("w_dataset_stats", " UNION ALL ".join(f"SELECT '{n}' AS slice, * FROM ({_stats_sql(s, c, None)})" for n, _, s, c in _slices()))
def w_dataset_stats(spark: SparkSession, d: str) -> DataFrame:
    parts = []
    for name, make, _, dense in _slices():
        numeric = tuple(c for c in dense if c in ("k", "hour", "dow", "l_quantity", "p_size"))
        ds = SubgroupDataset(make(spark, d), numeric=numeric, nominal=tuple(c for c in dense if c not in numeric))
        parts.append(stats.dataset_stats(ds).select(F.lit(name).alias("slice"), "*"))
    return reduce(DataFrame.unionByName, parts)


_DOMINANT = f"SELECT substr(token, strpos(token, '_') + 1) FROM ({TOKEN_SQL}) WHERE token LIKE 'FROM%' OR token LIKE 'JOIN%' GROUP BY 1 ORDER BY count(*) DESC, 1 LIMIT 1"
_DOMINANT_DS = f"SELECT l.*, l.time_s AS t FROM ({oracle.LOG}) l WHERE oid IN (SELECT oid FROM ({TOKEN_SQL}) WHERE token IN ('FROM_' || ({_DOMINANT}), 'JOIN_' || ({_DOMINANT})))"


@query("w_rq1_dominant_table", oracle.search(_DOMINANT_DS, oracle.selectors(("event_type",), {"k": [25, 50, 75]}) + " UNION ALL " + oracle.token_counts(TOKEN_SQL), "wracc", 10, 2, None, None, True, "CASE WHEN time_s > 25 THEN 1 ELSE 0 END"))
def w_rq1_dominant_table(spark: SparkSession, d: str) -> DataFrame:
    """Statements on the most used table: which clauses go with slow ones."""
    df = sqltext.with_tokens(statements(spark, d)).withColumn("t", (F.col("time_s") > 25).cast("int")).withColumnsRenamed({"kind": "event_type", "nrows": "k"})
    used = df.select(F.explode("tokens").alias("token", "n")).where("token like 'FROM%' or token like 'JOIN%'")
    top = used.groupBy(F.regexp_replace("token", "^[A-Z]+_", "").alias("name")).agg(F.count("*").alias("n")).orderBy(F.desc("n"), "name").first()["name"]
    df = df.where(F.array_contains(F.map_keys("tokens"), f"FROM_{top}") | F.array_contains(F.map_keys("tokens"), f"JOIN_{top}"))
    ds = SubgroupDataset(df, numeric=("k",), nominal=("event_type",), tokens="tokens")
    session = search.Session(ds, selectors.nominal(ds, ["event_type"]) + selectors.numeric("k", [25, 50, 75]) + selectors.tokens(ds, 1), False)
    try:
        return search.exhaustive(session, "wracc", 10, 2, binary=True).frame(spark)
    finally:
        session.close()


@query("p_clause_stats", f"SELECT string_split(token, '_')[1] AS clause, CAST(count(DISTINCT token) AS BIGINT) AS tokens FROM ({TOKEN_SQL}) GROUP BY 1")
def p_clause_stats(spark: SparkSession, d: str) -> DataFrame:
    return stats.clause_stats(statements_set(spark, d))


@query("p_feature_catalog", "SELECT * FROM (VALUES ('k', 'numeric'), ('hour', 'numeric'), ('dow', 'numeric'), ('c_acctbal', 'numeric'), ('event_type', 'nominal'), ('c_mktsegment', 'nominal'), ('r_name', 'nominal'), ('n_name', 'nominal')) v(attribute, kind)")
def p_feature_catalog(spark: SparkSession, d: str) -> DataFrame:
    return stats.feature_catalog(datasets.events_set(spark, d))


# ---- the flat baseline

FLAT = [{}, {}, {}, {}, {}, {}]
for _i, _t in enumerate(TOKENS):
    for _token, _n in _t.items():
        _clause, _, _name = _token.partition("_")
        if _clause in ("FROM", "JOIN"):
            _flat = "FROM_" + ("i.lines" if _name.endswith(".lines") else _name)
        elif _clause in sqltext.CLAUSES:
            _flat = f"{_clause}_{_name.rpartition('.')[2]}"
        else:
            continue
        FLAT[_i][_flat] = FLAT[_i].get(_flat, 0) + _n
_FLAT_VALUES = ", ".join(f"({i}, '{token}', {n})" for i, t in enumerate(FLAT) for token, n in t.items())


@query("b_flat_tokens", f"SELECT l.oid, v.token, CAST(v.n AS INTEGER) AS n FROM ({oracle.LOG}) l JOIN (VALUES {_FLAT_VALUES}) v(template, token, n) ON l.k % 6 = v.template")
def b_flat_tokens(spark: SparkSession, d: str) -> DataFrame:
    return _long(sqltext.with_tokens(statements(spark, d), flat=True))


@query("b_parser_collisions", f"SELECT f AS flat, CAST(count(DISTINCT token) AS BIGINT) AS qualified FROM (SELECT DISTINCT token, CASE WHEN token LIKE 'FROM%' OR token LIKE 'JOIN%' THEN 'FROM' ELSE string_split(token, '_')[1] END || '_' || regexp_extract(token, '[^.]*$') AS f FROM ({TOKEN_SQL}) WHERE regexp_matches(token, '^(SELECT|WHERE|GROUPBY|HAVING|ORDERBY)_')) GROUP BY 1")
def b_parser_collisions(spark: SparkSession, d: str) -> DataFrame:
    """For each flat column token the qualified tokens that it merges."""
    tokens = sqltext.with_tokens(statements(spark, d)).select(F.explode(F.map_keys("tokens")).alias("token")).distinct()
    columns = tokens.where("token rlike '^(SELECT|WHERE|GROUPBY|HAVING|ORDERBY)_'")
    flat = F.concat(F.substring_index("token", "_", 1), F.lit("_"), F.regexp_extract("token", "([^.]*)$", 1))
    return columns.groupBy(flat.alias("flat")).agg(F.count_distinct("token").alias("qualified"))


@query("udtf_parse", f"SELECT k % 6 AS template, string_split(token, '_')[1] AS clause, substr(token, strpos(token, '_') + 1) AS name, CAST(n AS INTEGER) AS cnt FROM (SELECT DISTINCT l.k, x.token, x.n FROM ({oracle.LOG}) l JOIN ({TOKEN_SQL}) x ON l.oid = x.oid) GROUP BY ALL")
def udtf_parse(spark: SparkSession, d: str) -> DataFrame:
    """The table function, lateral to one statement of each template."""
    sqltext.register_table_function(spark)
    one = statements(spark, d).groupBy((F.col("nrows") % 6).alias("template")).agg(F.min("sql_text").alias("sql_text"))
    one.createOrReplaceTempView("slowlens_statements")
    return spark.sql("SELECT s.template, p.clause, p.name, p.cnt FROM slowlens_statements s, LATERAL parse_sql(s.sql_text) p")
