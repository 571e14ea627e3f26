"""The surrounding relational operators on the given tables: scans, filters, joins, aggregates, windows, functions."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from slowlens.operators import enrich
from slowlens.plans import oracle
from slowlens.plans.registry import query
from slowlens.session import TABLES, load
from slowlens.sources import datasets, formats

_COLUMNS = {
    "region": "r_regionkey, r_name", "nation": "n_nationkey, n_name, n_regionkey", "customer": "c_custkey, c_name, c_mktsegment", "supplier": "s_suppkey, s_name, s_nationkey", "part": "p_partkey, p_brand, p_size",
    "orders": "o_orderkey, o_orderstatus, o_orderdate", "lineitem": "l_orderkey, l_partkey, l_quantity", "events": "event_id, user_id, event_type", "documents": "doc_id, lang, source", "embeddings": "vec_id, label",
    "pages": "page_id, url", "benchmark": "item_id, text", "labels": "doc_id, quality, toxic", "conversations": "conv_id, turn, role",
}
for _t in TABLES:
    query(f"s_scan_{_t}", f"SELECT {_COLUMNS[_t]} FROM {_t}")(lambda spark, d, t=_t: load(spark, d, t).select(*_COLUMNS[t].split(", ")))


def simple(key: str, sql: str, spark_sql: str | None = None, tables: tuple[str, ...] = ()) -> None:
    """A query whose Spark form is SQL text too; `tables` become views of a throw-away prefix."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        text = spark_sql or sql
        args = {t: load(spark, d, t) for t in tables}
        return spark.sql(text.replace("{{", "{").replace("}}", "}"), **args)

    query(key, sql.replace("{", "").replace("}", ""))(run)


# ---- sources and sinks

query("s_csv", "SELECT n_nationkey, n_name, n_regionkey FROM nation")(lambda spark, d: formats.round_trip(load(spark, d, "nation"), "csv"))
query("s_json", "SELECT event_id, user_id, event_type, value, props FROM events")(lambda spark, d: formats.round_trip(load(spark, d, "events").drop("ts"), "json"))
query("s_orc", "SELECT * FROM part")(lambda spark, d: formats.round_trip(load(spark, d, "part"), "orc"))
query("s_text_log", f"SELECT oid, server, time_s FROM ({oracle.LOG})")(lambda spark, d: formats.text_log(spark, formats.write_text_log(datasets.query_log(spark, d))).select("oid", "server", "time_s"))
query("s_partition_prune", "SELECT event_id, CAST(ts AS DATE) AS day FROM events WHERE CAST(ts AS DATE) = DATE '2024-01-05'")(lambda spark, d: formats.by_day(load(spark, d, "events")).where("day = DATE '2024-01-05'").select("event_id", "day"))


@query("s_bucketed", "SELECT o_orderkey, CAST(count(*) AS BIGINT) AS lines FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def s_bucketed(spark: SparkSession, d: str) -> DataFrame:
    """Both sides bucketed by the key: the join and the group-by exchange nothing."""
    o = formats.bucketed(load(spark, d, "orders").select("o_orderkey"), "o_orderkey", 8)
    li = formats.bucketed(load(spark, d, "lineitem").select("l_orderkey"), "l_orderkey", 8)
    return o.join(li, o.o_orderkey == li.l_orderkey).groupBy("o_orderkey").agg(F.count("*").alias("lines"))


@query("s_python_source")
def s_python_source(spark: SparkSession, d: str) -> DataFrame:
    formats.register_log_source(spark)
    path = formats.write_text_log(datasets.query_log(spark, d))
    return spark.read.format("slowlens_log").option("path", path).load()


@query("s_view_sql", "SELECT event_type, CAST(count(*) AS BIGINT) AS n FROM events GROUP BY 1")
def s_view_sql(spark: SparkSession, d: str) -> DataFrame:
    name = f"slowlens_events_{uuid.uuid4().hex}"
    load(spark, d, "events").createOrReplaceTempView(name)
    return spark.sql(f"SELECT event_type, count(*) AS n FROM {name} GROUP BY event_type")


# ---- filters and projections

EV = oracle.EVENTS_PLAIN
query("op_filter_pattern", f"SELECT oid FROM ({EV}) WHERE event_type = 'error' AND k >= 20 AND k < 60")(lambda spark, d: datasets.events_frame(spark, d, False).where((F.col("event_type") == "error") & (F.col("k") >= 20) & (F.col("k") < 60)).select("oid"))
simple("op_filter_interval", "SELECT l_orderkey, l_linenumber, l_quantity FROM {lineitem} WHERE l_quantity BETWEEN 10 AND 20 AND l_discount >= 0.03 AND l_discount < 0.07", None, ("lineitem",))
simple("op_filter_in", "SELECT event_id FROM {events} WHERE event_type IN ('error', 'view')", None, ("events",))
simple("op_filter_like", "SELECT p_partkey FROM {part} WHERE p_name LIKE '%ring' AND p_brand LIKE 'Brand#1_'", None, ("part",))
simple("op_case", "SELECT event_id, CASE WHEN value > 100 THEN 'slow' WHEN value > 10 THEN 'medium' ELSE 'fast' END AS speed FROM {events}", None, ("events",))
simple("op_null_safe", "SELECT o_orderkey, coalesce(l_quantity, 0) AS q, l_orderkey IS NULL AS empty FROM {orders} LEFT JOIN {lineitem} ON o_orderkey = l_orderkey WHERE l_orderkey IS NOT DISTINCT FROM NULL OR nullif(l_quantity, 1) IS NULL", None, ("orders", "lineitem"))
query("op_filter_not", f"SELECT oid FROM ({EV}) WHERE NOT (event_type = 'error' AND k < 20)")(lambda spark, d: datasets.events_frame(spark, d, False).where(~F.coalesce((F.col("event_type") == "error") & (F.col("k") < 20), F.lit(False))).select("oid"))
simple("op_project", "SELECT p_partkey AS id, upper(p_brand) AS brand, CAST(p_size AS DOUBLE) AS size, CAST(p_retailprice AS DECIMAL(18,2)) AS price FROM {part}", None, ("part",))

# ---- joins

simple("op_join_inner", "SELECT o_orderstatus, CAST(count(*) AS BIGINT) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS q FROM {lineitem} JOIN {orders} ON l_orderkey = o_orderkey GROUP BY 1", None, ("lineitem", "orders"))
query("op_join_broadcast", "SELECT c_mktsegment, CAST(count(*) AS BIGINT) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1")(lambda spark, d: (lambda e, c: e.join(enrich.small(c), e.user_id == c.c_custkey).groupBy("c_mktsegment").agg(F.count("*").alias("n")))(load(spark, d, "events"), load(spark, d, "customer").select("c_custkey", "c_mktsegment")))
simple("op_join_left", "SELECT o_orderkey, CAST(count(l_orderkey) AS BIGINT) AS lines FROM {orders} LEFT JOIN {lineitem} ON o_orderkey = l_orderkey GROUP BY 1", None, ("orders", "lineitem"))
simple("op_join_full", "SELECT c_custkey, user_id, CAST(count(*) AS BIGINT) AS n FROM {customer} FULL JOIN {events} ON c_custkey = user_id + 100 GROUP BY 1, 2", None, ("customer", "events"))
simple("op_join_right", "SELECT n_name, CAST(count(s_suppkey) AS BIGINT) AS n FROM {supplier} RIGHT JOIN {nation} ON s_nationkey = n_nationkey GROUP BY 1", None, ("supplier", "nation"))
simple("op_join_semi", "SELECT l_orderkey, l_linenumber, l_partkey FROM lineitem WHERE l_suppkey IN (SELECT s_suppkey FROM supplier WHERE s_acctbal > 5000)", "SELECT l_orderkey, l_linenumber, l_partkey FROM {lineitem} LEFT SEMI JOIN (SELECT s_suppkey FROM {supplier} WHERE s_acctbal > 5000) ON l_suppkey = s_suppkey", ("lineitem", "supplier"))
simple("op_join_anti", "SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)", "SELECT o_orderkey FROM {orders} LEFT ANTI JOIN {lineitem} ON o_orderkey = l_orderkey", ("orders", "lineitem"))
simple("op_join_cross", "SELECT r_name, n_name FROM {region} CROSS JOIN {nation} WHERE n_nationkey < 5", None, ("region", "nation"))


@query("op_join_range", "SELECT b.lo, CAST(count(*) AS BIGINT) AS n FROM lineitem JOIN (VALUES (0, 10), (10, 25), (25, 51)) b(lo, hi) ON l_quantity >= b.lo AND l_quantity < b.hi GROUP BY 1")
def op_join_range(spark: SparkSession, d: str) -> DataFrame:
    """Ranges are looked up in a sorted list of bounds, so each row costs its own bin and no nested loop."""
    edges = [0, 10, 25, 51]
    q = F.col("l_quantity")
    bin_no = F.aggregate(F.lit(edges), F.lit(0), lambda a, e: a + (q >= e).cast("int"))
    return load(spark, d, "lineitem").where((q >= edges[0]) & (q < edges[-1])).groupBy(F.element_at(F.lit(edges), bin_no).alias("lo")).agg(F.count("*").alias("n"))


query("op_join_interval", f"SELECT x.oid, CAST(count(*) AS BIGINT) AS alerts FROM ({oracle.LOG}) x JOIN (SELECT server, ended AS f FROM ({oracle.LOG}) WHERE event_type = 'error') y ON x.server = y.server AND x.ended > y.f AND x.started < y.f + INTERVAL 48 HOUR GROUP BY 1")(lambda spark, d: enrich.overlapping(datasets.query_log(spark, d), datasets.alert_intervals(spark, d)).groupBy("oid").agg(F.count("*").alias("alerts")))


@query("op_join_asof", f"SELECT x.oid, y.oid AS alert FROM ({oracle.LOG}) x ASOF LEFT JOIN (SELECT * FROM ({oracle.LOG}) WHERE event_type = 'error') y ON x.server = y.server AND x.started > y.started")
def op_join_asof(spark: SparkSession, d: str) -> DataFrame:
    """The last alert before each statement: one sort of the union in place of a join of ranges."""
    before = Window.partitionBy("server").orderBy("started").rowsBetween(Window.unboundedPreceding, -1)
    alert = F.when(F.col("kind") == "error", F.col("oid"))
    return datasets.query_log(spark, d).select("oid", F.last(alert, ignorenulls=True).over(before).alias("alert"))


simple("op_join_prefix", "SELECT a.n_name AS x, b.n_name AS y FROM {nation} a JOIN {nation} b ON a.n_regionkey = b.n_regionkey AND a.n_name < b.n_name", None, ("nation",))


@query("op_join_salted", "SELECT user_id, CAST(count(*) AS BIGINT) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1")
def op_join_salted(spark: SparkSession, d: str, salts: int = 8) -> DataFrame:
    """A hot key is spread over `salts` keys; the other side is repeated once a salt."""
    e = load(spark, d, "events").select("user_id", F.pmod(F.xxhash64("event_id"), F.lit(salts)).cast("int").alias("salt"))
    c = load(spark, d, "customer").select("c_custkey", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("c_salt"))
    return e.join(c, (e.user_id == c.c_custkey) & (e.salt == c.c_salt)).groupBy("user_id").agg(F.count("*").alias("n"))


simple("op_lateral", "SELECT o_orderkey, v FROM orders, (SELECT unnest([1, 2]) AS v)", "SELECT o_orderkey, v FROM {orders}, LATERAL explode(array(1, 2)) AS t(v)", ("orders",))

# ---- aggregates

D2 = "CAST({c} AS DECIMAL(18,2))"
simple("op_agg_moments", "SELECT event_type, CAST(count(*) AS BIGINT) AS n, CAST(sum(CAST(value AS DECIMAL(18,2))) AS DOUBLE) AS s1, min(value) AS lo, max(value) AS hi FROM {events} GROUP BY 1", None, ("events",))
simple("op_agg_distinct", "SELECT l_returnflag, CAST(count(DISTINCT l_partkey) AS BIGINT) AS parts FROM {lineitem} GROUP BY 1", None, ("lineitem",))
query("op_agg_approx_distinct")(lambda spark, d: load(spark, d, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts")))
simple("op_agg_percentile", "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS med, round(quantile_cont(value, 0.9), 6) AS q90 FROM events GROUP BY 1", "SELECT event_type, round(percentile(value, 0.5), 6) AS med, round(percentile(value, 0.9), 6) AS q90 FROM {events} GROUP BY 1", ("events",))
query("op_agg_percentile_approx")(lambda spark, d: load(spark, d, "events").groupBy("event_type").agg(F.percentile_approx("value", 0.5, 1000).alias("med"), F.expr("kll_sketch_get_quantile_double(kll_sketch_agg_double(value), 0.5D)").alias("kll")))
simple("op_agg_filter", "SELECT user_id, CAST(count(*) FILTER (WHERE event_type = 'error') AS BIGINT) AS errors, CAST(count(*) AS BIGINT) AS n FROM {events} GROUP BY 1", None, ("events",))
simple("op_agg_stddev", "SELECT event_type, round(stddev_pop(value), 4) AS sd, round(var_pop(value), 4) AS var FROM {events} GROUP BY 1", None, ("events",))
simple("op_agg_argmax", "SELECT event_type, max_by(event_id, value * 1000000 + event_id) AS top FROM events GROUP BY 1".replace("max_by", "arg_max"), "SELECT event_type, max_by(event_id, value * 1000000 + event_id) AS top FROM {events} GROUP BY 1", ("events",))
simple("op_agg_collect", "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1", "SELECT n_regionkey, array_join(array_sort(collect_list(n_name)), ',') AS names FROM {nation} GROUP BY 1", ("nation",))
simple("op_rollup", "SELECT l_returnflag, l_linestatus, CAST(count(*) AS BIGINT) AS n FROM {lineitem} GROUP BY ROLLUP (l_returnflag, l_linestatus)", None, ("lineitem",))
query("op_cube_subgroups", f"SELECT event_type, c_mktsegment, r_name, CAST(count(*) AS BIGINT) AS n, round(CAST(sum(t) AS DOUBLE) / count(*), 6) AS mean FROM ({EV}) GROUP BY CUBE (event_type, c_mktsegment, r_name)")(lambda spark, d: datasets.events_frame(spark, d, False).cube("event_type", "c_mktsegment", "r_name").agg(F.count("*").alias("n"), F.round(F.sum("t").cast("double") / F.count("*"), 6).alias("mean")))
simple("op_grouping_sets", "SELECT l_returnflag, l_linestatus, CAST(count(*) AS BIGINT) AS n FROM {lineitem} GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())", None, ("lineitem",))
query("op_pivot", "SELECT user_id, CAST(count(*) FILTER (WHERE event_type = 'click') AS BIGINT) AS click, CAST(count(*) FILTER (WHERE event_type = 'error') AS BIGINT) AS error FROM events GROUP BY 1")(lambda spark, d: load(spark, d, "events").groupBy("user_id").pivot("event_type", ["click", "error"]).agg(F.count("event_id")).na.fill(0))
query("op_unpivot", "SELECT c_custkey, 'c_name' AS attr, c_name AS v FROM customer UNION ALL SELECT c_custkey, 'c_mktsegment', c_mktsegment FROM customer")(lambda spark, d: load(spark, d, "customer").unpivot("c_custkey", ["c_name", "c_mktsegment"], "attr", "v"))
simple("op_having", "SELECT l_suppkey, CAST(count(DISTINCT l_orderkey) AS BIGINT) AS n FROM {lineitem} GROUP BY 1 HAVING count(DISTINCT l_orderkey) >= 550", None, ("lineitem",))
query("op_bitmap_count", "SELECT event_type, CAST(count(DISTINCT user_id) AS BIGINT) AS users FROM events GROUP BY 1")(lambda spark, d: load(spark, d, "events").groupBy("event_type", F.bitmap_bucket_number("user_id").alias("b")).agg(F.bitmap_count(F.bitmap_construct_agg(F.bitmap_bit_position("user_id"))).alias("c")).groupBy("event_type").agg(F.sum("c").alias("users")))
query("op_histogram", "SELECT CAST(CASE WHEN value >= 200 THEN 11 ELSE floor(value / 20) + 1 END AS BIGINT) AS bin, CAST(count(*) AS BIGINT) AS n FROM events GROUP BY 1")(lambda spark, d: load(spark, d, "events").groupBy(F.width_bucket("value", F.lit(0.0), F.lit(200.0), F.lit(10).cast("long")).alias("bin")).agg(F.count("*").alias("n")))
simple("op_corr", "SELECT round(corr(l_quantity, l_extendedprice), 6) AS r, round(covar_pop(l_quantity, l_extendedprice), 2) AS c FROM {lineitem}", None, ("lineitem",))

# ---- windows, sorts, sets

simple("op_rank", "SELECT p_partkey, CAST(rank() OVER (PARTITION BY p_brand ORDER BY p_size DESC) AS INTEGER) AS r, CAST(dense_rank() OVER (PARTITION BY p_brand ORDER BY p_size DESC) AS INTEGER) AS dr FROM {part}", None, ("part",))
simple("op_ntile", "SELECT p_partkey, CAST(ntile(4) OVER (PARTITION BY p_brand ORDER BY p_partkey) AS INTEGER) AS q, round(percent_rank() OVER (PARTITION BY p_brand ORDER BY p_partkey), 6) AS pr, round(cume_dist() OVER (PARTITION BY p_brand ORDER BY p_partkey), 6) AS cd FROM {part}", None, ("part",))
simple("op_lag", "SELECT event_id, lag(value) OVER (PARTITION BY user_id ORDER BY event_id) AS prev, lead(value) OVER (PARTITION BY user_id ORDER BY event_id) AS next FROM {events}", None, ("events",))
simple("op_running_sum", "SELECT event_id, CAST(sum(CAST(value AS DECIMAL(18,2))) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS DOUBLE) AS upto FROM {events}", None, ("events",))
simple("op_range_frame", "SELECT event_id, CAST(count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS BIGINT) AS day_before FROM events", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY unix_micros(CAST(ts AS TIMESTAMP)) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS day_before FROM {events}", ("events",))
simple("op_share", "SELECT event_type, round(CAST(count(*) AS DOUBLE) / sum(count(*)) OVER (), 6) AS share FROM {events} GROUP BY 1", None, ("events",))
simple("op_sort", "SELECT c_custkey, c_acctbal FROM {customer} ORDER BY c_acctbal DESC, c_custkey", None, ("customer",))
simple("op_topk", "SELECT event_id, value FROM {events} ORDER BY value DESC, event_id LIMIT 25", None, ("events",))
simple("op_topk_per_group", "SELECT event_type, event_id FROM (SELECT event_type, event_id, row_number() OVER (PARTITION BY event_type ORDER BY value DESC, event_id) AS r FROM {events}) WHERE r <= 5", None, ("events",))
simple("op_offset", "SELECT c_custkey FROM {customer} ORDER BY c_custkey LIMIT 10 OFFSET 20", None, ("customer",))
query("op_union", "SELECT c_custkey AS id, c_name AS name, NULL::VARCHAR AS brand FROM customer UNION ALL SELECT p_partkey, p_name, p_brand FROM part")(lambda spark, d: load(spark, d, "customer").select(F.col("c_custkey").alias("id"), F.col("c_name").alias("name")).unionByName(load(spark, d, "part").select(F.col("p_partkey").alias("id"), F.col("p_name").alias("name"), F.col("p_brand").alias("brand")), allowMissingColumns=True))
_A, _B = "SELECT event_id FROM {events} WHERE event_type = 'error'", "SELECT event_id FROM {events} WHERE value > 50"
simple("op_extent_intersect", f"{_A} INTERSECT {_B}", None, ("events",))
simple("op_extent_except", f"{_A} EXCEPT {_B}", None, ("events",))
simple("op_extent_union", f"{_A} UNION {_B}", None, ("events",))
simple("op_intersect_all", "SELECT l_partkey FROM {lineitem} WHERE l_quantity < 10 INTERSECT ALL SELECT l_partkey FROM {lineitem} WHERE l_quantity > 40", None, ("lineitem",))
simple("op_except_all", "SELECT l_partkey FROM {lineitem} WHERE l_quantity < 30 EXCEPT ALL SELECT l_partkey FROM {lineitem} WHERE l_quantity > 40", None, ("lineitem",))
query("op_dedupe", "SELECT DISTINCT event_type, user_id FROM events")(lambda spark, d: load(spark, d, "events").select("event_type", "user_id").dropDuplicates())

# ---- scalar functions

simple("op_str_basic", "SELECT p_partkey, upper(p_name) AS u, substring(p_name, 2, 3) AS s, replace(p_name, ' ', '_') AS r, lpad(p_brand, 10, '*') AS l, length(p_name) AS n, reverse(p_type) AS v, levenshtein(p_name, p_type) AS lev, concat_ws('-', p_brand, p_type) AS c, translate(p_type, 'AE', '43') AS t FROM {part}", None, ("part",))
simple("op_str_regex", "SELECT page_id, regexp_extract(url, '://([^/]+)', 1) AS host, regexp_replace(url, '[0-9]+', '#', 'g') AS masked FROM pages", "SELECT page_id, regexp_extract(url, '://([^/]+)', 1) AS host, regexp_replace(url, '[0-9]+', '#') AS masked FROM {pages}", ("pages",))
simple("op_str_hash", "SELECT p_partkey, md5(p_name) AS m, sha256(p_name) AS s FROM part", "SELECT p_partkey, md5(p_name) AS m, sha2(p_name, 256) AS s FROM {part}", ("part",))
simple("op_date", "SELECT event_id, CAST(hour(ts) AS INTEGER) AS h, CAST(isodow(ts) AS INTEGER) AS dow, CAST(date_trunc('month', ts) AS DATE) AS m, CAST(datediff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS INTEGER) AS days FROM events", "SELECT event_id, hour(ts) AS h, weekday(ts) + 1 AS dow, CAST(date_trunc('month', ts) AS DATE) AS m, datediff(CAST(ts AS DATE), DATE'2024-01-01') AS days FROM {events}", ("events",))
simple("op_math", "SELECT p_partkey, round(sqrt(p_retailprice), 6) AS s, round(ln(p_size + 1), 6) AS l, round(pow(p_size, 1.5), 4) AS p, p_size % 7 AS m, CAST(floor(p_retailprice) AS BIGINT) AS f, greatest(p_size, 10) AS g, least(p_size, 10) AS le, CAST(sign(p_size - 25) AS INTEGER) AS si FROM {part}", None, ("part",))
simple("op_decimal", "SELECT o_orderstatus, CAST(sum(CAST(o_totalprice AS DECIMAL(18,2))) AS VARCHAR) AS total FROM orders GROUP BY 1", "SELECT o_orderstatus, CAST(sum(CAST(o_totalprice AS DECIMAL(18,2))) AS STRING) AS total FROM {orders} GROUP BY 1", ("orders",))
query("op_array", "SELECT vec_id, len(embedding) AS n, round(CAST(list_max(embedding) AS DOUBLE), 6) AS hi, list_position(list_sort(embedding), embedding[1]) - 1 AS place FROM embeddings")(lambda spark, d: load(spark, d, "embeddings").select("vec_id", F.size("embedding").alias("n"), F.round(F.array_max("embedding").cast("double"), 6).alias("hi"), (F.array_position(F.array_sort("embedding"), F.element_at("embedding", 1)) - 1).alias("place")))
query("op_array_sets", "SELECT n_nationkey, list_sort(list_intersect([n_nationkey, n_regionkey, 3], [1, 2, 3, 4])) AS common, list_contains([1, 2, 3], n_regionkey) AS has FROM nation")(lambda spark, d: load(spark, d, "nation").select("n_nationkey", F.array_sort(F.array_intersect(F.array("n_nationkey", "n_regionkey", F.lit(3)), F.lit([1, 2, 3, 4]))).alias("common"), F.array_contains(F.lit([1, 2, 3]), F.col("n_regionkey")).alias("has")))
query("op_array_hof", "SELECT vec_id, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) AS positive, list_min(embedding) > -0.2 AS mild FROM embeddings")(lambda spark, d: load(spark, d, "embeddings").select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.forall("embedding", lambda x: x > F.lit(-0.2)).alias("mild")))
query("op_explode", "SELECT vec_id, CAST(generate_subscripts(embedding, 1) - 1 AS INTEGER) AS i, round(CAST(unnest(embedding) AS DOUBLE), 6) AS x FROM embeddings")(lambda spark, d: load(spark, d, "embeddings").select("vec_id", F.posexplode("embedding").alias("i", "x")).select("vec_id", "i", F.round(F.col("x").cast("double"), 6).alias("x")))
query("op_map", f"SELECT oid, CAST(count(*) AS INTEGER) AS brands FROM (SELECT DISTINCT oid, token FROM ({oracle.ORDER_TOKENS}) WHERE token LIKE 'BRAND%') GROUP BY 1")(lambda spark, d: datasets.orders_set(spark, d).df.select("oid", F.size(F.map_filter("tokens", lambda k, v: k.startswith("BRAND"))).alias("brands")).where("brands > 0"))
query("op_struct", "SELECT n_nationkey, n_name || '/' || r_name AS path FROM nation JOIN region ON n_regionkey = r_regionkey")(lambda spark, d: (lambda n, r: n.join(F.broadcast(r), n.n_regionkey == r.r_regionkey).select("n_nationkey", F.struct("n_name", "r_name").alias("s")).select("n_nationkey", F.concat_ws("/", "s.n_name", "s.r_name").alias("path")))(load(spark, d, "nation"), load(spark, d, "region")))
query("op_json", "SELECT event_id, CAST(regexp_extract(props, '[0-9]+') AS INTEGER) AS k FROM events")(lambda spark, d: load(spark, d, "events").select("event_id", F.from_json("props", "k int").getField("k").alias("k")))
query("op_json_variant", "SELECT event_id, CAST(regexp_extract(props, '[0-9]+') AS INTEGER) AS k FROM events")(lambda spark, d: load(spark, d, "events").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "int").alias("k")))
query("op_vector", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 5) AS norm2 FROM embeddings")(lambda spark, d: load(spark, d, "embeddings").select("vec_id", F.round(F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda a, b: a + b), 5).alias("norm2")))
simple("op_url", "SELECT page_id, regexp_extract(url, '^([a-z]+)://', 1) AS scheme, regexp_extract(url, '://([^/?#]+)', 1) AS host FROM pages", "SELECT page_id, try_parse_url(url, 'PROTOCOL') AS scheme, try_parse_url(url, 'HOST') AS host FROM {pages}", ("pages",))

# ---- functions of the user's own


@query("sql_score_functions", f"WITH ds AS ({EV}), g AS ({oracle._NORMS}), c AS (SELECT event_type, {oracle._STATS} FROM ds GROUP BY 1) SELECT event_type, round({oracle.score('wracc')}, 6) AS wracc, round({oracle.score('mean_test')}, 6) AS mean_test, round({oracle.score('lift')}, 6) AS lift, round({oracle.score('tscore')}, 6) AS tscore, round({oracle.score('median_0.5')}, 6) AS qmed FROM c, g")
def sql_score_functions(spark: SparkSession, d: str) -> DataFrame:
    from slowlens.functions import sqlfunctions

    sqlfunctions.register(spark)
    rows = datasets.events_frame(spark, d, False).select("event_type", "t")
    g = rows.agg(F.count("*").cast("double").alias("gn"), (F.sum("t").cast("double") / F.count("*")).alias("mu0"), F.percentile(F.col("t").cast("double"), 0.5).alias("med0"))
    c = rows.groupBy("event_type").agg(F.count("*").cast("double").alias("n"), F.sum("t").cast("double").alias("s1"), F.sum(F.col("t") * F.col("t")).cast("double").alias("s2"), F.percentile(F.col("t").cast("double"), 0.5).alias("med"))
    return c.join(F.broadcast(g)).selectExpr("event_type", "round(sg_wracc(n, s1, gn, mu0), 6) AS wracc", "round(sg_mean_test(n, s1, gn, mu0), 6) AS mean_test", "round(sg_lift(n, s1, mu0), 6) AS lift", "round(sg_tscore(n, s1, s2, gn, mu0), 6) AS tscore", "round(sg_qmed(n, med, gn, med0, 0.5D), 6) AS qmed")


@query("udf_grouped_search", f"WITH e AS ({EV}), g AS (SELECT c_mktsegment, count(*) AS tot, CAST(sum(t) AS DOUBLE) / count(*) AS mu0 FROM e GROUP BY 1), c AS (SELECT c_mktsegment, event_type, count(*) AS n, CAST(sum(t) AS DOUBLE) AS s1 FROM e GROUP BY 1, 2), x AS (SELECT c.*, round(CAST(n AS DOUBLE) / tot * (s1 / n - mu0), 6) AS score FROM c JOIN g ON c.c_mktsegment = g.c_mktsegment) SELECT c_mktsegment, event_type, score FROM x QUALIFY row_number() OVER (PARTITION BY c_mktsegment ORDER BY score DESC, event_type) = 1")
def udf_grouped_search(spark: SparkSession, d: str) -> DataFrame:
    """An exact small search inside each slice: one group is one slice's counts, not its rows."""
    e = datasets.events_frame(spark, d, False)
    counts = e.groupBy("c_mktsegment", "event_type").agg(F.count("*").alias("n"), F.sum("t").cast("double").alias("s1"))

    def best(pdf: pd.DataFrame) -> pd.DataFrame:
        total, mean = pdf["n"].sum(), pdf["s1"].sum() / pdf["n"].sum()
        pdf["score"] = (pdf["n"] / total * (pdf["s1"] / pdf["n"] - mean)).round(6)
        return pdf.sort_values(["score", "event_type"], ascending=[False, True]).head(1)[["c_mktsegment", "event_type", "score"]]

    return counts.groupBy("c_mktsegment").applyInPandas(best, "c_mktsegment string, event_type string, score double")


@query("udaf_trimmed_mean", "WITH q AS (SELECT event_type, value, quantile_cont(value, 0.05) OVER (PARTITION BY event_type) AS lo, quantile_cont(value, 0.95) OVER (PARTITION BY event_type) AS hi FROM events) SELECT event_type, round(avg(value), 4) AS trimmed FROM q WHERE value BETWEEN lo AND hi GROUP BY 1")
def udaf_trimmed_mean(spark: SparkSession, d: str) -> DataFrame:
    """A pandas aggregate as a measure of the user's own; it holds one group's values at a time."""

    @F.pandas_udf("double")
    def trimmed(v: pd.Series) -> float:
        lo, hi = v.quantile(0.05), v.quantile(0.95)
        return float(v[(v >= lo) & (v <= hi)].mean())

    return load(spark, d, "events").groupBy("event_type").agg(trimmed("value").alias("x")).select("event_type", F.round("x", 4).alias("trimmed"))
