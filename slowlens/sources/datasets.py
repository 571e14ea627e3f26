"""Datasets for the experiments, built on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from slowlens.operators import enrich, targets
from slowlens.operators.dataset import SubgroupDataset
from slowlens.session import load

#: Alert levels in rising order, event types, and the value above which an error has each level.
LEVELS = ("Info", "Alarm", "Critical", "Blocking")
TYPES = ("click", "error", "purchase", "signup", "view")
LEVEL_CUTS = (35, 70, 150)
#: Hours that a session of the log waits, and waiting sessions from which a run has an issue of concurrence.
WAIT_HOURS, BUSY = 24, 6

#: The toy table of eleven statements.
TOY_COLUMNS = "oid string, from_a int, from_b int, where_a_key int, where_a_date int, where_b_key int, soft_version string, site string, alert_sessions string, concurrency double, nrows int, time_s decimal(18,2), slow int"
TOY = [
    ("o1", 1, 0, 1, 0, 0, "v2", "LYN", "Alarm", 22, 10, "2.15", 0),
    ("o2", 1, 0, 1, 1, 0, "v1", "BLV", "Critical", 3, 1, "15.81", 1),
    ("o3", 0, 1, 0, 0, 1, "v1", "BLV", "Critical", 15, 27, "1.14", 0),
    ("o4", 1, 1, 0, 1, 1, "v2", "LYN", "Alarm", 31, 12, "10.87", 1),
    ("o5", 1, 1, 1, 0, 1, "v3", "LYN", "Alarm", 11, 25, "2.10", 0),
    ("o6", 1, 0, 1, 2, 0, "v3", "LYN", "Critical", 6, 100, "17.93", 1),
    ("o7", 1, 1, 1, 1, 1, "v2", "LYN", "Info", 27, 1, "15.80", 1),
    ("o8", 0, 1, 0, 0, 1, "v2", "BLV", "Alarm", 9, 37, "9.95", 0),
    ("o9", 1, 0, 1, 0, 0, "v3", "BLV", "Critical", 10, 112, "8.95", 0),
    ("o10", 0, 1, 0, 0, 1, "v2", "BLV", "Alarm", 7, 1, "14.70", 1),
    ("o11", 0, 1, 0, 0, 0, "v2", "LYN", "Info", 25, 16, "1.00", 0),
]

def toy_frame(spark: SparkSession) -> DataFrame:
    rows = ", ".join("(" + ", ".join(f"'{v}'" if isinstance(v, str) and not v[0].isdigit() else str(v) for v in r) + ")" for r in TOY)
    names = [c.split()[0] for c in TOY_COLUMNS.split(", ")]
    kinds = [c.split()[1] for c in TOY_COLUMNS.replace("(18,2)", "").split(", ")]
    raw = spark.sql(f"SELECT * FROM VALUES {rows} AS v({', '.join(names)})")
    return raw.select(*[F.col(n).cast("decimal(18,2)" if k == "decimal" else k).alias(n) for n, k in zip(names, kinds, strict=True)])

def toy(spark: SparkSession, target: str = "time_s") -> SubgroupDataset:
    df = toy_frame(spark).withColumn("t", F.col(target))
    return SubgroupDataset(df, numeric=("concurrency", "nrows"), nominal=("soft_version", "site"), ordinal={"alert_sessions": LEVELS}, boolean=())

def query_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    """events as a log of statements: oid, server, started, time_s, nrows, kind, ended."""
    e = load(spark, sf_dir, "events")
    log = e.select(F.col("event_id").alias("oid"), F.col("user_id").alias("server"), F.col("ts").cast("timestamp").alias("started"), F.col("value").cast("decimal(18,2)").alias("time_s"), F.get_json_object("props", "$.k").cast("int").alias("nrows"), F.col("event_type").alias("kind"))
    return log.withColumn("ended", enrich.run_end(F.col("started"), F.col("time_s")))

def environment(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Properties of each server: customers with nation and region."""
    c, n, r = (load(spark, sf_dir, t) for t in ("customer", "nation", "region"))
    return c.join(n, c.c_nationkey == n.n_nationkey).join(r, n.n_regionkey == r.r_regionkey).select(F.col("c_custkey").alias("server"), "c_mktsegment", "c_acctbal", "n_name", "r_name")

def alert_intervals(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Errors as alerts: raised when the statement ends, on for 48 hours at its server."""
    v = F.col("time_s")
    level = F.when(v > LEVEL_CUTS[2], LEVELS[3]).when(v > LEVEL_CUTS[1], LEVELS[2]).when(v > LEVEL_CUTS[0], LEVELS[1]).otherwise(LEVELS[0])
    log = query_log(spark, sf_dir).where("kind = 'error'")
    return log.select("server", F.lit("error").alias("kind"), level.alias("level"), F.col("ended").alias("from_ts"), (F.col("ended") + F.expr("INTERVAL 48 HOURS")).alias("to_ts"))

def waiting_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every event as a session of its class that waits WAIT_HOURS at its server."""
    later = F.col("started") + F.expr(f"INTERVAL {WAIT_HOURS} HOURS")
    return query_log(spark, sf_dir).select("server", "kind", F.col("started").alias("from_ts"), later.alias("to_ts"))

def events_frame(spark: SparkSession, sf_dir: str, context: bool = True) -> DataFrame:
    """Statements with clock and environment and, with `context`, waits (w_*), alerts (a_error), busy and crit."""
    log = query_log(spark, sf_dir)
    out = enrich.with_env(enrich.with_clock(log), environment(spark, sf_dir), "server")
    if context:
        waits = waiting_sessions(spark, sf_dir)
        out = enrich.with_waits(out, waits, list(TYPES))
        out = enrich.with_alerts(out, alert_intervals(spark, sf_dir), ["error"], LEVELS)
        out = targets.concurrence(out, waits, BUSY).withColumnRenamed("concurrence", "busy").withColumn("crit", F.coalesce(F.col("a_error") == "Blocking", F.lit(False)).cast("int"))
    return out.select(*out.columns, F.col("kind").alias("event_type"), F.col("nrows").alias("k"), F.col("time_s").alias("t")).drop("kind", "nrows")

def events_set(spark: SparkSession, sf_dir: str, target: str = "time_s", context: bool = False) -> SubgroupDataset:
    """DS-E."""
    df = events_frame(spark, sf_dir, context or target in ("busy", "crit"))
    df = df.withColumn("t", (F.col("time_s") > 25).cast("int") if target == "slow" else F.col(target))
    numeric = ("k", "hour", "dow", "c_acctbal") + (tuple(f"w_{c}" for c in TYPES) if context else ())
    return SubgroupDataset(df, numeric=numeric, nominal=("event_type", "c_mktsegment", "r_name", "n_name"), ordinal={"a_error": LEVELS} if context else {})

def lineitem_frame(spark: SparkSession, sf_dir: str) -> DataFrame:
    line, part, supp, nation, orders, cust = (load(spark, sf_dir, t) for t in ("lineitem", "part", "supplier", "nation", "orders", "customer"))
    supply = supp.join(F.broadcast(nation), supp.s_nationkey == nation.n_nationkey).select("s_suppkey", "n_name", F.col("n_regionkey").alias("s_regionkey"))
    order = orders.join(cust, orders.o_custkey == cust.c_custkey).select("o_orderkey", "o_custkey", "o_orderpriority", "c_mktsegment")
    whole = F.xxhash64(*[F.col(c) for c in line.columns])
    rows = line.withColumn("oid", whole).join(part, line.l_partkey == part.p_partkey).join(supply, line.l_suppkey == supply.s_suppkey).join(order, line.l_orderkey == order.o_orderkey)
    price = F.col("l_extendedprice").cast("decimal(18,2)")
    return rows.select(
        "oid", "l_returnflag", "l_linestatus", "l_quantity", "l_discount", "l_tax", "p_brand", "p_type", "p_size", "n_name", "s_regionkey", "o_orderpriority", "c_mktsegment", F.year("l_shipdate").alias("ship_year"),
        "l_suppkey", "o_custkey", price.alias("price"), (F.col("l_extendedprice") / F.col("l_quantity") > 2500).cast("int").alias("dear"), price.alias("t"),
    )

def lineitem_set(spark: SparkSession, sf_dir: str, target: str = "price") -> SubgroupDataset:
    """DS-L."""
    df = lineitem_frame(spark, sf_dir).withColumn("t", F.col(target))
    return SubgroupDataset(df, numeric=("l_quantity", "l_discount", "l_tax", "p_size", "ship_year"), nominal=("l_returnflag", "l_linestatus", "p_brand", "p_type", "n_name", "o_orderpriority", "c_mktsegment"))

def _counted(pairs: DataFrame) -> DataFrame:
    """(oid, token) -> (oid, tokens): counts as a map."""
    counts = pairs.groupBy("oid", "token").agg(F.count("*").cast("int").alias("c"))
    return counts.groupBy("oid").agg(F.map_from_entries(F.collect_list(F.struct("token", "c"))).alias("tokens"))

def orders_set(spark: SparkSession, sf_dir: str, target: str = "total") -> SubgroupDataset:
    """DS-O: brands, types and parts of an order as token counts."""
    orders, line, part, cust = (load(spark, sf_dir, t) for t in ("orders", "lineitem", "part", "customer"))
    bag = F.explode(F.array(F.concat(F.lit("BRAND_"), "p_brand"), F.concat(F.lit("TYPE_"), "p_type"), F.concat(F.lit("PART_"), F.col("p_partkey").cast("string"))))
    pairs = line.join(part, line.l_partkey == part.p_partkey).select(F.col("l_orderkey").alias("oid"), bag.alias("token"))
    base = orders.join(cust, orders.o_custkey == cust.c_custkey).select(F.col("o_orderkey").alias("key"), "o_orderpriority", "o_orderstatus", "c_mktsegment", F.col("o_totalprice").cast("decimal(18,2)").alias("total"), (F.col("o_orderstatus") == "F").cast("int").alias("finished"))
    df = base.join(_counted(pairs), F.col("key") == F.col("oid"), "left").drop("oid").withColumnRenamed("key", "oid")
    df = df.withColumn("tokens", F.coalesce("tokens", F.create_map().cast("map<string,int>"))).withColumn("t", F.col(target))
    nominal = ("c_mktsegment",) + (() if target == "finished" else ("o_orderstatus",))
    return SubgroupDataset(df, nominal=nominal, ordinal={"o_orderpriority": ("5-LOW", "4-NOT SPECIFIED", "3-MEDIUM", "2-HIGH", "1-URGENT")}, tokens="tokens")

def documents_set(spark: SparkSession, sf_dir: str, target: str = "bad") -> SubgroupDataset:
    """DS-D: words split on one blank, lower-cased, as tokens."""
    docs = load(spark, sf_dir, "documents").join(load(spark, sf_dir, "labels"), "doc_id")
    words = F.filter(F.split(F.lower("text"), " "), lambda w: w != "")
    pairs = docs.select(F.col("doc_id").alias("oid"), F.explode(words).alias("token"))
    base = docs.select(F.col("doc_id").alias("key"), "lang", "source", F.col("n_chars").cast("bigint").alias("n_chars"), F.size(words).alias("n_words"), F.size(F.split("text", "\n")).alias("n_lines"), (F.col("quality") == 0).cast("int").alias("bad"), F.col("toxic").cast("int").alias("toxic"))
    df = base.join(_counted(pairs), F.col("key") == F.col("oid"), "left").drop("oid").withColumnRenamed("key", "oid").withColumn("tokens", F.coalesce("tokens", F.create_map().cast("map<string,int>")))
    return SubgroupDataset(df.withColumn("t", F.col(target)), numeric=("n_chars", "n_words", "n_lines") if target != "n_chars" else ("n_words", "n_lines"), nominal=("lang", "source"), tokens="tokens")

def pages_set(spark: SparkSession, sf_dir: str) -> SubgroupDataset:
    """DS-P: tag counts, scheme and top domain; the target is the length of the page."""
    pages = load(spark, sf_dir, "pages")
    tags = F.regexp_extract_all("html", F.lit("<([a-z][a-z0-9]*)"), 1)
    pairs = pages.select(F.col("page_id").alias("oid"), F.explode(F.transform(tags, lambda t: F.concat(F.lit("TAG_"), t))).alias("token"))
    base = pages.select(F.col("page_id").alias("key"), F.regexp_extract("url", "^([a-z]+)://", 1).alias("scheme"), F.regexp_extract("url", r"^[a-z]+://[^/?#]*?([a-z]+)(?:[/?#]|$)", 1).alias("domain"), F.col("url").contains("?").cast("int").alias("has_query"), F.length("html").alias("t"))
    df = base.join(_counted(pairs), F.col("key") == F.col("oid"), "left").drop("oid").withColumnRenamed("key", "oid").withColumn("tokens", F.coalesce("tokens", F.create_map().cast("map<string,int>")))
    return SubgroupDataset(df, nominal=("scheme", "domain"), boolean=("has_query",), tokens="tokens")

def categories(df: DataFrame, column: str, most: int = 1000) -> list:
    """All values of a nominal target, sorted; over `most` of them are refused, not cut."""
    found = [r[0] for r in df.select(column).where(F.col(column).isNotNull()).distinct().limit(most + 1).collect()]
    if len(found) > most:
        raise ValueError(f"over {most} values of {column}")
    return sorted(found)

def embeddings_set(spark: SparkSession, sf_dir: str, label: int = 0, components: int = 64) -> SubgroupDataset:
    """DS-V: components as numeric attributes, one label against the rest."""
    v = load(spark, sf_dir, "embeddings")
    df = v.select(F.col("vec_id").alias("oid"), *[F.element_at("embedding", i + 1).cast("double").alias(f"e{i}") for i in range(components)], "label", (F.col("label") == label).cast("int").alias("t"))
    return SubgroupDataset(df, numeric=tuple(f"e{i}" for i in range(components)))

def conversations_set(spark: SparkSession, sf_dir: str, target: str = "n_chars") -> SubgroupDataset:
    """DS-C: turns with the role before."""
    from pyspark.sql import Window

    c = load(spark, sf_dir, "conversations")
    before = F.coalesce(F.lag("role").over(Window.partitionBy("conv_id").orderBy("turn")), F.lit("none"))
    df = c.select(F.struct("conv_id", "turn").alias("oid"), "turn", "role", before.alias("prev_role"), F.length("text").alias("n_chars"), (F.col("role") == "assistant").cast("int").alias("answers"))
    df = df.withColumn("t", F.col(target))
    return SubgroupDataset(df, numeric=("turn",) + (("n_chars",) if target != "n_chars" else ()), nominal=("prev_role",) + (("role",) if target != "answers" else ()))
