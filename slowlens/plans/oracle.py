"""DuckDB statements that compute the same results on their own: datasets, selectors, and searches as chains of CTEs."""

from __future__ import annotations

from slowlens.sources.datasets import BUSY, LEVEL_CUTS, LEVELS, TOY, TOY_COLUMNS, TYPES, WAIT_HOURS

ENV = "customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"
LOG = "SELECT event_id AS oid, user_id AS server, ts AS started, CAST(value AS DECIMAL(18,2)) AS time_s, CAST(regexp_extract(props, '[0-9]+') AS INTEGER) AS k, event_type, ts + to_microseconds(greatest(CAST(CAST(value AS DECIMAL(18,2)) * 1000000 AS BIGINT), 1)) AS ended FROM events"
_LEVEL = f"CASE WHEN time_s > {LEVEL_CUTS[2]} THEN 4 WHEN time_s > {LEVEL_CUTS[1]} THEN 3 WHEN time_s > {LEVEL_CUTS[0]} THEN 2 ELSE 1 END"
_WAITS = ", ".join(f"CAST(count(*) FILTER (WHERE wk = '{c}') AS BIGINT) AS w_{c}" for c in TYPES)
#: every period of ten seconds of every run, and the sessions that wait in it
BUSY_SQL = f"""
SELECT oid AS bo, CASE WHEN max(x) >= {BUSY} THEN 1 ELSE 0 END AS busy FROM (
  SELECT oid, a, sum(least(b, t) - greatest(a, f)) / CAST(b - a AS DOUBLE) AS x FROM (
    SELECT oid, server, a, least(a + 10000000, e) AS b FROM (SELECT *, unnest(range(s, e, 10000000)) AS a FROM (SELECT oid, server, epoch_us(started) AS s, epoch_us(ended) AS e FROM ({LOG})))) p
  JOIN (SELECT server AS v, epoch_us(started) AS f, epoch_us(started) + {WAIT_HOURS} * 3600000000 AS t FROM ({LOG})) w ON p.server = w.v AND f < b AND t > a
  GROUP BY oid, a, b) GROUP BY oid"""
EVENTS_PLAIN = f"SELECT l.*, hour(started) AS hour, isodow(started) AS dow, c_mktsegment, c_acctbal, n_name, r_name, time_s AS t FROM ({LOG}) l LEFT JOIN ({ENV}) ON server = c_custkey"
EVENTS = f"""
SELECT p.*, w.* EXCLUDE (wo), CASE a.lv {' '.join(f"WHEN {i + 1} THEN '{v}'" for i, v in enumerate(LEVELS))} END AS a_error,
  b.busy, CASE WHEN a.lv = 4 THEN 1 ELSE 0 END AS crit
FROM ({EVENTS_PLAIN}) p
JOIN (SELECT x.oid AS wo, {_WAITS} FROM ({LOG}) x JOIN (SELECT server AS ws, started AS wf, event_type AS wk FROM ({LOG})) y
  ON x.server = ws AND wf < x.ended AND wf + INTERVAL {WAIT_HOURS} HOUR > x.started GROUP BY 1) w ON p.oid = w.wo
JOIN ({BUSY_SQL}) b ON p.oid = b.bo
LEFT JOIN (SELECT x.oid AS ao, max(y.lv) AS lv FROM ({LOG}) x JOIN (SELECT server, ended AS f, {_LEVEL} AS lv FROM ({LOG}) WHERE event_type = 'error') y
  ON x.server = y.server AND x.ended > y.f AND x.started < y.f + INTERVAL 48 HOUR GROUP BY 1) a ON p.oid = a.ao
"""
LINES = """
SELECT hash(l) AS oid, l_returnflag, l_linestatus, l_quantity, l_discount, l_tax, p_brand, p_type, p_size, n_name, n_regionkey AS s_regionkey, o_orderpriority, c_mktsegment, year(l_shipdate) AS ship_year,
  l_suppkey, o_custkey, CAST(l_extendedprice AS DECIMAL(18,2)) AS price, CASE WHEN l_extendedprice / l_quantity > 2500 THEN 1 ELSE 0 END AS dear, CAST(l_extendedprice AS DECIMAL(18,2)) AS t
FROM lineitem l JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey
"""
ORDERS = "SELECT o_orderkey AS oid, o_orderpriority, o_orderstatus, c_mktsegment, CAST(o_totalprice AS DECIMAL(18,2)) AS total, CAST(o_totalprice AS DECIMAL(18,2)) AS t, CASE WHEN o_orderstatus = 'F' THEN 1 ELSE 0 END AS finished FROM orders JOIN customer ON o_custkey = c_custkey"
ORDER_TOKENS = "SELECT l_orderkey AS oid, unnest(['BRAND_' || p_brand, 'TYPE_' || p_type, 'PART_' || p_partkey]) AS token FROM lineitem JOIN part ON l_partkey = p_partkey"
DOCS = "SELECT d.doc_id AS oid, lang, source, n_chars, n_words, n_lines, CASE WHEN quality = 0 THEN 1 ELSE 0 END AS bad, toxic, n_chars AS t FROM (SELECT doc_id, concat(lang, '') AS lang, concat(source, '') AS source, n_chars, len(list_filter(string_split(lower(text), ' '), lambda w: w <> '')) AS n_words, len(string_split(text, chr(10))) AS n_lines FROM documents) d JOIN labels l ON d.doc_id = l.doc_id"
DOC_TOKENS = "SELECT oid, token FROM (SELECT doc_id AS oid, unnest(string_split(lower(concat(text, '')), ' ')) AS token FROM documents) WHERE token <> '' AND oid IN (SELECT doc_id FROM labels)"
PAGES = "SELECT page_id AS oid, regexp_extract(url, '^([a-z]+)://', 1) AS scheme, regexp_extract(url, '^[a-z]+://[^/?#]*?([a-z]+)(?:[/?#]|$)', 1) AS domain, CASE WHEN contains(url, '?') THEN 1 ELSE 0 END AS has_query, length(html) AS t FROM pages"
PAGE_TOKENS = "SELECT page_id AS oid, 'TAG_' || unnest(regexp_extract_all(html, '<([a-z][a-z0-9]*)', 1)) AS token FROM pages"
TURNS = "SELECT conv_id, turn, (conv_id, turn) AS oid, role, coalesce(lag(role) OVER (PARTITION BY conv_id ORDER BY turn), 'none') AS prev_role, length(text) AS n_chars, length(text) AS t, CASE WHEN role = 'assistant' THEN 1 ELSE 0 END AS answers FROM conversations"
TOY_SQL = "SELECT * FROM (VALUES " + ", ".join("(" + ", ".join(f"'{v}'" if isinstance(v, str) and not v[0].isdigit() else str(v) for v in r) + ")" for r in TOY) + f") v({', '.join(c.split()[0] for c in TOY_COLUMNS.split(', '))})"


def vectors(components: int, label: int = 0) -> str:
    return f"SELECT vec_id AS oid, {', '.join(f'CAST(embedding[{i + 1}] AS DOUBLE) AS e{i}' for i in range(components))}, label, CASE WHEN label = {label} THEN 1 ELSE 0 END AS t FROM embeddings"


# ---- selectors: (oid, t, label, key, blocks)


def nominal(attr: str) -> str:
    return f"SELECT oid, t, '{attr}=' || {attr} AS label, '{attr}|point' AS key, ['{attr}|point', '{attr}|low', '{attr}|high'] AS blocks FROM ds WHERE {attr} IS NOT NULL"


def cut(attr: str, c: object) -> str:
    low = f"SELECT oid, t, '{attr}>={c}', '{attr}|low', ['{attr}|point', '{attr}|low'] FROM ds WHERE {attr} >= {c}"
    return f"{low} UNION ALL SELECT oid, t, '{attr}<{c}', '{attr}|high', ['{attr}|point', '{attr}|high'] FROM ds WHERE {attr} < {c}"


def token_counts(source: str) -> str:
    return f"SELECT oid, t, token || '>0', 'token|' || token, ['token|' || token] FROM (SELECT DISTINCT oid, token FROM ({source})) k JOIN ds USING (oid)"


def selectors(nominals: tuple[str, ...] = (), cuts: dict[str, list] | None = None, tokens: str | None = None) -> str:
    parts = [nominal(a) for a in nominals] + [cut(a, c) for a, cs in (cuts or {}).items() for c in cs]
    first = "SELECT NULL::BIGINT AS oid, NULL AS t, '' AS label, '' AS key, ['']::VARCHAR[] AS blocks WHERE false"
    if not nominals:
        parts = [p.replace("SELECT oid, t, ", "SELECT oid, t, ", 1) for p in parts]
        parts[0] = parts[0].replace("SELECT oid, t, ", "SELECT * FROM (SELECT oid, t, ", 1) + ") v(oid, t, label, key, blocks)" if "UNION ALL" not in parts[0] else f"SELECT * FROM ({parts[0]}) v(oid, t, label, key, blocks)"
    del first
    return " UNION ALL ".join(parts + ([token_counts(tokens)] if tokens else []))


SCORES = {
    "support": "n / tot", "average": "s1 / n - mu0", "lift": "s1 / n / mu0", "wracc": "n / tot * (s1 / n - mu0)", "wracc_binary": "s1 / tot - n / tot * mu0", "wracc_abs": "abs(n / tot * (s1 / n - mu0))",
    "mean_test": "sqrt(n / tot) * (s1 / n - mu0)", "binomial": "sqrt(n) * (s1 / n - mu0) / sqrt(mu0 * (1 - mu0))", "precision": "s1 / n", "median_ratio": "med / med0",
    "tscore": "CASE WHEN n >= 2 AND sqrt(greatest(s2 / n - s1 / n * (s1 / n), 0)) > 1e-9 THEN sqrt(n / tot) / sqrt(greatest(s2 / n - s1 / n * (s1 / n), 0)) * (s1 / n - mu0) END",
}


def score(measure: str) -> str:
    if measure in SCORES:
        return SCORES[measure]
    if measure.startswith("low_"):
        return f"-({score(measure[4:])})"
    kind, _, a = measure.partition("_")
    a = a or "0.5"
    return f"pow(n / tot, {a}) * (s1 / n - mu0)" if kind == "klosgen" else f"pow(n / tot, {a}) * (med - med0)"


_STATS = "CAST(count(*) AS DOUBLE) AS n, CAST(sum(t) AS DOUBLE) AS s1, CAST(sum(CAST(t AS DOUBLE) * CAST(t AS DOUBLE)) AS DOUBLE) AS s2, median(CAST(t AS DOUBLE)) AS med, bit_xor(hash(oid)) AS sx, sum(hash(oid) // 2) AS ss"
_NORMS = "SELECT CAST(count(*) AS DOUBLE) AS tot, CAST(sum(t) AS DOUBLE) / count(*) AS mu0, median(CAST(t AS DOUBLE)) AS med0 FROM ds"


def search(ds: str, sel: str, measure: str, k: int = 10, depth: int = 2, width: int | None = None, min_support: int | None = None, ties: bool = False, target: str | None = None, levels: bool = False, stats: str = "") -> str:
    """The best k patterns; width None keeps all (exhaustive), else the best width extents of each level."""
    floor = str(min_support) if min_support is not None else "greatest(5, ceil(tot / 1000))"
    base = f"SELECT * REPLACE ({target} AS t) FROM ({ds})" if target and target != "t" else ds
    parts = [f"ds AS MATERIALIZED ({base})", f"g AS ({_NORMS})", f"sel AS MATERIALIZED ({sel})", "m0 AS (SELECT oid, t, []::VARCHAR[] AS labels, []::VARCHAR[] AS blocked FROM ds)"]
    for d in range(1, depth + 1):
        grown = f"SELECT DISTINCT ON (m.oid, list_sort(list_append(m.labels, s.label))) m.oid, m.t, list_sort(list_append(m.labels, s.label)) AS labels, list_concat(m.blocked, s.blocks) AS blocked FROM m{d - 1} m JOIN sel s ON m.oid = s.oid WHERE NOT list_contains(m.blocked, s.key)"
        if d == 1:
            grown = "SELECT oid, t, [label] AS labels, blocks AS blocked FROM sel"
        parts.append(f"c{d} AS MATERIALIZED ({grown})")
        scored = f"SELECT *, {d} AS n_sel, array_to_string(labels, ' & ') AS description, round({score(measure)}, 9) AS score FROM (SELECT labels, {_STATS} FROM c{d} GROUP BY labels), g WHERE n >= {floor}"
        scored = f"SELECT * FROM ({scored}) WHERE score IS NOT NULL"
        if width is not None:
            scored = f"SELECT * FROM ({scored}) QUALIFY row_number() OVER (PARTITION BY n, sx, ss ORDER BY n_sel, description) = 1 ORDER BY score DESC, n_sel, description LIMIT {width}"
        parts.append(f"k{d} AS MATERIALIZED ({scored})")
        parts.append(f"m{d} AS (SELECT c.* FROM c{d} c JOIN k{d} k ON c.labels = k.labels)")
    every = " UNION ALL ".join(f"SELECT * FROM k{d}" for d in range(1, depth + 1))
    head = "WITH " + ", ".join(parts)
    if levels:
        return f"{head} SELECT n_sel AS level, description, CAST(n AS BIGINT) AS size, score FROM ({every})"
    one = f"SELECT * FROM ({every}) QUALIFY row_number() OVER (PARTITION BY n, sx, ss ORDER BY n_sel, description) = 1"
    rank = "rank() OVER (ORDER BY score DESC)" if ties else "row_number() OVER (ORDER BY score DESC, n_sel, description)"
    extra = f", {stats}" if stats else ""
    return f"{head} SELECT CAST(rk AS INTEGER) AS rank, description, CAST(n_sel AS INTEGER) AS n_sel, CAST(n AS BIGINT) AS size, round(s1 / n, 6) AS mean, score{extra} FROM (SELECT *, {rank} AS rk FROM ({one})) WHERE rk <= {k}"
