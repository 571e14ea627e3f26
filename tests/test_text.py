"""The statement reader: golden statement, templates, edge texts, and random statements with known counts."""

import random
from collections import Counter

from slowlens.functions.sqltext import is_select, lex, parse_clauses, parse_flat, with_tokens
from slowlens.plans.text_queries import FLAT, TEMPLATES, TOKENS

GOLDEN = """SELECT o.o_orderkey, c.c_name FROM orders AS o JOIN customer AS c ON o.o_custkey = c.c_custkey
WHERE o.o_totalprice > 100 AND (c.c_acctbal < 5 OR o.o_totalprice < 9)
GROUP BY o.o_orderkey, c.c_name HAVING SUM(o.o_totalprice) > MAX(c.c_acctbal) ORDER BY c.c_name"""


def test_golden():
    want = {"SELECT_orders.o_orderkey": 1, "SELECT_customer.c_name": 1, "FROM_orders": 1, "JOIN_customer": 1, "WHERE_orders.o_custkey": 1, "WHERE_customer.c_custkey": 1, "WHERE_orders.o_totalprice": 2, "WHERE_customer.c_acctbal": 1, "GROUPBY_orders.o_orderkey": 1, "GROUPBY_customer.c_name": 1, "HAVING_orders.o_totalprice": 1, "HAVING_customer.c_acctbal": 1, "SUM_orders.o_totalprice": 1, "MAX_customer.c_acctbal": 1, "ORDERBY_customer.c_name": 1}
    assert parse_clauses(GOLDEN) == want == parse_clauses(GOLDEN.upper().replace("ORDERS AS O", "Orders AS O"))
    flat = {"SELECT_o_orderkey": 1, "SELECT_c_name": 1, "FROM_orders": 1, "FROM_customer": 1, "WHERE_o_custkey": 1, "WHERE_c_custkey": 1, "WHERE_o_totalprice": 2, "WHERE_c_acctbal": 1, "GROUPBY_o_orderkey": 1, "GROUPBY_c_name": 1, "HAVING_o_totalprice": 1, "HAVING_c_acctbal": 1, "ORDERBY_c_name": 1}
    assert parse_flat(GOLDEN) == flat


def test_templates():
    for text, tokens, flat in zip(TEMPLATES, TOKENS, FLAT, strict=True):
        assert parse_clauses(text.replace("{k}", "3").replace("{v}", "2.5")) == tokens
        assert parse_flat(text.replace("{k}", "3").replace("{v}", "2.5")) == flat


def test_edge_texts():
    assert parse_clauses(None) == {} == parse_clauses("  ")
    assert parse_clauses("select a from t where (b > 1") == {"SELECT_t.a": 1, "FROM_t": 1, "WHERE_t.b": 1}
    assert parse_clauses("select a from t where b = 'x from y where z' -- from q\n/* where w */") == {"SELECT_t.a": 1, "FROM_t": 1, "WHERE_t.b": 1}
    assert parse_clauses('select "A" from "T"') == {"SELECT_t.a": 1, "FROM_t": 1}
    assert parse_clauses("select x.a from t x, t y where x.a = y.a") == {"SELECT_t.a": 1, "FROM_t": 2, "WHERE_t.a": 2}
    assert parse_clauses("select * from u, v where u.i = v.i") == {"FROM_u": 1, "FROM_v": 1, "WHERE_u.i": 1, "WHERE_v.i": 1}
    assert parse_clauses("select a from t, u") == {"SELECT_a": 1, "FROM_t": 1, "FROM_u": 1}
    assert parse_clauses("select case when a > 1 then b else c end as z from t order by z") == {"SELECT_t.a": 1, "SELECT_t.b": 1, "SELECT_t.c": 1, "FROM_t": 1}
    assert parse_clauses("select a from t union select b from u") == {"SELECT_t.a": 1, "FROM_t": 1, "SELECT_u.b": 1, "FROM_u": 1}
    assert parse_clauses("select m.a from t m where exists (select 1 from u m where m.b = 1)") == {"SELECT_t.a": 1, "FROM_t": 1, "FROM_u": 1, "WHERE_u.b": 1}
    assert parse_clauses("select a from t where b > 1") != parse_clauses("select a from t where 1 < b and b > 1")
    assert parse_clauses("select t.a from t where t.b in (select u.b from u)", nested="depth")["SELECT_u.b@1"] == 1
    assert is_select(" (select 1)") and is_select("from A a") and not is_select("update t set a = 1") and not is_select(None)
    assert [x.text for x in lex("a.b>=:p")] == ["a", ".", "b", ">", "=", ":p"]


def test_random_statements():
    rng = random.Random(5)
    for _ in range(200):
        tables = rng.sample(["alpha", "beta", "gamma"], rng.randint(1, 3))
        alias = {t: f"q{i}" for i, t in enumerate(tables)}
        want: Counter = Counter()

        def col(clause, alias=alias, tables=tables, want=want):
            t, c = rng.choice(tables), rng.choice(["c1", "c2", "c3"])
            f = rng.choice([None, None, "sum", "max", "coalesce"]) if clause in ("SELECT", "HAVING") else None
            want[f"{clause}_{t}.{c}"] += 1
            if f in ("sum", "max"):
                want[f"{f.upper()}_{t}.{c}"] += 1
            ref = f"{alias[t]}.{c}"
            return f"{f}({ref})" if f else ref

        text = "select " + ", ".join(col("SELECT") for _ in range(rng.randint(1, 3)))
        text += f" from {tables[0]} {alias[tables[0]]}"
        want[f"FROM_{tables[0]}"] += 1
        for t in tables[1:]:
            text += f" {rng.choice(['', 'left ', 'inner '])}join {t} as {alias[t]} on {col('WHERE')} = {col('WHERE')}"
            want[f"JOIN_{t}"] += 1
        text += " where " + rng.choice([" and ", " or "]).join(f"{col('WHERE')} > {rng.randint(1, 9)}" for _ in range(rng.randint(1, 3)))
        if rng.random() < 0.5:
            text += f" group by {col('GROUPBY')} having {col('HAVING')} > 3"
        if rng.random() < 0.5:
            text += f" order by {col('ORDERBY')} desc limit 5"
        assert parse_clauses(text) == dict(want), text


def test_each_text_is_parsed_once(spark):
    df = spark.createDataFrame([(1, "select a from t"), (2, "select a from t"), (3, None)], "oid int, sql_text string")
    got = {r["oid"]: r["tokens"] for r in with_tokens(df).collect()}
    assert got == {1: {"SELECT_t.a": 1, "FROM_t": 1}, 2: {"SELECT_t.a": 1, "FROM_t": 1}, 3: {}}
