"""Every registered query with a DuckDB statement gives the same rows at the smallest scale."""

import math
from decimal import Decimal

import duckdb
import pytest

from slowlens.plans import operator_queries, registry, result_queries, search_queries, stream_queries, text_queries  # noqa: F401
from slowlens.session import TABLES

SF = "/root/testdata/sf0.001"
SAMPLE = [q for q in registry.QUERIES if q.startswith(("p_", "l_", "r_", "i_", "w_toy", "s_", "op_join", "st_w", "sql_", "udf_"))] + ["a_beam_d2", "a_exhaustive_d2", "b_brute_d2", "q_median", "q_tscore", "w_rq1_wracc"]


def norm(v):
    if isinstance(v, (float, Decimal)):
        return None if math.isnan(v) else float(f"{float(v):.6g}") + 0.0
    if isinstance(v, (list, tuple)):
        return tuple(map(norm, v))
    return int(v) if isinstance(v, bool) else v


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{SF}/{t}.parquet')")
    return c


@pytest.mark.parametrize("name", SAMPLE)
def test_same_rows(spark, duck, name):
    df = registry.QUERIES[name](spark, SF)
    columns = sorted(df.columns)
    got = sorted(repr([norm(r[c]) for c in columns]) for r in df.collect())
    if name in registry.ORACLES:
        rel = duck.sql(registry.ORACLES[name])
        names = list(rel.columns)
        assert sorted(names) == columns
        assert got == sorted(repr([norm(dict(zip(names, r, strict=True))[c]) for c in columns]) for r in rel.fetchall())


@pytest.mark.parametrize("name", ["l_generalisations", "w_toy_binary", "w_toy_extent"])
def test_reads_a_given_table(spark, name):
    assert any("events.parquet" in f for f in registry.QUERIES[name](spark, SF).inputFiles())
