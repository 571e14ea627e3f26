"""The scores as SQL functions; the optimizer inlines their bodies."""

from __future__ import annotations

from pyspark.sql import SparkSession

FUNCTIONS = {
    "sg_klosgen(n DOUBLE, s1 DOUBLE, total DOUBLE, mu0 DOUBLE, a DOUBLE)": "pow(n / total, a) * (s1 / n - mu0)",
    "sg_lift(n DOUBLE, s1 DOUBLE, mu0 DOUBLE)": "try_divide(s1 / n, mu0)",
    "sg_wracc(n DOUBLE, s1 DOUBLE, total DOUBLE, mu0 DOUBLE)": "n / total * (s1 / n - mu0)",
    "sg_mean_test(n DOUBLE, s1 DOUBLE, total DOUBLE, mu0 DOUBLE)": "sqrt(n / total) * (s1 / n - mu0)",
    "sg_tscore(n DOUBLE, s1 DOUBLE, s2 DOUBLE, total DOUBLE, mu0 DOUBLE)": "CASE WHEN n >= 2 THEN try_divide(sqrt(n / total) * (s1 / n - mu0), sqrt(greatest(s2 / n - (s1 / n) * (s1 / n), 0D))) END",
    "sg_qmed(n DOUBLE, med DOUBLE, total DOUBLE, med0 DOUBLE, a DOUBLE)": "pow(n / total, a) * (med - med0)",
    "sg_jaccard(shared DOUBLE, p DOUBLE, q DOUBLE)": "try_divide(shared, p + q - shared)",
}


def register(spark: SparkSession) -> None:
    for head, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURNS DOUBLE RETURN {body}")
