"""SQL surface: functions and views for use in spark.sql."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession

FUNCTIONS = {
    "sig_probability": "CREATE OR REPLACE TEMPORARY FUNCTION sig_probability(n DOUBLE, lam DOUBLE, mu DOUBLE) RETURNS DOUBLE RETURN 1 / (1 + power(lam, n) * mu)",
    "jaccard_counts": "CREATE OR REPLACE TEMPORARY FUNCTION jaccard_counts(m BIGINT, na BIGINT, nb BIGINT) RETURNS DOUBLE RETURN CASE WHEN na + nb - m = 0 THEN 0D ELSE CAST(m AS DOUBLE) / (na + nb - m) END",
    "year_of": "CREATE OR REPLACE TEMPORARY FUNCTION year_of(d DATE) RETURNS STRING RETURN CAST(year(d) AS STRING)",
    "street_name": r"CREATE OR REPLACE TEMPORARY FUNCTION street_name(s STRING) RETURNS STRING RETURN nullif(regexp_extract(s, '(?:^|\\s)([A-Za-z]+)(?=\\s|$)', 1), '')",
}


def register(spark: SparkSession) -> None:
    for text in FUNCTIONS.values():
        spark.sql(text)


def link_pairs(spark: SparkSession, a: str, b: str, combos: Sequence[Sequence[str]], cap: int, s_t: float) -> DataFrame:
    """Attribute-signature matches of two views, written in SQL alone."""
    register(spark)

    def long(view: str) -> str:
        each = " UNION ALL ".join(f"SELECT record_id, {i} AS combo_id, concat({', '.join(f'char(31), {c}' for c in combo)}) AS sig FROM {view}" for i, combo in enumerate(combos, 1))
        return f"SELECT * FROM (SELECT *, count(*) OVER (PARTITION BY combo_id, sig) AS n FROM ({each}) WHERE sig IS NOT NULL) WHERE n <= {cap}"

    return spark.sql(
        f"""WITH sa AS ({long(a)}), sb AS ({long(b)}),
        na AS (SELECT record_id, count(*) AS na FROM sa GROUP BY record_id), nb AS (SELECT record_id, count(*) AS nb FROM sb GROUP BY record_id),
        c AS (SELECT sa.record_id AS a_id, sb.record_id AS b_id, count(*) AS m FROM sa JOIN sb ON sa.combo_id = sb.combo_id AND sa.sig = sb.sig GROUP BY ALL)
        SELECT a_id, b_id, jaccard_counts(m, na, nb) AS s FROM c JOIN na ON na.record_id = a_id JOIN nb ON nb.record_id = b_id WHERE jaccard_counts(m, na, nb) >= {s_t} - 1e-9"""
    )
