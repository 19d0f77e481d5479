"""The methods from SQL: functions and a table function registered in a session, all native."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def register(spark: SparkSession) -> None:
    """bms_bin(pos, d, k), bms_offset(pos, d, k) and bms_unbiased(n_mat, n_emp, k) as expressions;
    bms_words(text, size) as a table function of (word, elem)."""
    for text in (
        "CREATE OR REPLACE TEMPORARY FUNCTION bms_bin(pos BIGINT, d BIGINT, k BIGINT) RETURNS BIGINT RETURN pos DIV (d DIV k)",
        "CREATE OR REPLACE TEMPORARY FUNCTION bms_offset(pos BIGINT, d BIGINT, k BIGINT) RETURNS BIGINT RETURN pos % (d DIV k)",
        "CREATE OR REPLACE TEMPORARY FUNCTION bms_unbiased(n_mat BIGINT, n_emp BIGINT, k BIGINT) RETURNS DOUBLE RETURN try_divide(CAST(n_mat AS DOUBLE), k - n_emp)",
        r"""CREATE OR REPLACE TEMPORARY FUNCTION bms_words(text STRING, size BIGINT) RETURNS TABLE (word STRING, elem BIGINT)
            RETURN SELECT w, CAST(conv(substring(md5(concat('e:', w)), 1, 7), 16, 10) AS BIGINT) % bms_words.size FROM (SELECT explode(regexp_extract_all(lower(bms_words.text), '([\\p{L}\\p{N}]+)', 1)) AS w)""",
    ):
        spark.sql(text)


def sketch_agg(pos: str, size: int = 1 << 24, k: int = 64) -> Column:
    """A sketch as one aggregate over positions: an array of k minima, -1 for a hole. Partial minima, no Python."""
    width = size // k
    own = F.expr(f"{pos} div {width}")
    return F.array(*[F.coalesce(F.min(F.when(own == j, F.col(pos) % F.lit(width))), F.lit(-1)) for j in range(k)])
