"""Reproducible random draws in [0, 2^32): pure functions of (seed, iteration, purpose, keys), whatever the layout or retries.

``fast`` hashes in the JVM; ``portable`` takes the first 32 bits of an md5, so that SQL engines draw the same numbers.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

RANGE = 4294967296.0


def draw(provider: str, seed: int, t: int, purpose: str, *keys: Column | str) -> Column:
    cols = [F.col(k) if isinstance(k, str) else k for k in keys]
    if provider == "fast":
        return F.shiftrightunsigned(F.xxhash64(F.lit(seed), F.lit(t), F.lit(purpose), *cols), 32)
    if provider == "portable":
        text = F.concat_ws("|", F.lit(f"{seed}|{t}|{purpose}"), *(c.cast("string") for c in cols))
        return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long")
    raise ValueError("provider is fast or portable")


def draw_sql(seed: int, t: int, purpose: str, *keys: str) -> str:
    """The portable draw, as DuckDB SQL."""
    text = " || '|' || ".join([f"'{seed}|{t}|{purpose}'", *(f"CAST({k} AS VARCHAR)" for k in keys)])
    return f"CAST('0x' || substr(md5({text}), 1, 8) AS BIGINT)"


def register_sql_functions(spark) -> None:
    """blp_penalty and blp_overflow_bound as SQL functions of built-in expressions."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION blp_penalty(b DOUBLE, c DOUBLE) RETURNS DOUBLE RETURN b / c")
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION blp_overflow_bound(n DOUBLE, r DOUBLE, eps DOUBLE, dmin DOUBLE, dmax DOUBLE) RETURNS DOUBLE "
        "RETURN exp(-2 * n * power(eps * r / (dmax - dmin), 2))"
    )
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION blp_draw(seed INT, t INT, purpose STRING, key BIGINT) RETURNS BIGINT "
        "RETURN cast(conv(substring(md5(concat_ws('|', seed, t, purpose, key)), 1, 8), 16, 10) AS BIGINT)"
    )
