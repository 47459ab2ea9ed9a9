"""Randomness as a function of content.

A coin depends on a seed and on the values it is tossed for, never on partitions, retries or arrival order, so every sampled
result is the same on any cluster.  Mode "md5" can be repeated bit for bit in any SQL engine; mode "xx" is the cheap one.
"""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

COIN_RANGE = 1 << 52


def coin52(seed: int, *cols: Column | str | int, mode: str = "md5") -> Column:
    """Uniform in [0, 2^52)."""
    parts = [F.lit(c) if isinstance(c, int) else F.col(c) if isinstance(c, str) else c for c in cols]
    if mode == "xx":
        return F.shiftrightunsigned(F.xxhash64(F.lit(seed), *parts), 12)
    text = F.concat_ws("|", F.lit(str(seed)), *(p.cast("string") for p in parts))
    return F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("long")


def edge_lo(a: Column | str, b: Column | str) -> Column:
    return F.least(a, b)


def edge_hi(a: Column | str, b: Column | str) -> Column:
    return F.greatest(a, b)


def register_sql_functions(spark: SparkSession) -> None:
    """The same as SQL functions, which the optimizer inlines."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION coin52(seed STRING, what STRING) RETURNS BIGINT RETURN CAST(conv(substr(md5(concat_ws('|', seed, what)), 1, 13), 16, 10) AS BIGINT)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION edge_lo(a BIGINT, b BIGINT) RETURNS BIGINT RETURN least(a, b)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION edge_hi(a BIGINT, b BIGINT) RETURNS BIGINT RETURN greatest(a, b)")
