"""Deterministic coins: the same value in Spark and in DuckDB, on any partitioning
and at any re-execution. A coin is 52 bits of an md5 digest over seed, tag and id."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

SIDES = 1 << 52


def coin(key: Column | str, seed: int, tag: int | str) -> Column:
    """Uniform BIGINT in [0, 2^52)."""
    key = F.col(key) if isinstance(key, str) else key
    text = F.concat_ws(":", F.lit(f"s{seed}"), F.lit(str(tag)), key.cast("string"))
    return F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("long")


def threshold(p: float) -> int:
    """What a coin must be below to land with probability ``p``; computed once, on the driver."""
    return int(min(1.0, max(0.0, p)) * SIDES)


def coin_sql(key: str, seed: int, tag: int | str) -> str:
    """The same coin for DuckDB."""
    return f"cast('0x' || substr(md5(concat_ws(':', 's{seed}', '{tag}', cast({key} as varchar))), 1, 13) as bigint)"


def register(spark: SparkSession) -> None:
    """SQL function grove_coin(id, seed, tag)."""
    spark.sql(
        "create or replace temporary function grove_coin(id bigint, seed int, tag string) returns bigint "
        "return cast(conv(substr(md5(concat_ws(':', concat('s', cast(seed as string)), tag, cast(id as string))), 1, 13), 16, 10) as bigint)"
    )
