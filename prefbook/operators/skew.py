"""Joins with popular items: one key may hold a third of all rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def salted_join(large: DataFrame, small: DataFrame, key: str, salts: int = 32, how: str = "inner") -> DataFrame:
    """``large`` joined with ``small`` (one row a key) over keys times salts: a key's rows go to ``salts`` tasks.

    The small side is repeated ``salts`` times, so it must be small beside the large one; left and inner joins only.
    Adaptive execution splits skewed partitions by itself where nothing above needs them whole; this is for the rest.
    """
    if how not in ("inner", "left", "left_semi", "left_anti"):
        raise ValueError(how)
    named = large.withColumn("_salt", F.pmod(F.xxhash64(*(F.col(c) for c in large.columns)), F.lit(salts)))
    spread = small.withColumn("_salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
    return named.join(spread, [key, "_salt"], how).drop("_salt")


def two_level_sum(df: DataFrame, keys: list[str], value: str, salts: int = 32) -> DataFrame:
    """Sums by key through sums by key and salt, for aggregates without a partial form on the way to one task."""
    salted = df.withColumn("_salt", F.pmod(F.xxhash64(*(F.col(c) for c in df.columns)), F.lit(salts)))
    partial = salted.groupBy(*keys, "_salt").agg(F.sum(value).alias(value))
    return partial.groupBy(*keys).agg(F.sum(value).alias(value))
