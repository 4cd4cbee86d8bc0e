"""One codebook in closed form, and its code lengths."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def optimal(items: DataFrame, n: int, weight: str = "f", by: list[str] | None = None, exact: bool = False) -> DataFrame:
    """The demand mean of the SPVs, normalised: the best single codebook. One pass, one row per group.

    ``exact``: sums in decimals, so that they don't depend on the order of the rows.
    """

    def total(x: Column) -> Column:
        return F.sum(x.cast("decimal(38,18)")).cast("double") if exact else F.sum(x)

    sums = [total(F.col(weight) * F.col("p")[i]).alias(f"s{i}") for i in range(n)]
    grouped = (items.groupBy(*by) if by else items).agg(*sums)
    mass = sum((F.col(f"s{i}") for i in range(1, n)), F.col("s0"))
    return grouped.select(*(by or []), F.array(*(F.col(f"s{i}") / mass for i in range(n))).alias("q"))


def book(items: DataFrame, n: int, weight: str = "f") -> np.ndarray:
    """The same as numbers: one row reaches the driver."""
    row = optimal(items, n, weight).first()
    return np.array([row["q"]], dtype=float)


def lengths(books: DataFrame) -> DataFrame:
    """``books`` with the ideal length of every symbol; infinite where it never occurs."""
    return books.withColumn("bits", F.transform("q", lambda x: F.when(x > 0, -F.log2(x)).otherwise(F.lit(float("inf")))))
