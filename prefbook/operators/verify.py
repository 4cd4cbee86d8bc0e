"""Checks that a design has to pass."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from prefbook.operators import single
from prefbook.operators.assign import book_rows, nearest


def fixed_point(items: DataFrame, q: np.ndarray) -> DataFrame:
    """(k, residual): how far each used book is from the demand mean of the items that choose it."""
    n = q.shape[1]
    means = single.optimal(nearest(items, q), n, by=["k"]).withColumnRenamed("q", "mean")
    both = means.join(F.broadcast(book_rows(items, q)), "k")
    return both.select("k", F.array_max(F.zip_with("mean", "q", lambda a, b: F.abs(a - b))).alias("residual"))


def regions(assigned: DataFrame) -> DataFrame:
    """(item_id, books): how many regions hold each item; 1 for disjoint regions that cover."""
    return assigned.groupBy("item_id").agg(F.count("k").alias("books"))
