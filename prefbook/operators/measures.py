"""Costs of designs and what is derived from them."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from prefbook.functions.info import entropy_unrolled
from prefbook.operators.assign import nearest
from prefbook.schemas import ITEM_LENGTH


def _grouped(df: DataFrame, by: list[str] | None):
    return df.groupBy(*by) if by else df


def _mean(value: Column) -> Column:
    """Demand-weighted mean; items that nobody asks for don't count, whatever they would cost."""
    return F.sum(F.when(F.col("f") > 0, F.col("f") * value)) / F.sum("f")


def expected_bits(items: DataFrame, q: np.ndarray, length: int = ITEM_LENGTH, by: list[str] | None = None) -> DataFrame:
    """bits_per_request: demand-weighted cost of an item under its cheapest book. One pass."""
    return _grouped(nearest(items, q), by).agg((length * _mean(F.col("cost"))).alias("bits_per_request"))


def mismatch(items: DataFrame, q: np.ndarray, by: list[str] | None = None) -> DataFrame:
    """mismatch: bits per symbol above the entropy."""
    return _grouped(nearest(items, q), by).agg(_mean(F.col("divergence")).alias("mismatch"))


def entropy_floor(items: DataFrame, n: int, length: int = ITEM_LENGTH, by: list[str] | None = None) -> DataFrame:
    """bits_per_request of a code of its own for each item, free of charge: no design costs less."""
    return _grouped(items, by).agg((length * _mean(entropy_unrolled(F.col("p"), n))).alias("bits_per_request"))


def saving(bits: Column, baseline: Column) -> Column:
    """Percent of the baseline's bits that a design does without."""
    return 100.0 * (1.0 - bits / baseline)


def kraft(books: DataFrame) -> DataFrame:
    """``books`` with kraft_sum; a prefix code exists if and only if it is at most 1."""
    return books.withColumn("kraft_sum", F.aggregate("q", F.lit(0.0), lambda s, x: s + x))


def index_bits(k: Column) -> Column:
    """Bits that name one of k books: the binary digits of k - 1, as rounded logarithms err at powers of two."""
    return F.when(k > 1, F.length(F.bin(k - 1))).otherwise(0)


def gain_per_book(report: DataFrame, by: list[str]) -> DataFrame:
    """``report`` (by, k, bits_per_request) with the bits that one more book saves."""
    window = Window.partitionBy(*by).orderBy("k")
    return report.withColumn("gain", F.col("bits_per_request") - F.lead("bits_per_request").over(window))


def trace_fit(report: DataFrame, by: list[str], x: str = "trace", y: str = "bits_per_request") -> DataFrame:
    """Straight line through bits against the trace: slope, intercept and r2."""
    return report.groupBy(*by).agg(F.regr_slope(y, x).alias("slope"), F.regr_intercept(y, x).alias("intercept"), F.regr_r2(y, x).alias("r2"))


def monotone(trace: DataFrame) -> DataFrame:
    """(run_id, steps, monotone): whether the objective never rose, but for rounding."""
    window = Window.partitionBy("run_id").orderBy("iteration")
    steps = trace.withColumn("rise", F.col("objective") - F.lag("objective").over(window))
    return steps.groupBy("run_id").agg(F.count("*").alias("steps"), F.coalesce(F.max("rise") <= 1e-9, F.lit(True)).alias("monotone"))


def border_distance(q: np.ndarray, left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Mean log-likelihood margin of each book between the mean SPVs of two interest regions; 0 is the border."""
    return q @ np.log2(left / right)
