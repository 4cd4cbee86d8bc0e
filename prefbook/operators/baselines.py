"""What designs are compared with."""

from __future__ import annotations

import zlib
from math import log2

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from prefbook.functions.info import entropy_unrolled
from prefbook.operators import measures, single
from prefbook.schemas import ITEM_LENGTH


def header_bits(p: Column, n: int, support_only: bool) -> Column:
    """Bits of a codebook that travels with its item: the lengths of its codewords, over all symbols or those that occur."""
    total = F.lit(0.0)
    for i in range(n):
        absent = F.lit(0.0) if support_only else F.lit(float("inf"))
        total = total + F.when(p[i] > 0, -F.log2(p[i])).otherwise(absent)
    return total


def self_decodable_bits(p: Column, n: int, length: int = ITEM_LENGTH, support_only: bool = False) -> Column:
    return length * entropy_unrolled(p, n) + header_bits(p, n, support_only)


def self_decodable(items: DataFrame, n: int, length: int = ITEM_LENGTH, support_only: bool = False) -> DataFrame:
    """bits_per_request when every item is coded by its own SPV and carries its codebook."""
    return items.agg((F.sum(F.col("f") * self_decodable_bits(F.col("p"), n, length, support_only)) / F.sum("f")).alias("bits_per_request"))


def self_decodable_pair(items: DataFrame, n: int, length: int = ITEM_LENGTH, support_only: bool = False) -> DataFrame:
    """The same for two users; equal requests are multicast."""
    weight = F.col("w0") + F.col("w1") + F.col("w2")
    return items.agg(F.sum(weight * self_decodable_bits(F.col("p"), n, length, support_only)).alias("bits_per_request"))


def source_based(items: DataFrame, n: int, length: int = ITEM_LENGTH) -> DataFrame:
    """One codebook that knows the items but not what is asked for, priced under the real demand."""
    q = single.book(items.withColumn("even", F.lit(1.0)), n, "even")
    return measures.expected_bits(items, q, length)


def fixed_length(n: int, length: int = ITEM_LENGTH) -> float:
    return length * log2(n)


def fixed_bits(n: Column, length: int = ITEM_LENGTH) -> Column:
    """The same for a column of numbers of symbols; no symbols take no bits."""
    return length * F.log2(F.greatest(n, F.lit(1)))


def mismatched_demand(items: DataFrame, books: np.ndarray, other: str, length: int = ITEM_LENGTH) -> DataFrame:
    """Books designed for the demand f, priced under the demand in another column."""
    return measures.expected_bits(items.drop("f").withColumnRenamed(other, "f"), books, length)


def zlib_bits(df: DataFrame, item: str, text: str, level: int = 6) -> DataFrame:
    """(item_id, raw_bits, packed_bits) under a general-purpose byte compressor of the LZ77 family."""

    @F.pandas_udf("long")
    def packed(texts: pd.Series) -> pd.Series:
        return texts.fillna("").map(lambda t: 8 * len(zlib.compress(t.encode(), level)))

    return df.select(F.col(item).alias("item_id"), (8 * F.octet_length(F.coalesce(F.col(text), F.lit("")))).cast("long").alias("raw_bits"), packed(text).alias("packed_bits"))
