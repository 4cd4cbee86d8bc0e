"""Demand of items: from a history of requests, or from any weight."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def empirical(log: DataFrame, item: str = "item_id", user: str | None = None) -> DataFrame:
    """Request shares, over all requests or over each user's; counts are added up before any shuffle."""
    keys = [user, item] if user else [item]
    counts = log.groupBy(*keys).agg(F.count("*").cast("double").alias("c"))
    if user:
        total = F.sum("c").over(Window.partitionBy(user))
        return counts.select(user, F.col(item).alias("item_id"), (F.col("c") / total).alias("f"))
    return _shared(counts.withColumnRenamed(item, "item_id"))


def weighted(df: DataFrame, item: str, weight: str) -> DataFrame:
    return _shared(df.groupBy(F.col(item).alias("item_id")).agg(F.sum(F.col(weight).cast("double")).alias("c")))


def _shared(counts: DataFrame) -> DataFrame:
    """c over its total; the total is one row, so it is a broadcast of known size rather than a window over everything."""
    total = counts.agg(F.sum("c").alias("total"))
    return counts.crossJoin(F.broadcast(total)).select("item_id", (F.col("c") / F.col("total")).alias("f"))


def edge_distribution(items: DataFrame, n: int, by: str | None = None) -> DataFrame:
    """The symbol law of the link to the user: the demand-weighted mean of the SPVs, as an array."""
    sums = [F.sum(F.col("f") * F.col("p")[i]) / F.sum("f") for i in range(n)]
    grouped = items.groupBy(by) if by else items
    return grouped.agg(F.array(*sums).alias("p"))
