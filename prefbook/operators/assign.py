"""Choice of the codebook of an item: cheapest book, region tests, and the channels of two users."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from prefbook.functions.info import cost_unrolled, entropy_unrolled
from prefbook.plans.engine import Layout, SparkEngine, code_bits


def book_rows(items: DataFrame, q: np.ndarray) -> DataFrame:
    """(k, q, bits): books as a relation of known size."""
    return items.sparkSession.createDataFrame([(k, row.tolist(), code_bits(row).tolist()) for k, row in enumerate(q)], "k int, q array<double>, bits array<double>")


def divergences(items: DataFrame, q: np.ndarray) -> DataFrame:
    """Every item with every book: (item_id, k, cost, divergence) in bits per symbol."""
    n = q.shape[1]
    pairs = items.crossJoin(F.broadcast(book_rows(items, q)))
    cost = cost_unrolled(F.col("p"), F.col("bits"), n)
    return pairs.select(*items.columns, "k", cost.alias("cost"), (cost - entropy_unrolled(F.col("p"), n)).alias("divergence"))


def nearest(items: DataFrame, q: np.ndarray) -> DataFrame:
    """``items`` with k, cost and divergence of the cheapest book; ties go to the lowest number. Narrow."""
    n = q.shape[1]
    bits = F.array(*(F.array(*(F.lit(float(x)) for x in row)) for row in code_bits(q)))
    costs = [F.struct(cost_unrolled(F.col("p"), bits[k], n).alias("cost"), F.lit(k).alias("k")) for k in range(len(q))]
    best = F.least(*costs) if len(costs) > 1 else costs[0]
    return items.withColumn("best", best).select(*items.columns, F.col("best.k").alias("k"), F.col("best.cost").alias("cost"), (F.col("best.cost") - entropy_unrolled(F.col("p"), n)).alias("divergence"))


def halfspace(p: Column, left: np.ndarray, right: np.ndarray) -> Column:
    """Whether p costs no more under ``left`` than under ``right``: a linear inequality in p."""
    total = F.lit(0.0)
    for i, x in enumerate(np.log2(right / left)):
        total = total + p[i] * F.lit(float(x))
    return total <= 0


def by_halfspace(items: DataFrame, q: np.ndarray) -> DataFrame:
    """The lowest book whose half-spaces all hold the item; equal to ``nearest`` off ties."""
    chosen = F.lit(None).cast("int")
    for k in reversed(range(len(q))):
        inside = F.lit(True)
        for j in range(len(q)):
            if j != k:
                inside = inside & halfspace(F.col("p"), q[k], q[j])
        chosen = F.when(inside, F.lit(k)).otherwise(chosen)
    return items.withColumn("k", chosen)


def channels(items: DataFrame, n: int, layout: Layout, q: np.ndarray) -> DataFrame:
    """(item_id, channel, w, p, h, book, pool, cost): the five region families of two users."""
    engine = SparkEngine(items, n)
    wide = engine.costs({0: (layout, q)})
    parts = F.array(*(F.struct(F.lit(i).alias("channel"), F.col(c).alias("w"), F.col(f"best{i}.book").alias("book"), F.col(f"best{i}.cost").alias("cost")) for i, c in enumerate(engine.channels)))
    rows = wide.select("item_id", "p", "h", F.explode(parts).alias("c")).select("item_id", "p", "h", "c.*").filter("book is not null")
    pools = F.array(*(F.lit(int(x)) for x in layout.pools))
    return rows.withColumn("pool", pools[F.col("book")])
