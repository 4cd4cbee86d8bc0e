"""Skipping of blocks that lie in one region.

Regions are bounded by hyperplanes, so a box of SPVs that is on one side of all of a book's
hyperplanes belongs to that book as a whole. Blocks of similar items keep their box and
their sums; an update reads the items of undecided blocks only.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from prefbook.operators.assign import nearest


def with_blocks(items: DataFrame, n: int, steps: int = 16) -> DataFrame:
    """``items`` with a block: the cell of a grid over the first coordinates, the same for every run."""
    cells = [F.floor(F.col("p")[i] * steps).cast("string") for i in range(n - 1)]
    return items.withColumn("block", F.concat_ws("|", *cells))


def statistics(blocked: DataFrame, n: int) -> DataFrame:
    """(block, lo, hi, w, s): box, weight and weighted sum of each block; made once for a design's loop."""
    p = F.col("p")
    return blocked.groupBy("block").agg(
        F.array(*(F.min(p[i]) for i in range(n))).alias("lo"), F.array(*(F.max(p[i]) for i in range(n))).alias("hi"), F.sum("f").alias("w"), F.array(*(F.sum(F.col("f") * p[i]) for i in range(n))).alias("s")
    )


def decided(stats: DataFrame, q: np.ndarray) -> DataFrame:
    """``stats`` with the book that holds the whole box, null where the box may be split."""
    n = q.shape[1]
    chosen = F.lit(None).cast("int")
    for k in reversed(range(len(q))):
        inside = F.lit(True)
        for j in range(len(q)):
            if j != k:
                worst = F.lit(0.0)
                for i, x in enumerate(np.log2(q[j] / q[k])):  # the corner where book k is worst against book j
                    worst = worst + (F.col("hi")[i] if x > 0 else F.col("lo")[i]) * F.lit(float(x))
                inside = inside & (worst < -1e-12)
        chosen = F.when(inside, F.lit(k)).otherwise(chosen)
    return stats.withColumn("k", chosen) if n else stats


def update(blocked: DataFrame, stats: DataFrame, q: np.ndarray) -> DataFrame:
    """(k, w, s0, s1, ...): sums per book, from the sums of decided blocks and the items of the others."""
    n = q.shape[1]
    marked = decided(stats, q)
    whole = marked.filter("k is not null").select("k", "w", *(F.col("s")[i].alias(f"s{i}") for i in range(n)))
    open_blocks = marked.filter("k is null").select("block")
    rest = nearest(blocked.join(open_blocks, "block", "left_semi"), q).select("k", F.col("f").alias("w"), *((F.col("f") * F.col("p")[i]).alias(f"s{i}") for i in range(n)))
    return whole.unionByName(rest).groupBy("k").agg(F.sum("w").alias("w"), *(F.sum(f"s{i}").alias(f"s{i}") for i in range(n)))
