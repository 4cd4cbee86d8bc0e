"""Alternating design for a continuous demand: regions and conditional means by quadrature."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from prefbook.operators import simplex
from prefbook.operators.refine import Design, Run
from prefbook.plans.engine import Layout, cross
from prefbook.plans.planner import solve


def nodes(spark: SparkSession, n: int, grid: int, density: str) -> DataFrame:
    """(item_id, p, f): cells of a lattice for three symbols, low-discrepancy points for more; f is the density's mass."""
    points = simplex.lattice(spark, grid) if n == 3 else simplex.spread_points(spark.range(grid * grid).withColumnRenamed("id", "item_id"), n)
    return simplex.weigh(points, n, density)


def filled(items: DataFrame, nodes: DataFrame) -> DataFrame:
    """``nodes`` (item_id, p) with the demand of the items that are nearest to each as f: an empirical density; ties go to the lowest node.

    Nodes are sent to the tasks, which give one sum per node.
    """
    held = nodes.select("item_id", "p").orderBy("item_id").collect()  # grid * grid rows
    ids, q = np.array([r["item_id"] for r in held]), np.array([r["p"] for r in held])

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        total = np.zeros(len(q))
        for frame in frames:
            for at in range(0, len(frame), 4096):
                part = frame.iloc[at : at + 4096]
                near = cross(np.array(part["p"].tolist()), q).argmin(axis=1)
                total += np.bincount(near, part["f"].to_numpy(), len(q))
        yield pd.DataFrame({"item_id": ids, "f": total})

    sums = items.select("p", "f").mapInPandas(work, "item_id long, f double").groupBy("item_id").agg(F.sum("f").alias("f"))
    return nodes.select("item_id", "p").join(F.broadcast(sums), "item_id", "left").select("item_id", "p", F.coalesce("f", F.lit(0.0)).alias("f"))


def design(spark: SparkSession, density: str, n: int, k: int, grid: int = 60, restarts: int = 4, **options) -> list[Design]:
    """One design per restart; integrals are sums over the nodes, so the loop is that of a discrete demand."""
    return solve(nodes(spark, n, grid, density), n, [Run(r, Layout(k), seed=r + 1) for r in range(restarts)], "refine", **options)
