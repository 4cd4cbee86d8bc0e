"""Design for a continuous demand from a sample of it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from prefbook.operators import simplex
from prefbook.operators.refine import Design, Run
from prefbook.plans.engine import Layout
from prefbook.plans.planner import solve


def draw(spark: SparkSession, density: str, n: int, size: int, seed: int = 11, how: str = "reject") -> DataFrame:
    """(item_id, p, f) of ``size`` points: accepted ones with equal demand, or all with the density as weight.

    A number of candidates is drawn that gives enough accepted ones, and the first ``size`` of these are kept.
    """
    if how == "weight" or density == "uniform":
        points = simplex.uniform_points(spark.range(size).withColumnRenamed("id", "item_id"), n, seed)
        return simplex.weigh(points, n, density)
    candidates = simplex.uniform_points(spark.range(8 * size).withColumnRenamed("id", "item_id"), n, seed)
    kept = simplex.reject(candidates, n, density, seed).orderBy("item_id").limit(size)
    return kept.withColumn("f", F.lit(1.0 / size))


def design(spark: SparkSession, density: str, n: int, k: int, size: int = 1000, method: str = "refine", how: str = "reject", restarts: int = 4, **options) -> list[Design]:
    return solve(draw(spark, density, n, size, how=how), n, [Run(r, Layout(k), seed=r + 1) for r in range(restarts)], method, **options)
