"""Points of the probability simplex: uniform samples, densities, lattices, and portable books."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from prefbook.functions.uniform import hash_uniform, uniform

BOOK_SEED = 77


def uniform_points(ids: DataFrame, n: int, seed: int, id_column: str = "item_id") -> DataFrame:
    """(item_id, p): SPVs uniform on the simplex, from normalised exponentials of hashed ids. Narrow."""
    draws = F.array(*(-F.ln(hash_uniform(seed, F.col(id_column), i)) for i in range(n)))
    drawn = ids.select(F.col(id_column).cast("long").alias("item_id"), draws.alias("e"))
    total = sum((F.col("e")[i] for i in range(1, n)), F.col("e")[0])
    return drawn.select("item_id", F.array(*(F.col("e")[i] / total for i in range(n))).alias("p"))


def spread_points(ids: DataFrame, n: int, id_column: str = "item_id") -> DataFrame:
    """(item_id, p): a low-discrepancy sequence in place of random numbers, from multiples of the powers of one irrational. Narrow.

    The irrational is the inverse of the root above 1 of x ** (n + 1) = x + 1, which spreads points evenly in n dimensions.
    """
    steps = spread_steps(n)
    number = lambda a: 0.5 + F.col(id_column) * F.lit(a)
    draws = F.array(*(-F.ln(number(a) - F.floor(number(a))) for a in steps))
    drawn = ids.select(F.col(id_column).cast("long").alias("item_id"), draws.alias("e"))
    total = sum((F.col("e")[i] for i in range(1, n)), F.col("e")[0])
    return drawn.select("item_id", F.array(*(F.col("e")[i] / total for i in range(n))).alias("p"))


def spread_steps(n: int) -> list[float]:
    root = 2.0
    for _ in range(60):
        root = (1 + root) ** (1 / (n + 1))
    return [root ** -(i + 1) for i in range(n)]


def distance(p: Column, n: int) -> Column:
    """Euclidean distance from the centre; at most sqrt(1 - 1 / n)."""
    return F.sqrt(sum((F.pow(p[i] - 1.0 / n, F.lit(2.0)) for i in range(1, n)), F.pow(p[0] - 1.0 / n, F.lit(2.0))))


DENSITIES = {"uniform": lambda p, n: F.lit(1.0), "distance": distance}


def weigh(points: DataFrame, n: int, density: str) -> DataFrame:
    """(item_id, p, f): points with normalised density as demand."""
    raw = points.withColumn("g", DENSITIES[density](F.col("p"), n))
    return raw.crossJoin(F.broadcast(raw.agg(F.sum("g").alias("total")))).select("item_id", "p", (F.col("g") / F.col("total")).alias("f"))


def reject(points: DataFrame, n: int, density: str, seed: int) -> DataFrame:
    """The points that a draw under the density's bound accepts; their law is the density's."""
    bound = float(np.sqrt(1 - 1 / n)) if density == "distance" else 1.0
    return points.filter(hash_uniform(seed, F.col("item_id"), 999) * bound <= DENSITIES[density](F.col("p"), n))


def lattice(spark: SparkSession, grid: int, n: int = 3) -> DataFrame:
    """(item_id, p): centres of the equal cells that a grid cuts the triangle into, grid * grid of them."""
    if n != 3:
        raise ValueError("equal cells are made for three symbols; use uniform_points for more")
    rows = spark.range(grid).withColumnRenamed("id", "a").select("a", F.explode(F.sequence(F.lit(0), F.lit(grid - 1) - F.col("a"))).alias("b"))
    both = rows.select("a", "b", F.explode(F.array(F.lit(0), F.lit(1))).alias("down")).filter((F.col("down") == 0) | (F.col("a") + F.col("b") < grid - 1))
    third = (F.col("down") + 1) / 3.0
    x, y = (F.col("a") + third) / grid, (F.col("b") + third) / grid
    return both.select(((F.col("down") * grid + F.col("a")) * grid + F.col("b")).cast("long").alias("item_id"), F.array(x, y, 1.0 - x - y).alias("p"))


def cell(p: Column, grid: int) -> Column:
    """The cell of ``lattice`` that holds a point; points on an outer border belong to the cell inside."""
    u, v = p[0] * grid, p[1] * grid
    a = F.least(F.floor(u), F.lit(grid - 1).cast("long"))
    b = F.least(F.floor(v), grid - 1 - a)
    down = F.when(((u - a) + (v - b) > 1) & (a + b < grid - 1), 1).otherwise(0)
    return ((down * grid + a) * grid + b).cast("long")


def portable_books(n: int, k: int, seed: int = BOOK_SEED) -> np.ndarray:
    """Books that any engine with md5 can make again."""
    e = np.array([[-np.log(uniform(seed, b, i)) for i in range(n)] for b in range(k)])
    return e / e.sum(axis=1, keepdims=True)
