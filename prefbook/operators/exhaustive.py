"""Search over all choices: pairs of lattice codebooks, and all partitions of a few items."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from prefbook.operators import simplex
from prefbook.plans.engine import cross
from prefbook.plans.planner import as_problem, local_engine


def pair_costs(points: DataFrame, grid: int) -> DataFrame:
    """(a, b, cost): bits per symbol of every pair of lattice codebooks, of which there are grid * grid.

    A task prices its points under all pairs and gives one sum per pair, so that what is shuffled doesn't grow with the points.
    """
    cells = simplex.lattice(points.sparkSession, grid).orderBy("item_id").collect()  # grid * grid rows
    ids, q = np.array([r["item_id"] for r in cells]), np.array([r["p"] for r in cells])

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        total, seen = np.zeros((len(q), len(q))), False
        for frame in frames:
            seen = seen or len(frame) > 0
            for at in range(0, len(frame), 1024):
                part = frame.iloc[at : at + 1024]
                f, costs = part["f"].to_numpy(), cross(np.array(part["p"].tolist()), q)
                for i in range(len(q) - 1):
                    total[i, i + 1 :] += f @ np.minimum(costs[:, i : i + 1], costs[:, i + 1 :])
        if seen:
            a, b = np.triu_indices(len(q), 1)
            yield pd.DataFrame({"a": ids[a], "b": ids[b], "cost": total[a, b]})

    return points.select("p", "f").mapInPandas(work, "a long, b long, cost double").groupBy("a", "b").agg(F.sum("cost").alias("cost"))


def search(points: DataFrame, grid: int = 24, rounds: int = 3, starts: int = 6) -> tuple[np.ndarray, float]:
    """Best two codebooks of three symbols: all pairs of a lattice, then of ever finer lattices around several of the best pairs.

    Candidates are spread over tasks; the points, a table of checked size, are sent to each.
    """
    engine = local_engine(as_problem(points), 3)
    spark = points.sparkSession
    p, w = engine.p, engine.w.sum(axis=1)

    def best(left: np.ndarray, right: np.ndarray, many: int) -> list[tuple[float, np.ndarray]]:
        """The cheapest partner of each left codebook, and the ``many`` cheapest of these pairs."""
        sent = spark.sparkContext.broadcast((p, w, left, right))

        def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            points, weights, rows, others = sent.value
            far = cross(points, others)
            for frame in frames:
                for i in frame["i"]:
                    costs = weights @ np.minimum(cross(points, rows[i : i + 1]), far)
                    yield pd.DataFrame({"i": [i], "j": [int(costs.argmin())], "cost": [float(costs.min())]})

        asked = spark.createDataFrame([(i,) for i in range(len(left))], "i int").repartition(min(len(left), 64))
        won = asked.mapInPandas(work, "i int, j int, cost double").orderBy("cost", "i").limit(many).collect()
        return [(r["cost"], np.array([left[r["i"]], right[r["j"]]])) for r in won]

    cells = np.array([r["p"] for r in simplex.lattice(spark, grid).orderBy("item_id").collect()])  # grid * grid rows
    found = best(cells, cells, 2 * starts)[::2]  # each pair is found from both ends
    out = []
    for cost, books in found:
        step = 1.0 / grid
        for _ in range(rounds):
            left, right = (_around(q, step) for q in books)
            now = _cheapest(p, w, left, right)
            if now[0] < cost:
                cost, books = now
            step /= 4
        out.append((cost, books))
    cost, books = min(out, key=lambda x: x[0])
    return books, cost


def _cheapest(p: np.ndarray, w: np.ndarray, left: np.ndarray, right: np.ndarray) -> tuple[float, np.ndarray]:
    """The cheapest pair of two lists of at most 81 codebooks each."""
    far, near = cross(p, right), cross(p, left)
    costs = np.array([w @ np.minimum(near[:, i : i + 1], far) for i in range(len(left))])
    i, j = np.unravel_index(costs.argmin(), costs.shape)
    return float(costs[i, j]), np.array([left[i], right[j]])


def _around(q: np.ndarray, step: float) -> np.ndarray:
    moves = np.array([(a, b) for a in np.linspace(-step, step, 9) for b in np.linspace(-step, step, 9)])
    found = np.column_stack([q[0] + moves[:, 0], q[1] + moves[:, 1]])
    found = np.column_stack([found, 1 - found.sum(axis=1)])
    return found[(found > 1e-9).all(axis=1)]


def partitions(items: DataFrame, n: int, k: int, most: int = 8) -> DataFrame:
    """(code, cost): every assignment of at most ``most`` items to k books, each book the mean of its items."""
    rows = items.select("item_id", "p", "f").orderBy("item_id").limit(most + 1).withColumn("place", F.row_number().over(_by_id()) - 1)
    count = rows.count()
    if count > most:
        raise ValueError(f"partitions are searched for at most {most} items")
    codes = items.sparkSession.range(k**count).withColumnRenamed("id", "code")
    book = (F.floor(F.col("code") / F.pow(F.lit(float(k)), F.col("place"))) % k).alias("book")
    sums = codes.crossJoin(F.broadcast(rows)).select("code", book, "f", "p").groupBy("code", "book").agg(*(F.sum(F.col("f") * F.col("p")[i]).alias(f"s{i}") for i in range(n)))
    mass = sum((F.col(f"s{i}") for i in range(1, n)), F.col("s0"))
    xlogx = lambda x: F.when(x > 0, x * F.log2(x)).otherwise(F.lit(0.0))
    cost = xlogx(mass) - sum((xlogx(F.col(f"s{i}")) for i in range(1, n)), xlogx(F.col("s0")))
    return sums.groupBy("code").agg(F.sum(cost).alias("cost"))


def _by_id():
    from pyspark.sql import Window

    return Window.orderBy("item_id")


