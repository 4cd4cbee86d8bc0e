"""Storage of codebooks: both ends of a link read the same file."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from prefbook.operators.refine import Design
from prefbook.schemas import BOOKS


def as_table(spark: SparkSession, designs: list[Design]) -> DataFrame:
    rows = [(d.run.run_id, int(pool), k, row.tolist()) for d in designs for k, (pool, row) in enumerate(zip(d.run.layout.pools, d.q))]
    return spark.createDataFrame(rows, BOOKS)


def save(books: DataFrame, path: str, form: str = "parquet") -> None:
    """Parquet is partitioned by run; CSV carries the vector as JSON text, which keeps every digit."""
    if form == "parquet":
        books.write.mode("overwrite").partitionBy("run_id").parquet(path)
    elif form == "json":
        books.write.mode("overwrite").json(path)
    elif form == "csv":
        books.withColumn("q", F.to_json("q")).write.mode("overwrite").csv(path, header=True, escape='"')
    else:
        raise ValueError(form)


def load(spark: SparkSession, path: str, form: str = "parquet") -> DataFrame:
    if form == "parquet":
        return spark.read.parquet(path).select("run_id", "pool", "k", "q")
    if form == "json":
        return spark.read.schema(BOOKS).json(path)
    if form == "csv":
        raw = spark.read.schema("run_id int, pool int, k int, q string").csv(path, header=True, escape='"')
        return raw.withColumn("q", F.from_json("q", "array<double>"))
    raise ValueError(form)


def as_array(books: DataFrame, run_id: int) -> np.ndarray:
    """Books of one run, a few numbers."""
    return np.array([r["q"] for r in books.filter(F.col("run_id") == run_id).orderBy("k").collect()])
