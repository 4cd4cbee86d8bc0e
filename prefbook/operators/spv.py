"""Symbol probability vectors of items."""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType, LongType, StructField, StructType

#: Character classes of a text; explicit sets of both cases.
CLASSES = ("[aeiouAEIOU]", "[bcdfghjklmnpqrstvwxyzBCDFGHJKLMNPQRSTVWXYZ]", "[0-9]", "[ \\t\\n\\r\\f\\x0B]")


def _shares(counts: list[Column], smoothing: float) -> Column:
    total = sum(counts[1:], counts[0]) + smoothing * len(counts)
    return F.when(total > 0, F.array(*((c + smoothing) / total for c in counts)))


def from_symbols(df: DataFrame, item: str, symbol: str, alphabet: tuple[str, ...], smoothing: float = 0.0, weight: str | None = None) -> DataFrame:
    """(item_id, n_sym, p), and the sum of ``weight`` as w if one is named: one shuffle of one row of counts per item and task.

    Items without any symbol of the alphabet have no SPV and are left out.
    """
    sums = [F.sum(F.col(weight).cast("double")).alias("w")] if weight else []
    counted = df.groupBy(F.col(item).alias("item_id")).agg(*(F.count_if(F.col(symbol) == a).alias(f"c{n}") for n, a in enumerate(alphabet)), F.count_if(F.col(symbol).isin(*alphabet)).alias("n_sym"), *sums)
    shares = _shares([F.col(f"c{n}").cast("double") for n in range(len(alphabet))], smoothing)
    return counted.filter("n_sym > 0").select("item_id", "n_sym", shares.alias("p"), *(["w"] if weight else []))


def from_text(df: DataFrame, item: str, text: str, classes: tuple[str, ...] = CLASSES) -> DataFrame:
    """(item_id, n_sym, p) with a last symbol for characters of no class; narrow, one pass over the bytes of a batch.

    Classes are sets of ASCII characters, written as the bracket expressions of regular expressions.
    """
    table = class_table(classes)
    n = len(classes) + 1
    source = df.select(F.col(item).alias("item_id"), F.coalesce(F.col(text), F.lit("")).alias("text")).filter(F.char_length("text") > 0)
    schema = StructType([source.schema["item_id"], StructField("n_sym", LongType()), StructField("p", ArrayType(DoubleType()))])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                counts = class_counts(batch.column(1), table, n)
                total = counts.sum(axis=1)
                shares = pa.ListArray.from_arrays(pa.array(np.arange(len(total) + 1) * n, pa.int32()), pa.array((counts / total[:, None]).ravel()))
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(total), shares], names=["item_id", "n_sym", "p"])

    return source.mapInArrow(count, schema)


def class_table(classes: tuple[str, ...]) -> np.ndarray:
    """The class of each byte: that of its character, one more for other characters, and -1 within a character."""
    table = np.full(256, len(classes), dtype=np.int64)
    table[0x80:0xC0] = -1
    for k, c in reversed(list(enumerate(classes))):
        table[[b for b in range(128) if re.fullmatch(c, chr(b))]] = k
    return table


def class_counts(texts: pa.Array, table: np.ndarray, n: int) -> np.ndarray:
    """Characters of each class in each of some texts (no nulls)."""
    wide = pa.types.is_large_string(texts.type)
    _, at, body = texts.buffers()
    offsets = np.frombuffer(at, dtype=np.int64 if wide else np.int32)[texts.offset : texts.offset + len(texts) + 1].astype(np.int64)
    marks = table[np.frombuffer(body, dtype=np.uint8)[offsets[0] : offsets[-1]]]
    out = np.empty((len(texts), n), dtype=np.int64)
    for k in range(n):
        upto = np.concatenate([[0], np.cumsum(marks == k)])
        out[:, k] = np.diff(upto[offsets - offsets[0]])
    return out


def from_vector(df: DataFrame, item: str, vec: str, how: str = "softmax") -> DataFrame:
    """(item_id, n_sym, p) of dense vectors by softmax, shifted by the largest coordinate; narrow."""
    if how != "softmax":
        raise ValueError(how)
    v = F.transform(vec, lambda x: x.cast("double"))
    powers = bound(v, lambda v: bound(F.array_max(v), lambda top: F.transform(v, lambda x: F.exp(x - top))))
    shares = bound(powers, lambda e: bound(F.aggregate(e, F.lit(0.0), lambda s, x: s + x), lambda total: F.transform(e, lambda x: x / total)))
    return df.select(F.col(item).alias("item_id"), F.size(vec).cast("long").alias("n_sym"), shares.alias("p"))


def bound(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of a value that is computed once for a row, not once for each element that a lambda walks over."""
    return F.transform(F.array(value), body)[0]


def long_form(df: DataFrame, item: str, symbols: str) -> DataFrame:
    """(item_id, symbol, cnt, p) for large alphabets from an array of symbols: one shuffle, and a window on the same key."""
    counts = df.select(F.col(item).alias("item_id"), F.explode(symbols).alias("symbol")).repartition("item_id").groupBy("item_id", "symbol").agg(F.count("*").alias("cnt"))
    return counts.withColumn("p", F.col("cnt") / F.sum("cnt").over(Window.partitionBy("item_id")))


def from_long(df: DataFrame, n: int) -> DataFrame:
    """Dense vectors from rows (item_id, symbol, p); absent symbols have probability 0."""
    held = df.groupBy("item_id").agg(F.map_from_entries(F.collect_list(F.struct("symbol", "p"))).alias("m"))
    return held.select("item_id", F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda i: F.coalesce(F.try_element_at("m", i), F.lit(0.0))).alias("p"))


def exploded(df: DataFrame, vector: str = "p", name: str = "p") -> DataFrame:
    """A row per symbol: the other columns, n and the value."""
    rest = [c for c in df.columns if c != vector]
    return df.select(*rest, F.posexplode(vector).alias("n", name))


def collapse_types(items: DataFrame) -> DataFrame:
    """Items of equal SPV merged, their weights added: exact, as costs depend on p alone. Bounds the loops' input by the number of types."""
    weights = [c for c in items.columns if c in ("f", "w0", "w1", "w2")]
    return items.groupBy("p").agg(F.min("item_id").alias("item_id"), *(F.sum(c).alias(c) for c in weights)).select("item_id", "p", *weights)


def valid(df: DataFrame, tolerance: float = 1e-9) -> Column:
    """Whether p lies on the simplex."""
    return F.forall("p", lambda x: x >= 0) & (F.abs(F.aggregate("p", F.lit(0.0), lambda s, x: s + x) - 1) <= tolerance)
