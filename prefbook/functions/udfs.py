"""Arrow UDFs of the codec, and a reference aggregate of the weighted mean."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

from prefbook.operators.codec import classes_of, decode, encode


def encode_text(text: Column, classes: list[str], q: np.ndarray, how: str = "ceil") -> Column:
    """struct(book, bits): a text coded by character class under its cheapest book; null where no book has its symbols."""

    @F.pandas_udf("book int, bits string")
    def run(texts: pd.Series) -> pd.DataFrame:
        rows = [encode(classes_of(t or "", classes), q, how) or (None, None) for t in texts]
        return pd.DataFrame(rows, columns=["book", "bits"])

    return run(text)


def decode_bits(book: Column, bits: Column, q: np.ndarray, how: str = "ceil") -> Column:
    """Array of symbols; null for bits that are no whole sequence of the book's codewords."""

    @F.pandas_udf("array<int>")
    def run(books: pd.Series, words: pd.Series) -> pd.Series:
        return pd.Series([None if pd.isna(k) or w is None else decode(w, list(q[int(k)]), how) for k, w in zip(books, words)], dtype=object)

    return run(book, bits)


def weighted_mean(p: Column, w: Column) -> Column:
    """Weighted mean of vectors as a grouped Arrow aggregate; sums of columns are the fast path, and this their check."""

    @F.pandas_udf("array<double>")
    def run(vectors: pd.Series, weights: pd.Series) -> np.ndarray:
        return (np.stack(vectors) * weights.to_numpy()[:, None]).sum(axis=0) / weights.sum()

    return run(p, w)
