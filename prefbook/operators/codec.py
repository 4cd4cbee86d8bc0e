"""Integer prefix codes from codebooks, coding and decoding, and codes for more than two users' channels."""

from __future__ import annotations

import heapq
import re
from collections.abc import Iterator
from functools import lru_cache
from itertools import combinations
from math import ceil, log2

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type
from pyspark.sql.types import StructType


def code_lengths(q: list[float], how: str = "ceil") -> dict[int, int]:
    """Whole bits per symbol of positive share: ideal lengths rounded up, or the best prefix code (Huffman's)."""
    present = [i for i, x in enumerate(q) if x > 0]
    if how == "ceil" or len(present) < 2:
        return {i: max(1, ceil(-log2(q[i]) - 1e-12)) for i in present}
    heap = [(q[i], i, [i]) for i in present]
    heapq.heapify(heap)
    depth = dict.fromkeys(present, 0)
    while len(heap) > 1:
        (a, x, left), (b, y, right) = heapq.heappop(heap), heapq.heappop(heap)
        for i in left + right:
            depth[i] += 1
        heapq.heappush(heap, (a + b, min(x, y), left + right))
    return depth


def integer_code(q: list[float], how: str = "ceil") -> dict[int, tuple[int, str]]:
    """(bits, codeword) of each symbol, canonical: codewords count up in the order of length and symbol."""
    lengths = code_lengths(q, how)
    code, last, out = 0, 0, {}
    for symbol, bits in sorted(lengths.items(), key=lambda x: (x[1], x[0])):
        code <<= bits - last
        out[symbol] = (bits, format(code, f"0{bits}b"))
        code, last = code + 1, bits
    return out


def code_tables(items: DataFrame, how: str = "ceil") -> DataFrame:
    """Rows (item_id, symbol, ideal_bits, code_bits, codeword) of every item's own book p; narrow, equal books of a task are coded once."""
    schema = StructType([items.schema["item_id"]]).add("symbol", "integer").add("ideal_bits", "double").add("code_bits", "integer").add("codeword", "string")
    types = pa.schema([(x.name, to_arrow_type(x.dataType)) for x in schema])

    def code(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        @lru_cache(maxsize=65536)
        def rows(q: tuple[float, ...]) -> list[tuple[int, float, int, str]]:
            return [(s, 0.0 - log2(q[s]), bits, word) for s, (bits, word) in sorted(integer_code(list(q), how).items())]

        for batch in batches:
            if not batch.num_rows:
                continue
            coded = [rows(tuple(q)) for q in batch.column(1).to_pylist()]
            ids = batch.column(0).take(pa.array(np.repeat(np.arange(len(coded)), [len(x) for x in coded])))
            columns = list(zip(*(row for x in coded for row in x))) or [()] * 4
            yield pa.RecordBatch.from_arrays([ids, *(pa.array(x, t) for x, t in zip(columns, types.types[1:]))], schema=types)

    return items.select("item_id", "p").mapInArrow(code, schema)


def classes_of(text: str, classes: list[str]) -> list[int]:
    """The symbol of each character: its class, or one more."""
    place = {c: k for k, group in enumerate(classes) for c in group}
    return [place.get(c, len(classes)) for c in text]


def encode(symbols: list[int], q: np.ndarray, how: str = "ceil") -> tuple[int, str] | None:
    """The cheapest book that has all the symbols, and the bits under it."""
    best = None
    counts = np.bincount(symbols, minlength=q.shape[1]) if symbols else np.zeros(q.shape[1])
    for k, row in enumerate(q):
        code = integer_code(list(row), how)
        if all(s in code for s in np.flatnonzero(counts)):
            size = sum(int(counts[s]) * bits for s, (bits, _) in code.items())
            if best is None or size < best[0]:
                best = (size, k, code)
    return None if best is None else (best[1], "".join(best[2][s][1] for s in symbols))


def decode(bits: str, row: list[float], how: str = "ceil") -> list[int] | None:
    """Symbols under one book, None where the bits are no whole sequence of its codewords."""
    words = {word: s for s, (_, word) in integer_code(list(row), how).items()}
    out, at = [], ""
    for b in bits:
        at += b
        if at in words:
            out.append(words[at])
            at = ""
    return None if at else out


def decode_by_trial(bits: str, q: np.ndarray, length: int, how: str = "ceil") -> list[tuple[int, list[int]]]:
    """All cached books under which the bits are exactly ``length`` symbols."""
    tried = [(k, decode(bits, list(row), how)) for k, row in enumerate(q)]
    return [(k, s) for k, s in tried if s is not None and len(s) == length]


class Codes:
    """Codewords and lengths of all books, made once; a symbol that a book lacks has no codeword there."""

    def __init__(self, q: np.ndarray, how: str = "ceil"):
        self.codes = [integer_code(list(row), how) for row in q]
        self.lengths = np.full(q.shape, np.inf)
        for k, code in enumerate(self.codes):
            for s, (bits, _) in code.items():
                self.lengths[k, s] = bits
        self.words = [{s: word for s, (_, word) in code.items()} for code in self.codes]
        self.symbols = [{word: chr(s) for s, word in words.items()} for words in self.words]
        self.patterns = [re.compile("|".join(sorted(x, key=len))) for x in self.symbols]

    def cheapest(self, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The book and the bits of each row of symbol counts; infinite where no book has all the symbols."""
        finite = np.where(np.isfinite(self.lengths), self.lengths, 0.0)
        bits = counts @ finite.T
        bits[(counts > 0).astype(float) @ (~np.isfinite(self.lengths)).T.astype(float) > 0] = np.inf
        return bits.argmin(axis=1), bits.min(axis=1)

    def encode(self, symbols: str, book: int) -> str:
        """Bits of a sequence of symbols, each symbol being the character of its number."""
        return symbols.translate({s: word for s, word in self.words[book].items()})

    def decode(self, bits: str, book: int) -> str | None:
        """Symbols under one book, None where the bits are no whole sequence of its codewords."""
        words = self.patterns[book].findall(bits)
        if sum(map(len, words)) != len(bits):
            return None
        return "".join(map(self.symbols[book].__getitem__, words))


class _Else(dict):
    """A translation table with a value for all other characters."""

    def __init__(self, table: dict[int, str], other: str):
        super().__init__(table)
        self.other = other

    def __missing__(self, key: int) -> str:
        self[key] = self.other
        return self.other

    def of(self, text: str | None) -> str:
        return (text or "").translate(self)


def _coded(df: DataFrame, item: str, text: str, classes: list[str], q: np.ndarray, how: str, schema: str, rows) -> DataFrame:
    sent = df.sparkSession.sparkContext.broadcast(q)
    source = df.select(F.col(item).alias("item_id"), F.col(text).alias("text"))
    table = StructType([source.schema["item_id"], *StructType.fromDDL(schema).fields])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codes = Codes(sent.value, how)
        n = sent.value.shape[1]
        marks = _Else({ord(c): chr(k) for k, group in enumerate(classes) for c in group}, chr(len(classes)))
        for batch in batches:
            symbols = [marks.of(t) for t in batch.column(1).to_pylist()]
            counts = np.array([[s.count(chr(k)) for k in range(n)] for s in symbols], dtype=float).reshape(-1, n)
            books, bits = codes.cheapest(counts)
            found = [rows(codes, s, int(k), b) for s, k, b in zip(symbols, books, bits)]
            columns = list(zip(*found)) if found else [()] * (len(table) - 1)
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, to_arrow_type(f.dataType)) for c, f in zip(columns, table.fields[1:]))], names=table.names)

    return source.mapInArrow(run, table)


def roundtrip(df: DataFrame, item: str, text: str, classes: list[str], q: np.ndarray, how: str = "ceil") -> DataFrame:
    """(item_id, symbols, book, bits, same): whole texts coded with the cheapest book and decoded, by tables made once a task."""

    def row(codes: Codes, symbols: str, book: int, bits: float) -> tuple:
        if not np.isfinite(bits):
            return len(symbols), None, None, False
        coded = codes.encode(symbols, book)
        return len(symbols), book, len(coded), codes.decode(coded, book) == symbols

    return _coded(df, item, text, classes, q, how, "symbols long, book int, bits long, same boolean", row)


def trial_decoding(df: DataFrame, item: str, text: str, classes: list[str], q: np.ndarray, how: str = "ceil") -> DataFrame:
    """(item_id, symbols, book, candidates, found): the receiver isn't told the book and tries all cached ones.

    Candidates are the books under which the bits are a whole number of codewords and give as many symbols as were sent;
    found says that the sender's book is one of them and gives the symbols that were sent.
    """

    def row(codes: Codes, symbols: str, book: int, bits: float) -> tuple:
        if not np.isfinite(bits):
            return len(symbols), None, 0, False
        coded = codes.encode(symbols, book)
        tried = {k: codes.decode(coded, k) for k in range(len(codes.codes))}
        fit = [k for k, s in tried.items() if s is not None and len(s) == len(symbols)]
        return len(symbols), book, len(fit), book in fit and tried[book] == symbols

    return _coded(df, item, text, classes, q, how, "symbols long, book int, candidates int, found boolean", row)


def user_channels(users: int) -> list[tuple[int, ...]]:
    """Channels of several users: the sets of users that can ask for one item at once, largest first."""
    return [c for size in range(users, 0, -1) for c in combinations(range(1, users + 1), size)]
