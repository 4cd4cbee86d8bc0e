"""Vectorised word scanning over the UTF-8 buffers of Arrow string columns.

A batch of texts is one byte array with row offsets. Words are maximal runs of
bytes that a 256-entry table does not call separators; no word crosses a row.
All separators used here are ASCII, so byte runs are character runs.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Text bytes that are scanned at once; bounds the temporary arrays of a task.
SLICE_BYTES = 1 << 19

_MULT = np.uint64(0x9E3779B97F4A7C15 | 1)
_MIX_A = np.uint64(0xBF58476D1CE4E5B9)
_MIX_B = np.uint64(0x94D049BB133111EB)


def separator_table(separators: bytes) -> np.ndarray:
    table = np.zeros(256, dtype=bool)
    table[list(separators)] = True
    return table


#: Space and the five ASCII controls 0x09 to 0x0D.
BLANKS = separator_table(b" \t\n\v\f\r")
#: Every ASCII character but digits and letters.
NOT_ALNUM = separator_table(bytes(b for b in range(128) if not (48 <= b < 58 or 65 <= b < 91 or 97 <= b < 123)))


def mix64(x: np.ndarray) -> np.ndarray:
    """Bijective scrambling of unsigned 64-bit values."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= _MIX_A
    x ^= x >> np.uint64(27)
    x *= _MIX_B
    x ^= x >> np.uint64(31)
    return x


def lower_table() -> np.ndarray:
    table = np.arange(256, dtype=np.uint8)
    table[65:91] += 32
    return table


#: Places of a word whose codes are tabulated.
TABLED = 256


def byte_codes(fold_case: bool) -> np.ndarray:
    """A code for each byte at each of the first TABLED places, unrelated to all others."""
    codes = mix64(mix64(np.arange(1, TABLED * 256 + 1, dtype=np.uint64) * _MULT) + _MIX_B).reshape(TABLED, 256)
    return (codes[:, lower_table()] if fold_case else codes).ravel()


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd multiplier and of its inverse modulo 2**64."""
    inverse = pow(int(_MULT), -1, 1 << 64)
    up, down = np.full(n, _MULT, dtype=np.uint64), np.full(n, np.uint64(inverse), dtype=np.uint64)
    up[:1] = 1
    down[:1] = 1
    return np.multiply.accumulate(up), np.multiply.accumulate(down)


class Texts:
    """Bytes and row offsets of a slice of a string column; null counts as empty."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray):
        self.data, self.offsets = data, offsets

    def __len__(self) -> int:
        return len(self.offsets) - 1


def texts_of(column: pa.Array) -> Texts:
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if not (pa.types.is_string(column.type) or pa.types.is_large_string(column.type)):
        column = column.cast(pa.large_string())
    if column.null_count:
        column = pc.fill_null(column, "")
    if len(column) == 0:
        return Texts(np.zeros(0, np.uint8), np.zeros(1, np.int64))
    wide = pa.types.is_large_string(column.type)
    _, at, body = column.buffers()
    offsets = np.frombuffer(at, dtype=np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data = np.frombuffer(body, dtype=np.uint8)[offsets[0] : offsets[-1]] if body is not None and offsets[-1] > offsets[0] else np.zeros(0, np.uint8)
    return Texts(data, offsets - offsets[0])


def sliced(batch: pa.RecordBatch, column: str, limit: int = SLICE_BYTES) -> Iterator[tuple[pa.RecordBatch, Texts]]:
    """Runs of rows whose texts hold at most ``limit`` bytes together, or one longer row."""
    whole = texts_of(batch.column(batch.schema.get_field_index(column)))
    at, n = 0, len(whole)
    while at < n:
        end = max(at + 1, int(np.searchsorted(whole.offsets, whole.offsets[at] + limit, side="right")) - 1)
        yield batch.slice(at, end - at), Texts(whole.data[whole.offsets[at] : whole.offsets[end]], whole.offsets[at : end + 1] - whole.offsets[at])
        at = end
    trim()


def trim() -> None:
    """Give memory that is free back to the system, so that idle workers hold little beside a busy one."""
    pa.default_memory_pool().release_unused()
    if hasattr(libc := ctypes.CDLL(None), "malloc_trim"):
        libc.malloc_trim(0)


class Words:
    """Start and end bytes of each word, its row, and the first word of each row."""

    def __init__(self, texts: Texts, separators: np.ndarray):
        data, offsets = texts.data, texts.offsets
        inside = np.zeros(len(data) + 2, dtype=bool)
        np.logical_not(separators[data], out=inside[1:-1])
        body = inside[1:-1]
        opens, closes = body & ~inside[:-2], body & ~inside[2:]
        edges = offsets[1:-1]
        edges = edges[(edges > 0) & (edges < len(data))]
        opens[edges] |= body[edges]
        closes[edges - 1] |= body[edges - 1]
        self.starts, self.ends = np.flatnonzero(opens), np.flatnonzero(closes) + 1
        self.firsts = np.searchsorted(self.starts, offsets)
        self.counts = np.diff(self.firsts)
        self.rows = np.repeat(np.arange(len(texts)), self.counts)

    def __len__(self) -> int:
        return len(self.starts)


class Hasher:
    """64-bit hashes of words: sums of a code for each byte at its place.

    Codes of different places aren't multiples of each other, so words of a regular build don't meet,
    as they do in polynomials modulo 2**64.
    """

    def __init__(self, fold_case: bool):
        self.codes = byte_codes(fold_case)

    def __call__(self, texts: Texts, words: Words) -> np.ndarray:
        n, starts, ends = len(texts.data), words.starts, words.ends
        if not len(starts):
            return np.zeros(0, dtype=np.uint64)
        lengths = ends - starts
        place = np.arange(n, dtype=np.int32)  # a slice has less than 2**31 bytes
        place[starts[0] :] -= np.repeat(starts.astype(np.int32), np.diff(np.append(starts, n)))
        far = np.flatnonzero(place >= TABLED) if lengths.max() > TABLED else starts[:0]
        beyond = (place[far] // TABLED).astype(np.uint64) * _MIX_A
        place &= TABLED - 1
        place <<= 8
        place |= texts.data
        terms = self.codes[place]
        terms[far] = mix64(terms[far] + beyond)
        sums = np.zeros(n + 1, dtype=np.uint64)
        np.cumsum(terms, out=sums[1:])
        return mix64(sums[ends] - sums[starts] + lengths.astype(np.uint64) * _MULT)


def chained(hashes: np.ndarray, width: int) -> np.ndarray:
    """Hash of each run of ``width`` consecutive values; one shorter by width - 1."""
    n = len(hashes) - width + 1
    if n <= 0:
        return np.zeros(0, dtype=np.uint64)
    total = np.full(n, width, dtype=np.uint64) * _MIX_B
    for k in range(width):
        total = total * _MULT + hashes[k : k + n]
    return mix64(total)


def code_points(texts: Texts) -> np.ndarray:
    """Code points before each byte, and in all."""
    out = np.zeros(len(texts.data) + 1, dtype=np.int64)
    np.cumsum((texts.data & 0xC0) != 0x80, out=out[1:])
    return out


def row_sums(values: np.ndarray, firsts: np.ndarray) -> np.ndarray:
    """Sums of runs ``firsts[i]:firsts[i + 1]``; empty runs give 0."""
    total = np.zeros(len(values) + 1, dtype=np.int64)
    np.cumsum(values, out=total[1:])
    return total[firsts[1:]] - total[firsts[:-1]]


def binary_rows(blob: np.ndarray, bounds: np.ndarray) -> pa.Array:
    """A binary column whose row i holds bytes bounds[i]:bounds[i + 1] of blob."""
    blob = np.ascontiguousarray(blob).view(np.uint8)
    return pa.Array.from_buffers(pa.large_binary(), len(bounds) - 1, [None, pa.py_buffer(bounds.astype(np.int64)), pa.py_buffer(blob)]).cast(pa.binary())
