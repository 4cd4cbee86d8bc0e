"""Repetition coverage: how much of a text lies inside repeated n-grams and lines.

Rolling hashes of several n-gram lengths are taken over the words of whole texts in
numpy. A word is covered at length n when some window of n words that holds it repeats
an earlier window of the text; coverage is the share of the text's word characters that
covered words hold, and is limited for each length. So is the share of word characters
in lines that repeat an earlier line.

Edge cases: a null or empty text has no words, so every count is 0 and the base rule
(too few words) rejects it. Repeated rows get the same row twice. Any other columns,
whatever their names, pass through ``filter_quality`` untouched.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .session import arrow_map, column, fields
from .textscan import BLANKS, Hasher, Texts, Words, chained, code_points, mix64, row_sums, separator_table, sliced

SYMBOLS = separator_table(b"#*$%&|<>")


@dataclass(frozen=True)
class RepetitionRules:
    """Published limits for characters in duplicate n-grams (5 to 10 words), for duplicate lines and for symbols to words."""

    min_words: int = 50
    max_repeat_words_percent: int = 50
    max_covered_percent: tuple[tuple[int, int], ...] = ((5, 15), (6, 14), (7, 13), (8, 12), (9, 11), (10, 10))
    max_line_char_percent: int = 20
    max_symbols_per_100_words: int = 10


RULES = RepetitionRules()
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


def repeated(values: np.ndarray) -> np.ndarray:
    """True where a value occurs at least twice."""
    if len(values) < 2:
        return np.zeros(len(values), dtype=bool)
    ordered = np.sort(values)
    twice = np.unique(ordered[1:][ordered[1:] == ordered[:-1]])
    if not len(twice):
        return np.zeros(len(values), dtype=bool)
    at = np.searchsorted(twice, values)
    at[at == len(twice)] = 0
    return twice[at] == values


class RepetitionScan:
    """Measures of each row of a slice of texts."""

    def __init__(self, rules: RepetitionRules = RULES):
        self.rules, self.hasher = rules, Hasher(fold_case=False)

    def lines(self, texts: Texts, words: Words, hashes: np.ndarray, chars: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Repeated lines of each row, and the word characters in them; the first of equal lines doesn't count.

        A line is known by its bytes: equal lines have equal bytes, white space included.
        """
        data = texts.data
        breaks = np.flatnonzero(data == 10)
        starts = np.union1d(texts.offsets[:-1][np.diff(texts.offsets) > 0], np.setdiff1d(breaks + 1, texts.offsets))
        starts = starts[starts < len(data)]
        rows = np.searchsorted(texts.offsets, starts, side="right") - 1
        ends = np.minimum(np.append(starts[1:], len(data)), texts.offsets[rows + 1])
        at = np.searchsorted(breaks, starts)
        stop = np.append(breaks, len(data))[at]
        ends = np.minimum(ends, stop)
        first, last = np.searchsorted(words.starts, starts), np.searchsorted(words.starts, ends)
        full = last > first
        starts, ends, rows, first, last = starts[full], ends[full], rows[full], first[full], last[full]
        span = _Spans(starts, ends)
        keys = self.hasher(texts, span) ^ mix64(rows.astype(np.uint64) + np.uint64(1))
        again = later(keys)
        totals = np.zeros(len(chars) + 1, dtype=np.int64)
        np.cumsum(chars, out=totals[1:])
        inside = (totals[last] - totals[first]) * again
        n = len(texts)
        return np.bincount(rows, weights=again, minlength=n).astype(np.int64), np.bincount(rows, weights=inside, minlength=n).astype(np.int64)

    def __call__(self, texts: Texts) -> dict[str, np.ndarray]:
        words = Words(texts, BLANKS)
        points = code_points(texts)
        chars = points[words.ends] - points[words.starts]
        hashes = self.hasher(texts, words)
        symbols = np.zeros(len(texts.data) + 1, dtype=np.int64)
        np.cumsum(SYMBOLS[texts.data], out=symbols[1:])
        out = {
            "n_words": words.counts.astype(np.int64),
            "word_chars": row_sums(chars, words.firsts),
            "n_symbols": symbols[texts.offsets[1:]] - symbols[texts.offsets[:-1]],
        }
        out["n_dup_lines"], out["dup_line_chars"] = self.lines(texts, words, hashes, chars)
        salt = mix64(words.rows.astype(np.uint64) + np.uint64(1))
        starts = np.arange(len(words))
        for n in sorted({3, *(n for n, _ in self.rules.max_covered_percent)}):
            starts = starts[starts + n <= len(words)]
            starts = starts[words.rows[starts] == words.rows[starts + n - 1]] if len(starts) else starts
            windows = _windows(hashes, starts, n) ^ salt[starts]
            twice = repeated(windows)
            starts, windows = starts[twice], windows[twice]  # a repeated longer window begins with a repeated shorter one
            if n == 3:
                out["n_repeat_words"] = row_sums(_covered(starts, n, len(words)), words.firsts)
            if n in dict(self.rules.max_covered_percent):
                out[f"covered_{n}"] = row_sums(chars * _covered(starts[later(windows)], n, len(words)), words.firsts)
        r = self.rules
        out["base_failed"] = (out["n_words"] < r.min_words) | (100 * out["n_repeat_words"] > r.max_repeat_words_percent * out["n_words"])
        total = out["word_chars"]
        bad = out["base_failed"] | (100 * out["dup_line_chars"] > r.max_line_char_percent * total) | (100 * out["n_symbols"] > r.max_symbols_per_100_words * out["n_words"])
        for n, most in r.max_covered_percent:
            bad |= 100 * out[f"covered_{n}"] > most * total
        out["kept"] = ~bad
        return out


def later(values: np.ndarray) -> np.ndarray:
    """True where an equal value stands before."""
    order = np.argsort(values, kind="stable")
    out = np.zeros(len(values), dtype=bool)
    out[order[1:]] = values[order[1:]] == values[order[:-1]]
    return out


def _covered(starts: np.ndarray, width: int, n: int) -> np.ndarray:
    """True for the n words that lie in a window of ``width`` words from one of ``starts``."""
    edge = np.zeros(n + 1, dtype=np.int64)
    np.add.at(edge, starts, 1)
    np.add.at(edge, starts + width, -1)
    return np.cumsum(edge[:-1]) > 0


class _Spans:
    def __init__(self, starts: np.ndarray, ends: np.ndarray):
        self.starts, self.ends = starts, ends


def _windows(hashes: np.ndarray, starts: np.ndarray, n: int) -> np.ndarray:
    if len(starts) > len(hashes) // 4:
        return chained(hashes, n)[starts]
    return chained(hashes[(starts[:, None] + np.arange(n)).ravel()], n)[::n] if len(starts) else np.zeros(0, np.uint64)


def measure_quality(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", rules: RepetitionRules = RULES) -> DataFrame:
    """One row of measures and verdicts for each row of ``docs``; narrow, no shuffle."""
    longs = [*MEASURES, "dup_line_chars", *(f"covered_{n}" for n, _ in rules.max_covered_percent)]
    schema = fields(docs, [id_column], *((c, "long") for c in longs), ("base_failed", "boolean"), ("kept", "boolean"))

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        measure = RepetitionScan(rules)
        for batch in batches:
            for rows, texts in sliced(pa.RecordBatch.from_arrays(batch.columns, names=["id", "text"]), "text"):
                out = measure(texts)
                yield pa.RecordBatch.from_arrays([rows.column(0), *(pa.array(out[c]) for c in longs), pa.array(out["base_failed"]), pa.array(out["kept"])], names=[id_column, *longs, "base_failed", "kept"])

    return docs.select(column(id_column), column(text_column)).transform(arrow_map, scan, schema)


def filter_quality(docs: DataFrame, text_column: str = "text", rules: RepetitionRules = RULES) -> DataFrame:
    """The rows of ``docs`` whose texts pass, all columns kept; narrow, no shuffle."""
    place = docs.columns.index(text_column)

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        measure = RepetitionScan(rules)
        for batch in batches:
            named = pa.RecordBatch.from_arrays(batch.columns, names=[f"c{i}" for i in range(batch.num_columns)])
            masks = [measure(texts)["kept"] for _, texts in sliced(named, f"c{place}")]
            if masks:
                yield batch.filter(pa.array(np.concatenate(masks)))

    return docs.transform(arrow_map, keep, docs.schema)
