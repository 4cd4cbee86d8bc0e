"""Multi-pattern word search for benchmark passages in whole texts, by block shifts.

Patterns are runs of benchmark words, all runs of ``width`` words, or the whole of a
shorter item. For each pattern length a shift table over hashed two-word blocks tells how
far a search position may move; where it may not move, the hash of the block selects a
bucket of patterns, and only an equal run of words, compared word by word as text, counts.
Many positions of a slice of texts are moved at once.

Patterns are sent to the executors in blocks of at most ``block_patterns``; a benchmark
with more is searched for in several passes over the texts, whose findings are united.

Edge cases: a null or empty text or item has no words. Repeated items count as items of
their own if their ids differ. Equal patterns of several items hit for each of them.
Repeated rows get equal output. Null item ids don't appear in the list of items. Other
columns, whatever their names, pass through ``drop_contaminated`` untouched.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .session import arrow_map, column, fields, settle
from .textscan import NOT_ALNUM, Hasher, Texts, Words, chained, lower_table, row_sums, sliced, texts_of


@dataclass(frozen=True)
class SearchParameters:
    width: int = 10
    table_bits: int = 16
    lanes: int = 2048
    block_patterns: int = 500_000


PARAMETERS = SearchParameters()
_LOWER = lower_table()


def _spelled(texts: Texts, starts: np.ndarray, ends: np.ndarray) -> tuple[bytes, ...]:
    return tuple(_LOWER[texts.data[a:b]].tobytes() for a, b in zip(starts.tolist(), ends.tolist()))


class Searcher:
    """Shift tables and buckets of one block of patterns; items are known by number."""

    def __init__(self, patterns: list[tuple[tuple[bytes, ...], list[int]]], p: SearchParameters):
        self.p, self.hasher = p, Hasher(fold_case=True)
        by_length = defaultdict(list)
        for words, items in patterns:
            by_length[len(words)].append((words, items))
        self.groups = [self._table(m, found) for m, found in sorted(by_length.items())]

    def _hashes(self, words: list[bytes]) -> np.ndarray:
        data = np.frombuffer(b" ".join(words), dtype=np.uint8)
        texts = Texts(data, np.array([0, len(data)]))
        return self.hasher(texts, Words(texts, NOT_ALNUM))

    def _blocks(self, hashes: np.ndarray, block: int) -> np.ndarray:
        return (chained(hashes, block) & np.uint64((1 << self.p.table_bits) - 1)).astype(np.int64)

    def _table(self, m: int, patterns: list) -> tuple:
        block = min(2, m)
        shift = np.full(1 << self.p.table_bits, m - block + 1, dtype=np.int64)
        buckets = defaultdict(list)
        for words, items in patterns:
            blocks = self._blocks(self._hashes(list(words)), block)
            np.minimum.at(shift, blocks, np.arange(m - block, -1, -1))
            buckets[int(blocks[-1])].append((words, items))
        return m, block, shift, dict(buckets)

    def occurrences(self, texts: Texts, words: Words) -> Iterator[tuple[int, int, int, list[int]]]:
        """Row, first word, end word and items of each occurrence of a pattern."""
        hashes = self.hasher(texts, words)
        for m, block, shift, buckets in self.groups:
            if len(words) < m:
                continue
            blocks = self._blocks(hashes, block)
            for at in self._stops(blocks, shift, m, block):
                first = at + block - m
                row = int(words.rows[first])
                if row != words.rows[at + block - 1]:
                    continue
                own = None
                for spelled, items in buckets.get(int(blocks[at]), ()):
                    own = own or _spelled(texts, words.starts[first : first + m], words.ends[first : first + m])
                    if own == spelled:
                        yield row, first, first + m, items

    def __call__(self, texts: Texts) -> tuple[np.ndarray, np.ndarray, list[set[int]]]:
        """Words of each row, hit words of each row, and the items found in each."""
        words = Words(texts, NOT_ALNUM)
        edge = np.zeros(len(words) + 1, dtype=np.int64)
        found: list[set[int]] = [set() for _ in range(len(texts))]
        for row, first, end, items in self.occurrences(texts, words):
            edge[first] += 1
            edge[end] -= 1
            found[row].update(items)
        return words.counts, row_sums(np.cumsum(edge[:-1]) > 0, words.firsts), found

    def _stops(self, blocks: np.ndarray, shift: np.ndarray, m: int, block: int) -> list[int]:
        """Blocks that a pattern may end with, in order; skipped positions are never looked at."""
        low, high = m - block, len(blocks)
        lanes = min(self.p.lanes, high - low)
        bounds = np.linspace(low, high, lanes + 1).astype(np.int64)
        at, end, stops = bounds[:-1].copy(), bounds[1:], []
        live = np.flatnonzero(at < end)
        while len(live):
            here = at[live]
            step = shift[blocks[here]]
            stops.append(here[step == 0])
            at[live] = here + np.maximum(step, 1)
            live = live[at[live] < end[live]]
        return np.sort(np.concatenate(stops)).tolist() if stops else []


def _item_patterns(batches: Iterator[pa.RecordBatch], width: int) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        texts = texts_of(batch.column(1))
        words = Words(texts, NOT_ALNUM)
        items, patterns = [], []
        for row, item in enumerate(batch.column(0).to_pylist()):
            a, n = int(words.firsts[row]), int(words.counts[row])
            spelled = _spelled(texts, words.starts[a : a + n], words.ends[a : a + n])
            runs = {spelled[i : i + width] for i in range(n - width + 1)} if n >= width else ({spelled} if n else set())
            items += [item] * len(runs)
            patterns += [b" ".join(run).decode() for run in runs]
        yield pa.RecordBatch.from_arrays([pa.array(items, pa.string()), pa.array(patterns, pa.string())], names=["item", "pattern"])


def pattern_blocks(benchmark: DataFrame, id_column: str, text_column: str, p: SearchParameters) -> tuple[DataFrame, int]:
    """(pattern, items, block) and the number of blocks; each block holds about block_patterns patterns."""
    source = benchmark.select(F.coalesce(column(id_column).cast("string"), F.lit("")).alias("item"), column(text_column).alias("text"))
    runs = source.transform(arrow_map, lambda b: _item_patterns(b, p.width), "item string, pattern string")
    runs = settle(runs.groupBy("pattern").agg(F.sort_array(F.collect_set("item")).alias("items")))
    n = max(1, -(-runs.count() // p.block_patterns))
    return runs.withColumn("block", F.pmod(F.xxhash64("pattern"), F.lit(n))), n


def _search(docs: DataFrame, patterns: DataFrame, n_blocks: int, p: SearchParameters, schema, emit) -> list[DataFrame]:
    out = []
    for block in range(n_blocks):
        rows = [(r["pattern"], r["items"]) for r in patterns.filter(F.col("block") == block).collect()]
        names = sorted({i for _, items in rows for i in items})
        place = {name: k for k, name in enumerate(names)}
        sent = docs.sparkSession.sparkContext.broadcast(([(tuple(w.encode() for w in text.split(" ")), [place[i] for i in items]) for text, items in rows], names))

        def scan(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            known, labels = sent.value
            search = Searcher(known, p)
            for batch in batches:
                yield from emit(batch, search, labels)

        out.append(docs.transform(arrow_map, scan, schema))
    return out


def find_contamination(docs: DataFrame, benchmark: DataFrame, id_column: str = "doc_id", text_column: str = "text", item_column: str = "item_id", item_text_column: str | None = None, parameters: SearchParameters = PARAMETERS) -> DataFrame:
    """One row per row of ``docs``: id, n_words, n_hit, n_items, items (ids as sorted strings), contaminated.

    The benchmark's texts are in ``item_text_column``, or in a column of the same name as the documents'.
    """
    p = parameters
    patterns, n_blocks = pattern_blocks(benchmark, item_column, item_text_column or text_column, p)
    texts = docs.select(column(id_column).alias("id"), column(text_column).alias("text"))
    if n_blocks > 1:
        return _united(texts, id_column, patterns, n_blocks, p)
    schema = fields(texts, ["id"], ("n_words", "long"), ("n_hit", "long"), ("items", "array<string>"))

    def emit(batch: pa.RecordBatch, search: Searcher, labels: list[str]) -> Iterator[pa.RecordBatch]:
        for rows, part in sliced(batch, "text"):
            counts, hit, found = search(part)
            yield pa.RecordBatch.from_arrays(
                [rows.column(0), pa.array(counts, pa.int64()), pa.array(hit, pa.int64()), pa.array([sorted(labels[k] for k in f if labels[k]) for f in found], pa.list_(pa.string()))], names=["id", "n_words", "n_hit", "items"]
            )

    return _described(_search(texts, patterns, 1, p, schema, emit)[0], id_column)


def _described(found: DataFrame, id_column: str) -> DataFrame:
    return found.select(F.col("id").alias(id_column), "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), "items", (F.col("n_hit") > 0).alias("contaminated"))


def _united(texts: DataFrame, id_column: str, patterns: DataFrame, n_blocks: int, p: SearchParameters) -> DataFrame:
    """Several passes: the hit words of a text are united as runs of positions."""
    keyed = texts.withColumn("row_key", F.xxhash64("text"))
    schema = "id_key string, row_key long, n_words long, runs array<struct<a:long,b:long>>, items array<string>"
    keyed = keyed.select(F.col("id").cast("string").alias("id_key"), "row_key", "text")  # rows that repeat add runs that unite with their own

    def emit(batch: pa.RecordBatch, search: Searcher, labels: list[str]) -> Iterator[pa.RecordBatch]:
        for rows, part in sliced(batch, "text"):
            words = Words(part, NOT_ALNUM)
            runs: list[list[dict]] = [[] for _ in range(len(part))]
            items: list[set[int]] = [set() for _ in range(len(part))]
            for row, first, end, own in search.occurrences(part, words):
                runs[row].append({"a": first - int(words.firsts[row]), "b": end - int(words.firsts[row])})
                items[row].update(own)
            counts, found = words.counts, [sorted(labels[k] for k in f if labels[k]) for f in items]
            yield pa.RecordBatch.from_arrays(
                [rows.column(0), rows.column(1), pa.array(counts, pa.int64()), pa.array(runs, pa.list_(pa.struct([("a", pa.int64()), ("b", pa.int64())]))), pa.array(found, pa.list_(pa.string()))],
                names=["id_key", "row_key", "n_words", "runs", "items"],
            )

    parts = _search(keyed, patterns, n_blocks, p, schema, emit)
    every = parts[0]
    for part in parts[1:]:
        every = every.unionByName(part)
    merged = every.groupBy("id_key", "row_key").agg(F.first("n_words").alias("n_words"), F.array_sort(F.flatten(F.collect_list("runs"))).alias("runs"), F.sort_array(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"))
    step = lambda s, r: F.struct((s["hit"] + F.greatest(F.lit(0), r["b"] - F.greatest(r["a"], s["end"]))).alias("hit"), F.greatest(s["end"], r["b"]).alias("end"))
    zero = F.struct(F.lit(0).cast("long").alias("hit"), F.lit(0).cast("long").alias("end"))
    merged = merged.withColumn("n_hit", F.aggregate("runs", zero, step, lambda s: s["hit"]))
    rows = texts.select("id", F.col("id").cast("string").alias("id_of"), F.xxhash64("text").alias("key_of"))
    joined = rows.join(merged, F.col("id_of").eqNullSafe(F.col("id_key")) & (F.col("key_of") == F.col("row_key")))
    return _described(joined, id_column)


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, id_column: str = "doc_id", text_column: str = "text", item_column: str = "item_id", item_text_column: str | None = None, parameters: SearchParameters = PARAMETERS) -> DataFrame:
    """The rows of ``docs`` without any occurrence, all columns kept; narrow, one pass for each block of patterns."""
    patterns, n_blocks = pattern_blocks(benchmark, item_column, item_text_column or text_column, parameters)
    place = docs.columns.index(text_column)

    def emit(batch: pa.RecordBatch, search: Searcher, labels: list[str]) -> Iterator[pa.RecordBatch]:
        plain = pa.RecordBatch.from_arrays(batch.columns, names=[f"c{i}" for i in range(batch.num_columns)])
        masks = [search(part)[1] == 0 for _, part in sliced(plain, f"c{place}")]
        if masks:
            yield batch.filter(pa.array(np.concatenate(masks)))

    for block in range(n_blocks):
        docs = _search(docs, patterns.filter(F.col("block") == block).withColumn("block", F.lit(0)), 1, parameters, docs.schema, emit)[0]
    return docs
