"""Perplexity of whole texts under an interpolated modified Kneser-Ney n-gram model of trusted text.

The model's grams are runs of ``order`` characters. Every code point is a symbol of its
own, of whatever script, so the model grows with the text that it is counted from. A gram
is an exact pair of integers, the packed characters before and the character.

All trusted texts are counted. Counts, their context totals and the lower orders'
continuation counts are tables sharded by context or gram and joined there: a seen gram
becomes one row with its probability, made of its own discounted count and of the row of
its shortened gram, and a seen context one row with the weight that it leaves to shorter
ones. Scoring joins the grams of the texts with those rows where the texts are: the rows
are cut into shards by the last two characters of their contexts, a shard is sent to the
executors, and each position of a text meets the one shard that its context belongs to.
A model of several shards is met in as many narrow steps over the texts, so no gram is
left out however large the model is. Grams of two characters and one are in every shard.

A text's perplexity is 2 to the power of its mean bits per character. It is kept if that
does not exceed its language's limit: a quantile of the trusted texts of the language,
read from a table of counts by perplexity step. Languages without enough trusted texts,
and null, share the limit of all trusted texts.

Edge cases: a null or empty text has no perplexity and is not kept. Labels of unknown
documents don't matter, repeated labels count once. A character that no trusted text has
costs as much as one of all code points after what the model leaves for it. Without any
trusted text every code point is as likely as any other, there is no limit, and all texts
with characters are kept. Repeated rows get equal output; extra columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .session import arrow_map, column, fields, settle
from .textscan import Texts, code_points, mix64, sliced

#: Bits of a packed character: its code point plus 1, or 0 for the place before a text. Three fit into a long.
BITS = 21
POINTS = 0x110000
_WIDE = (1 << BITS) - 1


@dataclass(frozen=True)
class ModelParameters:
    #: Characters of a gram, 1 to 4.
    order: int = 4
    quantile: float = 0.995
    #: Steps of the perplexity table per unit of log2; its size doesn't grow with the input.
    steps: int = 200
    least_trusted: int = 20
    #: Grams that are sent at once, some 60 bytes each in a task.
    shard_grams: int = 1_000_000
    filter_bits: int = 24


PARAMETERS = ModelParameters()


class Line:
    """The packed characters of a slice of texts, each text behind ``order`` - 1 empty places."""

    def __init__(self, texts: Texts, order: int):
        points = np.frombuffer(texts.data.tobytes().decode("utf-8", "replace").encode("utf-32-le"), dtype="<u4")
        self.firsts = code_points(texts)[texts.offsets]
        pad, n = order - 1, len(points)
        self.codes = np.zeros(n + pad * len(texts), dtype=np.int64)
        self.places = np.arange(n) + pad * (np.repeat(np.arange(len(texts)), np.diff(self.firsts)) + 1)
        self.codes[self.places] = points
        self.codes[self.places] += 1
        self.symbols = self.codes[self.places]

    def contexts(self, width: int, at: np.ndarray | None = None) -> np.ndarray:
        """The ``width`` characters before each position."""
        places = self.places if at is None else self.places[at]
        packed = np.zeros(len(places), dtype=np.int64)
        for back in range(width, 0, -1):
            packed = packed << BITS | self.codes[places - back]
        return packed


def gram_counts(texts: DataFrame, order: int) -> DataFrame:
    """(context, symbol, c) over all texts; each task adds up its own first."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = np.zeros((0, 2), np.int64)
        sums = np.zeros(0, np.int64)
        for batch in batches:
            for _, part in sliced(batch, "text"):
                line = Line(part, order)
                held, sums = _added(held, sums, np.stack([line.contexts(order - 1), line.symbols], axis=1))
                if len(sums) > 1 << 21:  # a task's table stays bounded; the sums meet again in the exchange
                    yield _counted(held, sums)
                    held, sums = held[:0], sums[:0]
        yield _counted(held, sums)

    return texts.select("text").transform(arrow_map, count, "context long, symbol long, c long").groupBy("context", "symbol").agg(F.sum("c").alias("c"))


def _added(held: np.ndarray, sums: np.ndarray, new: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pairs and their sums, with a count of one more for each new pair."""
    new, times = _runs(new, np.ones(len(new), dtype=np.int64))
    return _runs(np.concatenate([held, new]), np.concatenate([sums, times]))


def _runs(pairs: np.ndarray, times: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    if not len(pairs):
        return pairs, times
    key = gram_keys(pairs[:, 0], pairs[:, 1], 0)
    order = np.argsort(key, kind="stable")
    key = key[order]
    starts = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
    return pairs[order[starts]], np.add.reduceat(times[order], starts)


def _counted(held: np.ndarray, sums: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(held[:, 0]), pa.array(held[:, 1]), pa.array(sums)], names=["context", "symbol", "c"])


def gram_keys(contexts: np.ndarray, symbols: np.ndarray, width: int) -> np.ndarray:
    """A 64-bit hash of each gram: of 1e8 grams, no two agree but with a chance of three in ten thousand."""
    return mix64(mix64(contexts.astype(np.uint64) + np.uint64(width) * np.uint64(0x9E3779B97F4A7C15)) + symbols.astype(np.uint64))


def discounts(counts: DataFrame) -> list[float]:
    """The three discounts of an order, from how many grams occur once to four times."""
    n = [0.0] + [float(x or 0) for x in counts.agg(*(F.count_if(F.col("c") == k) for k in (1, 2, 3, 4))).first()]
    if not n[1] or not n[2]:
        return [0.5, 0.5, 0.5]
    y = n[1] / (n[1] + 2 * n[2])
    return [min(max(k - (k + 1) * y * n[k + 1] / n[k], 0.0), float(k)) if n[k] else k * y for k in (1, 2, 3)]


@dataclass(frozen=True)
class Level:
    """Rows of one order: ``grams`` (context, symbol, p) and ``contexts`` (context, rest), rest being what a context leaves to shorter ones."""

    grams: DataFrame
    contexts: DataFrame


def _level(counts: DataFrame, lower: Level | None, width: int) -> Level:
    d1, d2, d3 = discounts(counts)
    cut: Column = F.when(F.col("c") == 1, d1).when(F.col("c") == 2, d2).otherwise(d3)
    rows = counts.withColumn("d", cut)
    totals = settle(rows.groupBy("context").agg(F.sum("c").alias("total"), *(F.count_if(F.col("c") == k).alias(f"n{k}") for k in (1, 2)), F.count("*").alias("n")))
    spare = F.col("n1") * d1 + F.col("n2") * d2 + (F.col("n") - F.col("n1") - F.col("n2")) * d3
    totals = totals.select("context", "total", (spare / F.col("total")).alias("rest"))
    own = rows.join(totals, "context").select("context", "symbol", "rest", (F.greatest(F.lit(0.0), F.col("c") - F.col("d")) / F.col("total")).alias("own"))
    if lower is None:
        below = F.lit(1.0 / POINTS)
    else:
        short = F.col("context").bitwiseAND((1 << BITS * (width - 2)) - 1)
        own = own.withColumn("short", short).join(lower.grams.select(F.col("context").alias("short"), "symbol", F.col("p").alias("below")), ["short", "symbol"])
        below = F.col("below")
    grams = settle(own.select("context", "symbol", (F.col("own") + F.col("rest") * below).alias("p")))
    return Level(grams, totals.select("context", "rest"))


def train(texts: DataFrame, p: ModelParameters = PARAMETERS) -> list[Level]:
    """The levels of all orders from 1 on."""
    if not 1 <= p.order <= 4:
        raise ValueError("order must be 1 to 4: three characters fit into a long")
    by_order = [settle(gram_counts(texts, p.order))]
    for width in range(p.order - 1, 0, -1):  # continuation counts: the different symbols before a gram
        low = F.col("context").bitwiseAND((1 << BITS * (width - 1)) - 1)
        by_order.insert(0, settle(by_order[0].groupBy(low.alias("context"), "symbol").agg(F.count("*").alias("c"))))
    levels: list[Level] = []
    for width, counts in enumerate(by_order, 1):
        levels.append(_level(counts, levels[-1] if levels else None, width))
    return levels


def _shard_of(contexts, shards: int):
    """The shard of a packed context, by its last two characters; the same in numpy and in Spark."""
    if isinstance(contexts, Column):
        low = contexts.bitwiseAND((1 << 2 * BITS) - 1)
        return F.pmod(low.bitwiseXOR(F.shiftright(low, BITS) * 40503), F.lit(shards))
    low = contexts & ((1 << 2 * BITS) - 1)
    return (low ^ (low >> BITS) * 40503) % shards


class Shard:
    """Log2 probabilities of the grams and rests of the contexts of one shard."""

    def __init__(self, tables: list[tuple], number: int, shards: int):
        self.number, self.shards = number, shards
        self.levels = []
        for width, (contexts, symbols, p, heads, rests) in enumerate(tables, 1):
            keys = gram_keys(contexts, symbols, width)
            order, by = np.argsort(keys), np.argsort(heads)
            self.levels.append((keys[order], p[order], heads[by], rests[by]))
        keys, p = self.levels[-1][:2]
        # Most grams of the highest order are found at one look: where they lie alone in a table of eight times their number.
        self.shift = np.uint64(64 - max(10, int(8 * len(keys)).bit_length()))
        self.spots = np.zeros(1 << (64 - int(self.shift)), dtype=np.uint64)
        self.values = np.full(len(self.spots), np.nan, dtype=np.float32)
        at = (keys >> self.shift).astype(np.int64)
        self.spots[at] = keys
        self.values[at] = p

    def __call__(self, line: Line) -> np.ndarray:
        """Log2 probability of each character whose context belongs here, 0 elsewhere."""
        order = len(self.levels)
        contexts, symbols = line.contexts(order - 1), line.symbols
        mine = None
        if self.shards > 1:
            mine = np.flatnonzero(_shard_of(contexts, self.shards) == self.number)
            contexts, symbols = contexts[mine], symbols[mine]
        keys = gram_keys(contexts, symbols, order)
        at = (keys >> self.shift).astype(np.int64)
        out = self.values[at].astype(np.float64)
        missed = np.flatnonzero((self.spots[at] != keys) | np.isnan(out))
        out[missed] = self._slowly(contexts[missed], symbols[missed])
        if mine is None:
            return out
        whole = np.zeros(len(line.symbols))
        whole[mine] = out
        return whole

    def _slowly(self, contexts: np.ndarray, symbols: np.ndarray) -> np.ndarray:
        """From the highest order down, what a context leaves is multiplied until a gram is found."""
        out = np.zeros(len(symbols))
        left = np.arange(len(symbols))
        for width in range(len(self.levels), 0, -1):
            keys, p, heads, rests = self.levels[width - 1]
            context = contexts[left] & ((1 << BITS * (width - 1)) - 1)
            wanted = gram_keys(context, symbols[left], width)
            at, seen = _places(keys, wanted)
            out[left[seen]] += p[at[seen]]
            left, context = left[~seen], context[~seen]
            at, seen = _places(heads, context)
            out[left[seen]] += rests[at[seen]]
        out[left] -= np.log2(POINTS)
        return out


def _places(ordered: np.ndarray, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    if not len(ordered):
        return np.zeros(len(wanted), dtype=np.int64), np.zeros(len(wanted), dtype=bool)
    at = np.minimum(np.searchsorted(ordered, wanted), len(ordered) - 1)
    return at, ordered[at] == wanted


def _sent(levels: list[Level], p: ModelParameters) -> list:
    """Broadcast shards of the model, each of about ``shard_grams`` grams of three characters and more."""
    spark = levels[0].grams.sparkSession
    shards = max(1, -(-sum(x.grams.count() for x in levels[2:]) // p.shard_grams))
    log = lambda c: F.when(F.col(c) > 0, F.log2(c)).otherwise(F.lit(-1074.0)).cast("float").alias(c)
    out = []
    for number in range(shards):
        tables = []
        for width, level in enumerate(levels, 1):
            here = _shard_of(F.col("context"), shards) == number if width > 2 and shards > 1 else F.lit(True)
            grams = level.grams.filter(here).select("context", "symbol", log("p")).toArrow()
            heads = level.contexts.filter(here).select("context", log("rest")).toArrow()
            tables.append(tuple(c.to_numpy() for c in [*grams.columns, *heads.columns]))
        out.append((spark.sparkContext.broadcast(tables), number, shards))
    return out


def score(docs: DataFrame, levels: list[Level], columns: list[str], p: ModelParameters = PARAMETERS) -> DataFrame:
    """``columns`` of ``docs`` with chars and bits (mean per character, null for none); narrow. docs: a column text too."""
    shards = _sent(levels, p)
    rows = docs.select(*(column(c) for c in columns), column("text"), F.lit(0.0).alias("sum"))
    for n, (sent, number, many) in enumerate(shards, 1):
        last = n == len(shards)
        names = [*columns, "chars", "bits"] if last else [*columns, "text", "sum"]

        def run(batches: Iterator[pa.RecordBatch], sent=sent, number=number, many=many, last=last, names=names) -> Iterator[pa.RecordBatch]:
            shard = Shard(sent.value, number, many)
            for batch in batches:
                for part, texts in sliced(batch, "text"):
                    line = Line(texts, p.order)
                    total = np.zeros(len(line.symbols) + 1)
                    np.cumsum(-shard(line), out=total[1:])
                    bits = part.column(part.num_columns - 1).to_numpy() + total[line.firsts[1:]] - total[line.firsts[:-1]]
                    own = part.columns[: len(names) - 2]
                    if last:
                        chars = np.diff(line.firsts)
                        yield pa.RecordBatch.from_arrays([*own, pa.array(chars), pa.array(np.round(bits / np.maximum(chars, 1), 9), mask=chars == 0)], names=names)
                    else:
                        yield pa.RecordBatch.from_arrays([*own, part.column(len(own)), pa.array(bits)], names=names)

        rows = rows.transform(arrow_map, run, fields(docs, columns, ("chars", "long"), ("bits", "double")) if last else fields(docs, [*columns, "text"], ("sum", "double")))
    return rows


def limits(scored: DataFrame, p: ModelParameters) -> DataFrame:
    """(lang, limit) in bits, and a row of null language for the rest; scored: lang and bits of trusted texts."""
    held = scored.filter("bits is not null").select("lang", F.ceil(F.col("bits") * p.steps).alias("step"))
    table = settle(held.groupBy("lang", "step").agg(F.count("*").alias("m")))
    every = table.groupBy("step").agg(F.sum("m").alias("m")).withColumn("lang", F.lit(None).cast("string")).select("lang", "step", "m")
    both = table.filter("lang is not null").unionByName(every)
    up = Window.partitionBy("lang").orderBy("step").rowsBetween(Window.unboundedPreceding, 0)
    walked = both.select("lang", "step", F.sum("m").over(up).alias("upto"), F.sum("m").over(Window.partitionBy("lang")).alias("n"))
    reached = walked.filter((F.col("upto") >= p.quantile * F.col("n")) & ((F.col("n") >= p.least_trusted) | F.col("lang").isNull()))
    return reached.groupBy("lang").agg((F.min("step") / p.steps).alias("limit"))


def judge_perplexity(docs: DataFrame, labels: DataFrame, id_column: str = "doc_id", text_column: str = "text", language_column: str = "lang", trusted: str = "quality = 1", parameters: ModelParameters = PARAMETERS) -> DataFrame:
    """id, lang, n_chars, perplexity, limit (of perplexity) and kept, for each row of ``docs``."""
    p = parameters
    spark = docs.sparkSession
    rows = docs.select(column(id_column).alias("id"), column(language_column).alias("lang"), column(text_column).alias("text"))
    names = labels.filter(trusted).select(column(id_column).alias("id")).filter("id is not null").distinct()
    bitmap = spark.sparkContext.broadcast(_trusted_bits(names, p))

    def sift(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits = bitmap.value
        for batch in batches:
            low = batch.column(0).fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64) & (len(bits) * 8 - 1)
            yield batch.filter(pa.array((bits[low >> 3] >> (low & 7).astype(np.uint8)) & 1 == 1))

    # Most texts that nobody trusts are left out before the texts are shuffled to meet the labels.
    likely = rows.select("id", "text").transform(arrow_map, sift, fields(rows, ["id", "text"]))
    # The join is a merge join at every size: the labels grow with the documents.
    good = likely.join(names.hint("merge"), "id", "left_semi")
    scored = settle(score(rows, train(good, p), ["id", "lang"], p))
    known = limits(scored.join(names, "id", "left_semi"), p).collect()  # one row per language with trusted texts
    by_language = {r["lang"]: r["limit"] for r in known}
    rest = F.lit(by_language.pop(None, None)).cast("double")
    limit = rest
    if by_language:
        limit = F.coalesce(F.try_element_at(F.create_map(*(F.lit(x) for pair in sorted(by_language.items()) for x in pair)), F.coalesce("lang", F.lit(""))), rest)
    out = scored.withColumn("bound", F.round(F.pow(F.lit(2.0), limit), 6))
    perplexity = F.round(F.pow(F.lit(2.0), F.col("bits")), 6)
    kept = F.coalesce(F.col("bits") <= limit, F.col("bits").isNotNull())
    return out.select(F.col("id").alias(id_column), "lang", F.col("chars").alias("n_chars"), perplexity.alias("perplexity"), F.col("bound").alias("limit"), kept.alias("kept"))


def _trusted_bits(names: DataFrame, p: ModelParameters) -> np.ndarray:
    """A bit for the low bits of each trusted id: 2**filter_bits / 8 bytes, whatever their number."""
    spots = names.select((F.col("id").cast("long").bitwiseAND((1 << p.filter_bits) - 1) + 1).alias("v"))
    maps = spots.groupBy(F.bitmap_bucket_number("v").alias("b")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("v")).alias("m"))
    out = np.zeros((1 << p.filter_bits) // 8, dtype=np.uint8)
    for row in maps.collect():
        out[(row["b"] - 1) * 4096 : row["b"] * 4096] = np.frombuffer(bytes(row["m"]), dtype=np.uint8)
    return out
