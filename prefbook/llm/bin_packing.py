"""Packing of token sequences by minimum bin slack.

Only lengths matter for how full a bin gets, so the bins are planned from the counts of
the lengths 1 to ``capacity``, a table of bounded size. For each bin a bitset of reachable
sums over the available lengths finds the fullest feasible combination; the combination is
removed as often as the counts allow, which uses up one of its lengths, so the plan has no
more patterns than lengths. The bin starts from the longest piece left, which has to be
put somewhere. Equally full combinations leave different rests, so a few orders of search are
tried until a plan needs no more bins than the tokens do. Pieces take their places by their rank among pieces of equal length; ranks
come from counts of hashed buckets and a rank within each bucket, so that one frequent
length, or one source, doesn't meet in one task.

Tokens are those of a byte-level BPE vocabulary, followed by an end id. Texts of common
letters are encoded by the faster of two libraries that share the vocabulary; the others,
and very long runs without a break, by the library of the vocabulary's file.

Edge cases: a null or empty text has the end id alone. Repeated rows are pieces of their
own. An empty table gives an empty result. Only texts longer than a bin are cut; their
first piece may be shorter than a bin, all others fill one.
"""

from __future__ import annotations

import os
import re
import zlib
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .session import arrow_map, column, fields, process_cache, settle


def public_vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


@dataclass(frozen=True)
class PackingParameters:
    capacity: int = 2048
    end_id: int = 0
    vocabulary: str = "byte_bpe_50k.json"
    ranks: str = "byte_bpe_50k.tiktoken"
    #: Rank buckets; a length that a third of 1e11 pieces have leaves some 1e7 rows a bucket, which a sort can spill.
    buckets: int = 4096


PARAMETERS = PackingParameters()

#: Latin letters, ASCII and general punctuation: both libraries split these alike. No run of 4096 characters without a change of class.
_PLAIN = re.compile(r"[\x00-ɏ‐-‧€]*")
_LONG_RUN = re.compile(r"\S{4096}|\s{4096}")


class Encoder:
    """Token ids of texts, as the vocabulary's own library gives them without special tokens added."""

    def __init__(self, p: PackingParameters):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        import base64

        import public_tokenizers
        import tiktoken
        from tokenizers import Tokenizer

        self.slow = Tokenizer.from_file(public_vocabulary(p.vocabulary))
        with open(public_vocabulary(p.ranks), "rb") as lines:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
        special = {t.content: i for i, t in self.slow.get_added_tokens_decoder().items()}
        self.marks = tuple(special)
        self.fast = tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens=special)

    def __call__(self, text: str) -> np.ndarray:
        if _PLAIN.fullmatch(text) and not _LONG_RUN.search(text) and not any(m in text for m in self.marks):
            return np.asarray(self.fast.encode_ordinary(text), dtype="<u4")
        return np.asarray(self.slow.encode(text, add_special_tokens=False).ids, dtype="<u4")


def token_pieces(docs: DataFrame, id_column: str, text_column: str, p: PackingParameters) -> DataFrame:
    """(id, piece, start, length, ids_crc32); narrow. The ids themselves don't leave the task."""
    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = process_cache(("encoder", p), lambda: Encoder(p))
        end = np.array([p.end_id], dtype="<u4")
        for batch in batches:
            rows, piece, start, length, crc = [], [], [], [], []
            for row, text in enumerate(batch.column(1)):
                ids = np.concatenate([encode(text.as_py() or ""), end])
                first = (len(ids) - 1) % p.capacity + 1
                cuts = [0, *range(first, len(ids) + 1, p.capacity)]
                for k, (a, b) in enumerate(zip(cuts, cuts[1:])):
                    rows.append(row)
                    piece.append(k)
                    start.append(a)
                    length.append(b - a)
                    crc.append(zlib.crc32(ids[a:b].tobytes()))
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(rows, pa.int64())), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64())], names=[id_column, "piece", "start", "length", "ids_crc32"])

    schema = fields(docs, [id_column], ("piece", "int"), ("start", "long"), ("length", "long"), ("ids_crc32", "long"))
    return docs.select(column(id_column), column(text_column)).transform(arrow_map, cut, schema)


def ordered(lengths: Iterable[int], order: int) -> list[int]:
    """Long ones first, short ones first, or mixed by a hash: which of equally full combinations is found depends on it."""
    if order < 2:
        return sorted(lengths, reverse=order == 0)
    return sorted(lengths, key=lambda n: (n * (2 * order + 1) * 2654435761 & 0xFFFFFFFF, n))


def fullest(room: int, counts: dict[int, int], order: int = 0) -> list[int]:
    """Lengths, with repeats, of a combination of available pieces whose sum is the largest up to ``room``.

    Bit s of the set is on if some combination sums to s.
    """
    mask = (1 << (room + 1)) - 1
    reach = [1]
    used: list[tuple[int, int]] = []
    for length in ordered((n for n in counts if n <= room), order):
        left, times = min(counts[length], room // length), 1
        while left:  # 1, 2, 4, ... and the rest: every number of copies is a sum of some of these
            take = min(times, left)
            step = (reach[-1] | reach[-1] << (take * length)) & mask
            if step != reach[-1]:
                used.append((length, take))
                reach.append(step)
            left -= take
            times *= 2
        if reach[-1] >> room & 1:
            break
    total = reach[-1].bit_length() - 1
    chosen: list[int] = []
    for (length, take), before in zip(reversed(used), reversed(reach[:-1])):
        if not before >> total & 1:
            chosen += [length] * take
            total -= length * take
    return chosen


def plan_bins(counts: dict[int, int], capacity: int, orders: int = 8) -> tuple[np.ndarray, int]:
    """The plan with the fewest bins of a few orders of search; the first that no plan can beat ends it."""
    least = -(-sum(n * c for n, c in counts.items()) // capacity)
    best: tuple[np.ndarray, int] | None = None
    for order in range(orders):
        plan = _planned(counts, capacity, order)
        if best is None or plan[1] < best[1]:
            best = plan
        if best[1] <= least:
            break
    return best if best is not None else _planned(counts, capacity, 0)


def _planned(counts: dict[int, int], capacity: int, order: int) -> tuple[np.ndarray, int]:
    """Rows (length, from rank, to rank, copies a bin, first bin, place of the first copy) and the number of bins."""
    left = {n: c for n, c in counts.items() if c > 0}
    ranks = dict.fromkeys(left, 0)
    rows, bins = [], 0
    while left:
        longest = max(left)
        left[longest] -= 1
        content = [longest, *fullest(capacity - longest, {n: c for n, c in left.items() if c}, order)]
        left[longest] += 1
        copies = {n: content.count(n) for n in content}
        times = min(left[n] // k for n, k in copies.items())
        place = 0
        for n, k in copies.items():
            rows.append((n, ranks[n], ranks[n] + times * k, k, bins, place))
            ranks[n] += times * k
            place += n * k
            left[n] -= times * k
            if not left[n]:
                del left[n]
        bins += times
    return np.array(rows, dtype=np.int64).reshape(-1, 6), bins


def ranked(df: DataFrame, group: str, order: list[str], buckets: int, name: str) -> DataFrame:
    """``df`` with a gapless rank from 0 within each value of ``group``: bucket offsets plus ranks within the buckets.

    ``df`` has been settled, so that a row's partition is the same in each reading; rows that are equal in all of
    ``order`` are dealt by it and don't meet in one bucket.
    """
    keys = [column(c) for c in order]
    spread = df.withColumn("_bucket", F.pmod(F.xxhash64(*keys, F.spark_partition_id()), F.lit(buckets)).cast("int"))
    sizes = spread.groupBy(group, "_bucket").agg(F.count("*").alias("_n"))
    before = Window.partitionBy(group).orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)
    starts = sizes.select(F.col(group).alias("_g"), F.col("_bucket").alias("_b"), F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_from"))
    within = Window.partitionBy(group, "_bucket").orderBy(*keys)
    placed = spread.withColumn("_at", F.row_number().over(within) - 1)
    joined = placed.join(starts, (F.col(group) == F.col("_g")) & (F.col("_bucket") == F.col("_b")))
    return joined.withColumn(name, F.col("_from") + F.col("_at")).drop("_bucket", "_at", "_g", "_b", "_from")


def pack_pieces(pieces: DataFrame, order: list[str], p: PackingParameters = PARAMETERS) -> DataFrame:
    """``pieces`` (with a column length of 1 to capacity) with sequence_id and offset."""
    pieces = settle(pieces)
    counts = {r["length"]: r["m"] for r in pieces.groupBy("length").agg(F.count("*").alias("m")).collect()}  # capacity rows at most
    plan, _ = plan_bins(counts, p.capacity)
    order_of = np.lexsort((plan[:, 1], plan[:, 0]))
    plan = plan[order_of]
    sent = pieces.sparkSession.sparkContext.broadcast(plan)  # at most capacity patterns of bounded size
    schema = fields(pieces, pieces.columns, ("sequence_id", "long"), ("offset", "long"))

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = sent.value
        key = table[:, 0] << 44
        starts = key + table[:, 1]
        for batch in batches:
            length = batch.column(batch.schema.get_field_index("length")).to_numpy()
            rank = batch.column(batch.schema.get_field_index("rank")).to_numpy()
            _, _, _, copies, first, base = table[np.searchsorted(starts, (length << 44) + rank, side="right") - 1].T
            at = rank - table[np.searchsorted(starts, (length << 44) + rank, side="right") - 1, 1]
            kept = [batch.column(i) for i, n in enumerate(batch.schema.names) if n != "rank"]
            yield pa.RecordBatch.from_arrays([*kept, pa.array(first + at // copies), pa.array(base + at % copies * length)], names=[*(n for n in batch.schema.names if n != "rank"), "sequence_id", "offset"])

    return ranked(pieces, "length", order, p.buckets, "rank").transform(arrow_map, place, schema)


def pack_documents(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", parameters: PackingParameters = PARAMETERS) -> DataFrame:
    """One row per piece: id, piece, start, length, ids_crc32, sequence_id, offset."""
    pieces = token_pieces(docs, id_column, text_column, parameters)
    return pack_pieces(pieces, [id_column, "piece", "ids_crc32"], parameters)
