"""Jaccard self-join of word-shingle sets over a token-group matrix.

Sets of equal content are one class. Classes that agree on a MinHash band and are
verified to link with the band's most central class form a root; the classes of a root are cut
into groups of bounded size. The matrix has a row for each token and group: a group's
token union, reduced to the tokens that prefix filtering needs. Two groups meet only when
they share as many such tokens as a link needs, by the sizes of their sets, and belong to
different roots. For each meeting pair the overlap of every query set with the other
group's whole token union is bounded, and only groups that pass are opened and compared
set by set. A link between any two sets of two groups joins their roots, whose sets are
connected already, so no pair inside a root is ever formed.

Sets are compared by 64-bit hashes of their shingles, and classes by a 64-bit hash of the
set: with 1e10 classes about three pairs of different sets may fall into one class.

Frequent tokens stand last in the order that prefixes are cut from. Their counts come from
a table of fixed size that sums the hashed tokens of all texts; any table gives whole
results, a coarse one only more candidates.

Edge cases: null or empty texts have an empty set and link with nothing. Texts shorter
than a shingle have one shingle, the whole sequence. Repeated rows get equal output rows.
A null id counts as no id: it never becomes a component's name unless all ids of the
component are null. Other columns, whatever their names, are not touched.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from math import ceil

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from .session import arrow_map, column, fresh, settle
from .textscan import BLANKS, Hasher, Words, chained, mix64, powers, sliced


@dataclass(frozen=True)
class JoinParameters:
    """``percent``: links need 100 * overlap >= percent * union."""

    width: int = 5
    percent: int = 75
    bands: int = 8
    rows_per_band: int = 2
    sketch_bits: int = 20
    sketch_chunks: int = 64
    #: Bits of the maps of classes and tokens for each entry, and their logarithm's bounds: at most 128 MB are sent.
    filter_spread: int = 8
    filter_bits: tuple[int, int] = (20, 30)
    group_tokens: int = 16384


PARAMETERS = JoinParameters()


# --- sets of a slice of texts ---------------------------------------------------------


class Shingler:
    """Sorted distinct shingle hashes of each row of a slice of texts."""

    def __init__(self, width: int):
        self.width, self.hasher = width, Hasher(fold_case=True)

    def __call__(self, texts) -> tuple[np.ndarray, np.ndarray]:
        """All rows' sets behind each other, and where each row's begins."""
        words = Words(texts, BLANKS)
        hashes = self.hasher(texts, words)
        windows = chained(hashes, self.width)
        sets, bounds = [], np.zeros(len(texts) + 1, dtype=np.int64)
        for i, (first, n) in enumerate(zip(words.firsts.tolist(), words.counts.tolist())):
            if n >= self.width:
                own = np.unique(windows[first : first + n - self.width + 1])
            elif n:
                own = chained(hashes[first : first + n], n)
            else:
                own = windows[:0]
            sets.append(own)
            bounds[i + 1] = bounds[i] + len(own)
        return (np.concatenate(sets) if sets else windows[:0]), bounds


def _reduce(ufunc, values: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """ufunc over each run; runs must not be empty."""
    return ufunc.reduceat(values, bounds[:-1]) if len(bounds) > 1 else values[:0]


def signatures(sets: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """Order-free hash of each (non-empty) set."""
    scrambled = mix64(sets ^ np.uint64(0x5851F42D4C957F2D))
    return mix64(_reduce(np.add, scrambled, bounds) + np.diff(bounds).astype(np.uint64)).view(np.int64)


def band_keys(sets: np.ndarray, bounds: np.ndarray, p: JoinParameters) -> np.ndarray:
    """Hash of each band's minima, one row per set."""
    multipliers = powers(p.bands * p.rows_per_band + 1)[0][1:] | np.uint64(1)
    out = np.empty((len(bounds) - 1, p.bands), dtype=np.int64)
    for b in range(p.bands):
        key = np.full(len(bounds) - 1, b + 1, dtype=np.uint64)
        for r in range(p.rows_per_band):
            values = sets * multipliers[b * p.rows_per_band + r]
            values ^= values >> np.uint64(32)
            key = mix64(key + _reduce(np.minimum, values * multipliers[r], bounds))
        out[:, b] = key.view(np.int64)
    return out


def _base(batches: Iterator[pa.RecordBatch], p: JoinParameters) -> Iterator[pa.RecordBatch]:
    shingles = Shingler(p.width)
    counts = np.zeros(1 << p.sketch_bits, dtype=np.int64)
    names = ["id", "n", "sig", "bands", "chunk", "sketch"]
    any_tokens = False
    for batch in batches:
        for rows, texts in sliced(batch, "text"):
            sets, bounds = shingles(texts)
            sizes = np.diff(bounds)
            full = sizes > 0
            any_tokens |= bool(len(sets))
            counts += np.bincount((sets & np.uint64(len(counts) - 1)).astype(np.int64), minlength=len(counts))
            tight = np.concatenate([[0], bounds[1:][full]])
            sig = np.zeros(len(sizes), dtype=np.int64)
            bands = np.zeros((0, p.bands), dtype=np.int64)
            if full.any():
                sig[full] = signatures(sets, tight)
                bands = band_keys(sets, tight, p)
            lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(full * p.bands)]).astype(np.int32)), pa.array(bands.ravel()))
            n = len(sizes)
            yield pa.RecordBatch.from_arrays([rows.column(0), pa.array(sizes), pa.array(sig, mask=~full), lists, pa.nulls(n, pa.int32()), pa.nulls(n, pa.binary())], names=names)
    if any_tokens:
        parts = np.split(counts, p.sketch_chunks)
        k = len(parts)
        yield pa.RecordBatch.from_arrays(
            [pa.nulls(k, pa.int64()), pa.nulls(k, pa.int64()), pa.nulls(k, pa.int64()), pa.nulls(k, pa.list_(pa.int64())), pa.array(range(k), pa.int32()), pa.array([zlib.compress(x.tobytes(), 1) for x in parts], pa.binary())],
            names=names,
        )


def _summed(frame: pd.DataFrame) -> pd.DataFrame:
    total = sum(np.frombuffer(zlib.decompress(x), dtype=np.int64) for x in frame["sketch"])
    return pd.DataFrame({"chunk": [frame["chunk"].iloc[0]], "salt": [0], "sketch": [zlib.compress(total.tobytes(), 1)]})


def frequency_classes(sketches: DataFrame, p: JoinParameters) -> np.ndarray:
    """Binary order of magnitude of each counter: one byte each, 2**sketch_bits bytes in all on the driver.

    Sums go up in two levels, so no task gathers more than a thousandth of the tasks' tables.
    """
    schema = "chunk int, salt int, sketch binary"
    partly = sketches.withColumn("salt", F.pmod(F.spark_partition_id(), F.lit(1024)))
    for keys in (["chunk", "salt"], ["chunk"]):
        partly = partly.select("chunk", "salt", "sketch").groupBy(*keys).applyInPandas(_summed, schema)
    width = (1 << p.sketch_bits) // p.sketch_chunks
    classes = np.zeros(1 << p.sketch_bits, dtype=np.uint8)
    for row in partly.collect():  # sketch_chunks rows
        counts = np.frombuffer(zlib.decompress(row["sketch"]), dtype=np.int64)
        classes[row["chunk"] * width : (row["chunk"] + 1) * width] = np.ceil(np.log2(counts + 1)).astype(np.uint8)
    return classes


# --- which texts and tokens a later pass needs ----------------------------------------


def bit_filter(df: DataFrame, value: F.Column, p: JoinParameters) -> np.ndarray:
    """Bytes of a bit map of the low bits of a long, as many as the rows need, within bounds; a full map admits more, and loses nothing."""
    least, most = p.filter_bits
    bits = min(max((df.count() * p.filter_spread).bit_length(), least), most)
    low = F.bitwise_and(value, F.lit((1 << bits) - 1)) if hasattr(F, "bitwise_and") else value.bitwiseAND(F.lit((1 << bits) - 1))
    spots = df.select((low + 1).alias("v"))
    maps = spots.groupBy(F.bitmap_bucket_number("v").alias("b")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("v")).alias("m"))
    out = np.zeros((1 << bits) // 8, dtype=np.uint8)
    for row in maps.collect():
        start = (row["b"] - 1) * 4096
        piece = np.frombuffer(bytes(row["m"]), dtype=np.uint8)[: len(out) - start]
        out[start : start + len(piece)] = piece
    return out


def hits(bitmap: np.ndarray, values: np.ndarray) -> np.ndarray:
    low = (values.view(np.uint64) & np.uint64(len(bitmap) * 8 - 1)).astype(np.int64)
    return (bitmap[low >> 3] >> (low & 7).astype(np.uint8)) & 1 == 1


def _member(first: F.Column, sig: F.Column) -> F.Column:
    return F.coalesce(first, F.lit(0)).bitwiseXOR(sig)


class _Pass:
    """A pass over the texts that rebuilds the sets of the rows that a bit map admits."""

    def __init__(self, p: JoinParameters, rows_filter):
        self.p, self.rows_filter = p, rows_filter

    def sets(self, batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        shingles, seen = Shingler(self.p.width), set()
        for batch in batches:
            for rows, texts in sliced(batch, "text"):
                sets, bounds = shingles(texts)
                full = np.flatnonzero(np.diff(bounds))
                if not len(full):
                    continue
                sig = signatures(sets, np.concatenate([[0], bounds[1:][full]]))
                ids = rows.column(0).fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)[full]
                good = np.flatnonzero(hits(self.rows_filter.value, ids ^ sig))
                new = []
                for g in good.tolist():
                    if (s := int(sig[g])) not in seen:
                        seen.add(s)
                        new.append(g)
                if new:
                    yield sig[new], sets, np.stack([bounds[full[new]], bounds[full[new] + 1]], axis=1)


def set_rows(docs: DataFrame, wanted: DataFrame, order, p: JoinParameters) -> DataFrame:
    """(sig, tokens, common) of the classes in ``wanted`` (first, sig), and of a few others that share a bit with them.

    ``common`` is how common a set's tokens are in the mean, by the logarithms of their counts.
    """
    work = _Pass(p, docs.sparkSession.sparkContext.broadcast(bit_filter(wanted, _member(F.col("first"), F.col("sig")), p)))

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for sig, sets, spans in work.sets(batches):
            ranks = order.value[(sets & np.uint64(len(order.value) - 1)).astype(np.int64)]
            common = [int(1024 * ranks[a:b].mean()) for a, b in spans]
            yield pa.RecordBatch.from_arrays([pa.array(sig), pa.array([sets[a:b].tobytes() for a, b in spans], pa.binary()), pa.array(common, pa.int32())], names=["sig", "tokens", "common"])

    return docs.transform(arrow_map, rows, "sig long, tokens binary, common int")


def prefix_rows(docs: DataFrame, classes: DataFrame, order, p: JoinParameters, tokens_filter=None) -> DataFrame:
    """(sig, tokens, places): the first tokens of each class in the common order, rare ones first, and each one's place in it.

    Sets that reach the threshold share a token within both prefixes, for any order.
    """
    work = _Pass(p, docs.sparkSession.sparkContext.broadcast(bit_filter(classes, _member(F.col("first"), F.col("sig")), p)))

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ranks = order.value
        for sig, sets, spans in work.sets(batches):
            kept, places, bounds = [], [], [0]
            for a, b in spans.tolist():
                own = sets[a:b]
                n = b - a
                rank = (ranks[(own & np.uint64(len(ranks) - 1)).astype(np.int64)].astype(np.uint64) << np.uint64(56)) | (mix64(own) >> np.uint64(8))
                first = own[np.argsort(rank)[: n - ceil(p.percent * n / 100) + 1]].view(np.int64)
                place = np.arange(len(first), dtype=np.int32)
                if tokens_filter is not None:
                    place = np.flatnonzero(hits(tokens_filter.value, first)).astype(np.int32)
                    first = first[place]
                kept.append(first)
                places.append(place)
                bounds.append(bounds[-1] + len(first))
            ends = pa.array(bounds, pa.int32())
            lists = (pa.ListArray.from_arrays(ends, pa.array(np.concatenate(x))) for x in (kept, places))
            yield pa.RecordBatch.from_arrays([pa.array(sig), *lists], names=["sig", "tokens", "places"])

    return docs.transform(arrow_map, rows, "sig long, tokens array<long>, places array<int>")


# --- comparison ------------------------------------------------------------------------


def _linked(a: np.ndarray, b: np.ndarray, percent: int) -> bool:
    small, large = sorted((len(a), len(b)))
    if 100 * small < percent * large:
        return False
    both = len(np.intersect1d(a, b, assume_unique=True))
    return 100 * both >= percent * (len(a) + len(b) - both)


def any_link(left: list[np.ndarray], right: list[np.ndarray], percent: int) -> bool:
    """True if some set of the left group links with some set of the right one.

    The right group's token union bounds what a left set can share with any of its sets; only on reaching
    the threshold against its own size is the group opened.
    """
    union = right[0] if len(right) == 1 else np.unique(np.concatenate(right))
    for query in left:
        if 100 * np.isin(query, union, assume_unique=True).sum() >= percent * len(query) and any(_linked(query, other, percent) for other in right):
            return True
    return False


def _unpack(blobs) -> list[np.ndarray]:
    return [np.frombuffer(x, dtype=np.uint64) for x in blobs]


def _compare(percent: int):
    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a, b, left, right = (batch.column(i) for i in range(4))
            good = [any_link(_unpack(x.as_py()), _unpack(y.as_py()), percent) for x, y in zip(left, right)]
            keep = pa.array(good, pa.bool_())
            yield pa.RecordBatch.from_arrays([a.filter(keep), b.filter(keep)], names=["a", "b"])

    return compare


def components(edges: DataFrame) -> DataFrame:
    """(node, label): least node of each connected component of the edges (a, b).

    Labels pass to neighbours and then jump along labels, so the rounds grow with the logarithm of the
    longest chain; each round is settled.
    """
    both = settle(edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct())
    labels = settle(both.groupBy(F.col("a").alias("node")).agg(F.least(F.col("a"), F.min("b")).alias("label")))
    while True:
        near = both.join(labels.select(F.col("node").alias("b"), "label"), "b").groupBy(F.col("a").alias("node")).agg(F.min("label").alias("near"))
        stepped = labels.join(near, "node").select("node", "label", F.least("label", "near").alias("new"))
        jumped = stepped.join(labels.select(F.col("node").alias("new"), F.col("label").alias("over")), "new").select("node", "label", F.least("new", "over").alias("new"))
        jumped = settle(jumped)
        if not jumped.filter("label <> new").head(1):
            return labels
        labels = jumped.select("node", F.col("new").alias("label"))


def _jump(parents: DataFrame) -> DataFrame:
    """(sig, root) from (sig, parent), where no path of parents comes back: follow parents to the end."""
    now = settle(parents.select("sig", F.col("parent").alias("root")))
    while True:
        up = now.select(F.col("sig").alias("root"), F.col("root").alias("over"))
        after = settle(now.join(up, "root", "left").select("sig", F.coalesce("over", "root").alias("root"), F.col("over").isNotNull().alias("moved")))
        now = after.select("sig", "root")
        if not after.filter("moved").head(1):
            return now


def needed_tokens(percent: int, left: tuple[str, str], right: tuple[str, str]) -> F.Column:
    """Prefix tokens that two groups, their sets' sizes given as ranges, must share at least, if some of their sets link.

    Linked sets of a and b tokens share ceil(percent * (a + b) / (100 + percent)). In the common order, those up to the
    nearer end of the two prefixes lie in both prefixes; beyond it, the set whose prefix ends there has
    ceil(percent * size / 100) - 1 tokens left. Between two groups of one size each, this is the need. Over ranges the
    ceilings make it rise and fall, so the real numbers under them stand in for it: the need exceeds their difference,
    which is concave and thus least at a corner of the size ranges. It is 1 where a corner is too uneven to link.
    """
    exact, bounds = [], []
    for a in left:
        for b in right:
            low, high = F.least(a, b), F.greatest(a, b)
            linked, beyond = percent * (F.col(a) + F.col(b)) / (100 + percent), percent * high / 100
            uneven = 100 * low < percent * high
            exact.append(F.when(uneven, F.lit(1)).otherwise(F.ceil(linked - 1e-6) - F.ceil(beyond - 1e-6) + 1))
            bounds.append(F.when(uneven, F.lit(1)).otherwise(F.floor(linked - beyond - 1e-6) + 1))
    single = (F.col(left[0]) == F.col(left[1])) & (F.col(right[0]) == F.col(right[1]))
    return F.greatest(F.lit(1), F.when(single, exact[0]).otherwise(F.least(*bounds)))


def room(percent: int, size: F.Column, place: F.Column) -> F.Column:
    """What percent times the size of a linked set may reach, if the first token in common has this place (from 0) in a set of this size.

    All that the two share stands from there on: size - place >= percent * (size + other) / (100 + percent).
    """
    return 100 * size - (100 + percent) * place


# --- the join ---------------------------------------------------------------------------


def similar_components(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", parameters: JoinParameters = PARAMETERS) -> DataFrame:
    """One row per row of ``docs``: id, n_shingles, component_id, and sig, the class of equal sets (null when empty)."""
    p = parameters
    spark = docs.sparkSession
    texts = docs.select(column(id_column).cast("long").alias("id"), column(text_column).alias("text"))
    base = settle(texts.transform(arrow_map, lambda batches: _base(batches, p), "id long, n long, sig long, bands array<long>, chunk int, sketch binary"))
    rows = base.filter("chunk is null")
    order = spark.sparkContext.broadcast(frequency_classes(base.filter("chunk is not null"), p))
    classes = settle(rows.filter("sig is not null").groupBy("sig").agg(F.min("id").alias("first"), F.min("n").alias("n"), F.first("bands").alias("bands")))

    # Roots: each class turns to one class that it shares a band with, if the two link. Only a band's most central class
    # is turned to, one whose bands are the most crowded, so that no path comes back; of several, the one with the most
    # bands in common. Crowds count by their logarithms: a class with several crowded bands is in the middle of near
    # copies, while one or two may be those of a passage that unlike texts share.
    # Of equally crowded ones, that with the most common shingles has the fewest changes of its own.
    keyed = classes.select("sig", F.explode("bands").alias("key"))
    crowds = keyed.groupBy("key").agg(F.count("*").alias("m")).filter("m > 1")
    crowded = keyed.join(crowds, "key").withColumn("score", F.sum(F.floor(16 * F.log2("m"))).over(Window.partitionBy("sig")))
    crowded = settle(crowded.select("sig", "key", "score"))
    wanted = settle(classes.select("sig", "first").join(crowded.select("sig"), "sig", "left_semi"))
    sets = settle(set_rows(texts, wanted, order, p).dropDuplicates(["sig"]))
    crowded = crowded.join(sets.select("sig", "common"), "sig")
    rank = F.struct("score", "common", (-F.col("sig")).alias("low"))
    pivots = crowded.groupBy("key").agg(F.max_by("sig", rank).alias("pivot"), F.max(rank).alias("rank"))
    alike = crowded.select("sig", "key").join(pivots, "key").filter("pivot <> sig").groupBy("sig", "pivot").agg(F.struct(F.count("*").alias("bands"), F.first("rank").alias("rank")).alias("alike"))
    choice = settle(alike.groupBy("sig").agg(F.max_by("pivot", "alike").alias("pivot")))
    sets = sets.drop("common")
    met = choice.join(sets, "sig").withColumnRenamed("tokens", "left").join(sets.withColumnsRenamed({"sig": "pivot", "tokens": "right"}), "pivot")
    tied = met.select(F.col("sig").alias("a"), F.col("pivot").alias("b"), F.array("left"), F.array("right")).transform(arrow_map, _compare(p.percent), "a long, b long")
    roots = _jump(tied.select(F.col("a").alias("sig"), F.col("b").alias("parent")).distinct())

    # Groups: the classes of a root, cut to a bounded number of tokens.
    rooted = classes.drop("bands").join(roots, "sig", "left").withColumn("root", F.coalesce("root", "sig"))
    # Few roots are large, and only those are looked up.
    large = settle(rooted.groupBy("root").agg(F.ceil(F.sum("n") / p.group_tokens).alias("cuts")).filter("cuts > 1"))
    cut = F.pmod(F.xxhash64("sig"), F.col("cuts"))
    grouped = settle(rooted.join(large, "root", "left").select("sig", "first", "n", "root", F.when(F.col("cuts").isNull(), F.col("root")).otherwise(F.xxhash64("root", cut)).alias("grp")))

    # Token-group matrix over the prefix tokens that more than one class has.
    firsts = prefix_rows(texts, grouped, order, p)
    shared = settle(firsts.select(F.explode("tokens").alias("token")).groupBy("token").agg(F.count("*").alias("m")).filter("m > 1").select("token"))
    shared_filter = spark.sparkContext.broadcast(bit_filter(shared, F.col("token"), p))
    entries = prefix_rows(texts, grouped, order, p, shared_filter).filter(F.size("tokens") > 0)
    spots = F.posexplode(F.arrays_zip("tokens", "places")).alias("at", "spot")
    entries = entries.join(grouped, "sig").select("grp", "root", "n", F.size("tokens").alias("s"), spots)
    entries = entries.select("grp", "root", "n", F.col("spot.tokens").alias("token"), (F.col("s") - F.col("at")).alias("rest"), room(p.percent, F.col("n"), F.col("spot.places")).alias("room"))
    matrix = entries.groupBy("token", "grp", "root").agg(F.max("rest").alias("rest"), F.max("room").alias("room"), F.min("n").alias("least"), F.max("n").alias("most"))
    by_token = Window.partitionBy("token")
    matrix = settle(matrix.withColumns({"lo": F.min("root").over(by_token), "hi": F.max("root").over(by_token)}).filter("lo <> hi").drop("lo", "hi"))

    # Candidate pairs of groups: at the first token that two linked sets share, each has as many prefix tokens left as
    # they must share; and groups share that many. rest counts the tokens that more than one class has, from this one on.
    # There too, each has room for the other: near copies of one text, each too much changed to link with the others,
    # share the text's tokens, but only behind so many of their own that no link is possible.
    x, y = matrix.alias("x"), matrix.alias("y")
    sizes = (100 * F.col("x.most") >= p.percent * F.col("y.least")) & (100 * F.col("y.most") >= p.percent * F.col("x.least"))
    enough = F.least("x.rest", "y.rest") >= needed_tokens(p.percent, ("x.least", "x.most"), ("y.least", "y.most"))
    roomy = (F.col("x.room") >= p.percent * F.col("y.least")) & (F.col("y.room") >= p.percent * F.col("x.least"))
    met = x.join(y, (F.col("x.token") == F.col("y.token")) & (F.col("x.root") < F.col("y.root")) & sizes & roomy & enough)
    met = settle(met.select(F.col("x.grp").alias("ga"), F.col("y.grp").alias("gb"), F.col("x.root").alias("ra"), F.col("y.root").alias("rb")).distinct())
    held = matrix.groupBy("grp").agg(F.collect_list("token").alias("tokens"), F.min("least").alias("least"), F.max("most").alias("most"))
    both = met.join(held.select(F.col("grp").alias("ga"), *(F.col(c).alias(f"a_{c}") for c in ("tokens", "least", "most"))), "ga")
    both = both.join(held.select(F.col("grp").alias("gb"), *(F.col(c).alias(f"b_{c}") for c in ("tokens", "least", "most"))), "gb")
    common = F.size(F.array_intersect("a_tokens", "b_tokens"))
    pairs = settle(both.filter(common >= needed_tokens(p.percent, ("a_least", "a_most"), ("b_least", "b_most"))).select("ga", "gb", "ra", "rb"))

    # Open the groups that meet.
    if pairs.head(1):
        used = pairs.select(F.col("ga").alias("grp")).union(pairs.select("gb")).distinct()
        wanted = settle(grouped.join(used, "grp").select("sig", "first", "grp"))
        members = set_rows(texts, wanted, order, p).drop("common").join(wanted.select("sig", "grp"), "sig").groupBy("grp").agg(F.collect_list("tokens").alias("sets"))
        met = pairs.join(members.withColumnsRenamed({"grp": "ga", "sets": "left"}), "ga").join(members.withColumnsRenamed({"grp": "gb", "sets": "right"}), "gb")
        edges = settle(met.select("ra", "rb", "left", "right").transform(arrow_map, _compare(p.percent), "a long, b long").distinct())
        if edges.head(1):
            merged = components(edges)
            grouped = grouped.join(merged.select(F.col("node").alias("root"), "label"), "root", "left").withColumn("root", F.coalesce("label", "root")).drop("label")

    # Settled, so that the join is one of two exchanges, whose large partitions Spark can split.
    names = settle(grouped.groupBy("root").agg(F.min("first").alias("component")))
    named = grouped.select("sig", "root").join(names, "root").select("sig", "component")
    out = rows.select("id", "n", "sig").join(named, "sig", "left")
    return out.select(F.col("id").alias(id_column), F.col("n").alias("n_shingles"), F.coalesce("component", "id").alias("component_id"), "sig")


def _signed(docs: DataFrame, text_column: str, name: str, p: JoinParameters) -> DataFrame:
    """``docs`` with the class of each row's set as a further column."""
    place, names = docs.columns.index(text_column), [*docs.columns, name]

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingles = Shingler(p.width)
        for batch in batches:
            plain = pa.RecordBatch.from_arrays(batch.columns, names=[f"c{i}" for i in range(batch.num_columns)])
            for rows, texts in sliced(plain, f"c{place}"):
                sets, bounds = shingles(texts)
                full = np.diff(bounds) > 0
                sig = np.zeros(len(full), dtype=np.int64)
                if full.any():
                    sig[full] = signatures(sets, np.concatenate([[0], bounds[1:][full]]))
                yield pa.RecordBatch.from_arrays([*rows.columns, pa.array(sig, mask=~full)], names=names)

    return docs.transform(arrow_map, sign, StructType([*docs.schema.fields, StructField(name, LongType())]))


def keep_one_of_each(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", parameters: JoinParameters = PARAMETERS) -> DataFrame:
    """The rows of ``docs`` whose id names their component, all columns kept; of rows with equal id and set one stays."""
    marks = similar_components(docs, id_column, text_column, parameters)
    own, stay_id, stay_sig, seen_id, sig = fresh(docs.columns, "own_id", "stay_id", "stay_sig", "seen_id", "sig")
    mark = column(id_column)
    stay = settle(marks.filter(mark.eqNullSafe(F.col("component_id"))).select(mark.alias(stay_id), F.col("sig").alias(stay_sig)))
    counts = marks.groupBy(mark.alias(seen_id)).agg(F.count("*").alias("rows"))
    again = settle(counts.filter((F.col("rows") > 1) | F.col(seen_id).isNull()).select(seen_id))
    keyed = docs.withColumn(own, mark.cast("long"))
    if not again.head(1):
        return keyed.join(stay.select(stay_id), F.col(own) == F.col(stay_id), "left_semi").drop(own)
    once = keyed.join(stay.join(again, F.col(stay_id).eqNullSafe(F.col(seen_id)), "left_anti").select(stay_id), F.col(own) == F.col(stay_id), "left_semi")
    rows = _signed(keyed.join(again, F.col(own).eqNullSafe(F.col(seen_id)), "left_semi"), text_column, sig, parameters)
    rows = rows.join(stay, F.col(own).eqNullSafe(F.col(stay_id)) & F.col(sig).eqNullSafe(F.col(stay_sig)), "left_semi")
    return once.unionByName(rows.dropDuplicates([own, sig]).drop(sig)).drop(own)
