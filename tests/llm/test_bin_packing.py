"""Minimum bin slack: combinations against exhaustive search, whole packings, and token ids."""

import zlib
from itertools import combinations

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from prefbook.llm.bin_packing import PARAMETERS, Encoder, PackingParameters, fullest, pack_documents, plan_bins


@settings(max_examples=80, deadline=None)
@given(st.lists(st.integers(1, 20), max_size=9), st.integers(0, 30))
def test_fullest_is_the_best_sum(lengths, room):
    counts = {n: lengths.count(n) for n in lengths}
    chosen = fullest(room, counts)
    sums = {sum(c) for k in range(len(lengths) + 1) for c in combinations(lengths, k)}
    assert sum(chosen) == max(s for s in sums if s <= room)
    assert all(chosen.count(n) <= counts[n] for n in chosen)


@settings(max_examples=40, deadline=None)
@given(st.dictionaries(st.integers(1, 50), st.integers(1, 40), max_size=12))
def test_plan_places_every_piece_once(counts):
    rows, bins = plan_bins(counts, 50)
    fill = np.zeros(bins, dtype=int)
    for n in counts:
        own = sorted((a, b) for m, a, b, *_ in rows.tolist() if m == n)
        assert [a for a, _ in own] == [0, *(b for _, b in own[:-1])] and own[-1][1] == counts[n]
    for n, a, b, copies, first, _ in rows.tolist():
        for at in range(b - a):
            fill[first + at // copies] += n
    assert (fill <= 50).all() and (fill > 0).all() and fill.sum() == sum(n * c for n, c in counts.items())


def test_many_pieces_need_few_patterns():
    counts = {n: 10**9 + n for n in range(1, 2049)}
    rows, bins = plan_bins(counts, 2048)
    total = sum(n * c for n, c in counts.items())
    assert bins <= total // 2048 * 1.001 + 2 and len(rows) < 200_000


TEXTS = ["", None, "word " * 5000, "a<|endoftext|>b", "日本語テキスト", "x" * 10000, "é\n\n  tab\t", "plain text", "plain text", " " * 9000, "don't 123 ​ “quotes”"]


@pytest.fixture(scope="module")
def packed(spark):
    docs = spark.createDataFrame([(i, t, "k") for i, t in enumerate(TEXTS)] + [(None, "null id", "k"), (7, "plain text", "k")], "doc_id long, text string, length string")
    return pack_documents(docs).toPandas()


def test_pieces(packed):
    slow = Encoder(PARAMETERS).slow
    for i, t in enumerate(TEXTS):
        if i == 7:
            continue
        ids = np.array([*slow.encode(t or "", add_special_tokens=False).ids, 0], dtype="<u4")
        rows = packed[packed.doc_id == i].sort_values("piece")
        assert rows.length.sum() == len(ids) and (rows.length[1:] == 2048).all() and (rows.length <= 2048).all()
        for r in rows.itertuples():
            assert r.ids_crc32 == zlib.crc32(ids[r.start : r.start + r.length].tobytes())
    assert len(packed[packed.doc_id == 7]) == 2 and packed.doc_id.isna().sum() == 1


def test_places(packed):
    rows = packed.sort_values(["sequence_id", "offset"])
    ends = rows.groupby("sequence_id").length.cumsum()
    assert (ends - rows.length == rows.offset).all() and ends.max() <= 2048
    assert rows.sequence_id.nunique() == -(-rows.length.sum() // 2048)


def test_both_libraries_agree(spark, middle):
    encode = Encoder(PARAMETERS)
    for r in spark.read.parquet(f"{middle}/documents.parquet").select("text").limit(200).collect():
        assert encode(r.text).tolist() == encode.slow.encode(r.text, add_special_tokens=False).ids


def test_empty_and_small_bins(spark):
    docs = spark.createDataFrame([(1, "a b c d e f g h")], "doc_id long, text string")
    assert pack_documents(docs.limit(0)).count() == 0
    rows = pack_documents(docs, parameters=PackingParameters(capacity=4)).orderBy("piece").collect()
    assert [r.length for r in rows] == [1, 4, 4] and [r.start for r in rows] == [0, 1, 5]
