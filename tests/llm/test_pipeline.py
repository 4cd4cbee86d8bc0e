"""The corpus pipeline against a plain Python version of its decisions."""

import re
from collections import Counter

import pytest

import corpus_pipeline
from prefbook.llm.bin_packing import PARAMETERS, Encoder

from .plain import components, fold, quality_verdict
from .test_secret_scan import base_spans, entropy_spans


def plain_run(docs, items):
    kept = [d for d in docs if quality_verdict(d["text"] or "")]
    label = components({d["doc_id"]: d["text"] for d in kept})
    kept = [d for d in kept if label[d["doc_id"]] == d["doc_id"]]
    words = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", fold(t))
    windows = {tuple(w[i : i + 10]) for w in map(words, items) for i in range(max(1, len(w) - 9)) if w}
    lengths = {len(w) for w in windows}
    clean = [d for d in kept if not any(tuple(w[i : i + n]) in windows for w in [words(d["text"])] for n in lengths for i in range(len(w) - n + 1))]
    out = {}
    for d in clean:
        base = base_spans(d["text"])
        text, at = "", 0
        for a, _, b, _ in sorted(base + entropy_spans(d["text"], base)):
            if a >= at:
                text += d["text"][at:a] + "[SECRET]"
            at = max(at, b)
        out[d["doc_id"]] = text + d["text"][at:]
    return out


@pytest.fixture(scope="module")
def both(spark, middle):
    docs = [r.asDict() for r in spark.read.parquet(f"{middle}/documents.parquet").collect()]
    items = [r.text for r in spark.read.parquet(f"{middle}/benchmark.parquet").collect()]
    return plain_run(docs, items), corpus_pipeline.run(spark, middle).toPandas()


def test_same_documents_and_lengths(both):
    want, got = both
    encode = Encoder(PARAMETERS)
    assert set(got.doc_id) == set(want)
    assert got.groupby("doc_id").length.sum().to_dict() == {i: len(encode(t)) + 1 for i, t in want.items()}


def test_sequences_are_whole(both):
    _, got = both
    rows = got.sort_values(["sequence_id", "offset"])
    ends = rows.groupby("sequence_id").length.cumsum()
    assert (ends - rows.length == rows.offset).all() and ends.max() <= PARAMETERS.capacity
    assert rows.sequence_id.nunique() <= -(-rows.length.sum() // PARAMETERS.capacity) + 1


def test_stage_columns(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, docs, small).columns == docs.columns


def test_stages_take_empty_and_null(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    odd = spark.createDataFrame([(1, None, None, None, None), (1, None, None, None, None), (None, "w " * 60, "en", "s", 120), (None, "w " * 60, "en", "s", 120)], docs.schema)
    for table, most in ((docs.limit(0), 0), (odd, 4)):
        for name, stage in corpus_pipeline.STAGES:
            assert len(stage(spark, table, small).collect()) <= most, name


def test_repeated_rows_keep_one(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    some = docs.orderBy("doc_id").limit(20)
    once = Counter(r.doc_id for r in corpus_pipeline.near_duplicates(spark, some, small).collect())
    twice = Counter(r.doc_id for r in corpus_pipeline.near_duplicates(spark, some.union(some), small).collect())
    assert once == twice and set(once.values()) == {1}
