"""Quality rules, similarity join, decontamination and sharding against plain Python versions."""

import hashlib
import re
import zlib

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from prefbook.llm import shingle_join
from prefbook.llm.decontaminate import SearchParameters, drop_contaminated, find_contamination
from prefbook.llm.quality_rules import filter_quality, measure_quality
from prefbook.llm.sharding import shard_documents
from prefbook.llm.shingle_join import JoinParameters, keep_one_of_each, needed_tokens, similar_components

from .plain import components, fold, quality_measures, quality_verdict, shingle_set

SCHEMA = "doc_id long, text string, sig string, kept boolean"
WORDS = "alpha beta gamma delta epsilon zeta eta theta iota kappa".split()


def prose(start, n):
    return " ".join(f"{WORDS[(start * 7 + i * i + i * start) % 10]}{(start + i * 3) % 23}" for i in range(n))


ODD = ["", None, " \n\t ", "one", "A b C d", "a b c d e", "é É ß " * 30, prose(1, 200), prose(1, 200), prose(1, 195) + " x y z", "dup line here\n" * 20 + prose(2, 60), "x" * 200000, prose(3, 30000), "### ||| " * 60]


def frame(spark, texts):
    return spark.createDataFrame([(i, t, "s", None) for i, t in enumerate(texts)], SCHEMA)


def test_quality_measures(spark):
    rows = {r.doc_id: r for r in measure_quality(frame(spark, ODD)).collect()}
    for i, t in enumerate(ODD):
        want = quality_measures(t or "")
        assert {k: rows[i][k] for k in want} == want
        assert rows[i].kept == quality_verdict(t or "")
    kept = filter_quality(frame(spark, ODD))
    assert {r.doc_id for r in kept.collect()} == {i for i, t in enumerate(ODD) if quality_verdict(t or "")} and kept.columns == ["doc_id", "text", "sig", "kept"]
    assert filter_quality(frame(spark, ODD).limit(0)).count() == 0


@settings(max_examples=40, deadline=None)
@given(st.lists(st.text(alphabet="ab \n\té#|", max_size=60), min_size=1, max_size=6))
def test_quality_scan_property(texts):
    import pyarrow as pa

    from prefbook.llm.quality_rules import RepetitionScan
    from prefbook.llm.textscan import texts_of

    out = RepetitionScan()(texts_of(pa.array(texts)))
    for i, t in enumerate(texts):
        want = quality_measures(t)
        assert {k: int(out[k][i]) for k in want} == want


@pytest.mark.parametrize("group_tokens", [16384, 300])
def test_components(spark, group_tokens):
    base = [prose(k, 80) for k in range(4)]
    near = [" ".join(w if i != cut else "changed" for i, w in enumerate(b.split())) for b in base for cut in (3, 40, 79)]
    chain = [" ".join(prose(9, 120).split()[k : k + 80]) for k in range(0, 40, 5)]
    texts = ODD + base + near + chain + [base[0].upper()]
    marks = {r.doc_id: r for r in similar_components(frame(spark, texts), parameters=JoinParameters(group_tokens=group_tokens)).collect()}
    want = components(dict(enumerate(texts)))
    assert {i: marks[i].component_id for i in marks} == want
    assert {i: marks[i].n_shingles for i in marks} == {i: len(shingle_set(t)) for i, t in enumerate(texts)}
    kept = {r.doc_id for r in keep_one_of_each(frame(spark, texts)).collect()}
    assert kept == {i for i, c in want.items() if i == c}


def test_needed_tokens_of_all_inner_sizes(spark):
    up = lambda a, b: -(-a // b)
    need = {(a, b): up(75 * (a + b), 175) - up(75 * max(a, b), 100) + 1 for a in range(20, 140) for b in range(20, 140) if 100 * min(a, b) >= 75 * max(a, b)}
    ranges = [(a, a + w, b, b + v) for a in range(20, 128) for w in range(12) for b in range(20, 136) for v in (0, 4) if any((x, b) in need for x in range(a, a + w + 1))]
    rows = spark.createDataFrame(ranges, "a long, c long, b long, d long").withColumn("n", needed_tokens(75, ("a", "c"), ("b", "d"))).toPandas()
    for a, c, b, d, n in rows.itertuples(index=False):
        least = min(need.get((x, y), 999) for x in range(a, c + 1) for y in range(b, d + 1))
        assert n == max(1, least) if a == c and b == d else n <= max(1, least), (a, c, b, d)
    assert (rows.n > 1).any()


def test_many_near_copies(spark):
    """A large group of near copies whose members link with some others only."""
    base = prose(5, 150).split()
    texts = []
    for k in range(400):
        words = list(base)
        for j in range(k % 6):
            words[(k * 37 + j * 29) % 150] = f"edit{k}x{j}"
        texts.append(" ".join(words))
    marks = {r.doc_id: r.component_id for r in similar_components(frame(spark, texts)).collect()}
    assert marks == components(dict(enumerate(texts)))


def test_candidates_of_a_large_group(spark, monkeypatch):
    """Near copies, half of them too much changed to link: the pairs that meet follow the texts, not their square."""
    base = prose(5, 150).split()
    texts = []
    for k in range(1500):
        words = list(base)
        for j in range(k % 12):
            words[(k * 37 + j * 29) % 150] = f"edit{k}x{j}"
        texts.append(" ".join(words))
    made = []
    plain = shingle_join.settle

    def counted(df):
        out = plain(df)
        if out.columns == ["ga", "gb", "ra", "rb"]:
            made.append(out.count())
        return out

    monkeypatch.setattr(shingle_join, "settle", counted)
    marks = {r.doc_id: r.component_id for r in similar_components(frame(spark, texts)).collect()}
    assert max(made) <= 2 * len(texts)
    assert all(marks[k] == 0 for k in range(1500) if k % 12 < 4)


def test_words_of_a_regular_build_differ(spark):
    """Two words that agree in every polynomial of an odd number modulo 2**64."""
    one = "a"
    for _ in range(10):
        one += one.translate(str.maketrans("ab", "ba"))
    other = one.translate(str.maketrans("ab", "ba"))
    marks = similar_components(frame(spark, [one, other])).collect()
    assert {r.component_id for r in marks} == {0, 1}
    rows = measure_quality(frame(spark, [f"{one} x y {other} x y"])).collect()
    assert rows[0].n_repeat_words == 0


def test_clashing_names(spark):
    names = ["stay_id", "seen_id", "own_id", "SIG", "root", "n words", "a.b"]
    docs = spark.createDataFrame([(i, prose(1, 60), *range(len(names))) for i in (3, 3, 4)] + [(5, "w " * 70, *range(len(names)))], "`doc id` long, text string, " + ", ".join(f"`{n}` int" for n in names))
    kept = keep_one_of_each(docs, "doc id")
    assert kept.columns == docs.columns and sorted(r[0] for r in kept.collect()) == [3, 5]
    other = docs.withColumnRenamed("text", "body").withColumnRenamed("doc id", "text").withColumnRenamed("seen_id", "id")
    items = spark.createDataFrame([(1, "w " * 12)], "item long, passage string")
    for p in (SearchParameters(), SearchParameters(block_patterns=1)):
        found = find_contamination(other, items, "text", "body", "item", "passage", p)
        assert {r.text: r.contaminated for r in found.collect()} == {3: False, 4: False, 5: True}
    assert drop_contaminated(other, items, "text", "body", "item", "passage").columns == other.columns
    assert {r.text for r in measure_quality(other, "text", "body").collect()} == {3, 4, 5}
    assert len(shard_documents(other, id_column="text", text_column="body").collect()) == 4


def test_components_odd_rows(spark):
    rows = [(None, prose(1, 60)), (7, prose(1, 60)), (7, prose(1, 60)), (7, prose(2, 60)), (9, None), (9, None)]
    docs = spark.createDataFrame([(i, t, None, None) for i, t in rows], SCHEMA)
    marks = similar_components(docs).collect()
    assert len(marks) == 6 and {r.component_id for r in marks} == {7, 9}
    assert sorted(r.doc_id for r in keep_one_of_each(docs).collect()) == [7, 7, 9]
    assert similar_components(docs.limit(0)).count() == 0 and keep_one_of_each(docs.limit(0)).count() == 0


def search(docs, items, width=10):
    words = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", fold(t or ""))
    runs = {}
    for i, t in items:
        w = words(t)
        for k in range(max(1, len(w) - width + 1)):
            if w:
                runs.setdefault(tuple(w[k : k + width]), set()).add(str(i))
    out = []
    for t in docs:
        w = words(t)
        hit, named = set(), set()
        for n in {len(r) for r in runs}:
            for k in range(len(w) - n + 1):
                if (found := runs.get(tuple(w[k : k + n]))) is not None:
                    hit.update(range(k, k + n))
                    named |= found
        out.append((len(w), len(hit), sorted(named)))
    return out


@pytest.mark.parametrize("block", [500_000, 7])
def test_decontamination(spark, block):
    items = [(1, prose(1, 30)), (2, "Short Item!"), (3, prose(2, 10)), (4, None), (5, ""), (11, prose(1, 12)), (6, "solo"), (7, "a b c d e f g h i j a b c d e f g h i j k")]
    docs = [*ODD, prose(1, 12) + " tail", "x " + prose(2, 10).upper() + ", y", "the short... item", "solo", prose(2, 9), "a b c d e f g h i j " * 4, "pre " + prose(1, 30) + " mid " + prose(1, 30)]
    benchmark = spark.createDataFrame(items, "item_id long, text string")
    p = SearchParameters(block_patterns=block)
    got = {r.doc_id: r for r in find_contamination(frame(spark, docs), benchmark, parameters=p).collect()}
    for i, (n, hit, named) in enumerate(search(docs, items)):
        assert (got[i].n_words, got[i].n_hit, got[i].n_items, got[i]["items"], got[i].contaminated) == (n, hit, len(named), named, hit > 0), docs[i]
    kept = drop_contaminated(frame(spark, docs), benchmark, parameters=p)
    assert {r.doc_id for r in kept.collect()} == {i for i, r in got.items() if not r.contaminated} and kept.columns == ["doc_id", "text", "sig", "kept"]
    assert find_contamination(frame(spark, docs), benchmark.limit(0)).filter("contaminated").count() == 0
    assert find_contamination(frame(spark, docs).limit(0), benchmark).count() == 0


def test_sharding(spark, middle):
    docs = spark.read.parquet(f"{middle}/documents.parquet")
    texts = {r.doc_id: r.text for r in docs.select("doc_id", "text").collect()}
    rows = shard_documents(docs).collect()
    slots = {}
    for r in rows:
        raw = (texts[r.doc_id] or "").encode()
        assert r["size"] == len(raw) + 8 and r.text_crc32 == zlib.crc32(raw) and r.law == "key"
        u = [(int(hashlib.md5(f"{r.doc_id}|{s}".encode()).hexdigest()[:13], 16) + 0.5) / 2**52 for s in range(25)]
        assert r.shard == u.index(max(u[:24])) and r.grown_shard == u.index(max(u))
        slots.setdefault(r.shard, []).append(r.slot)
    assert all(sorted(s) == list(range(len(s))) for s in slots.values()) and set(slots) == set(range(24))


def test_weighted_shards(spark):
    docs = spark.range(4000).selectExpr("id as doc_id", "cast(id as string) as text")
    rows = shard_documents(docs, weights={0: 1.0, 1: 3.0, 2: 0.0}).collect()
    same = shard_documents(spark.range(0, 5000, 1, 8).selectExpr("7L as doc_id", "'x' as text")).collect()
    assert sorted(r.slot for r in same) == list(range(5000)) and len({r.shard for r in same}) == 1
    share = sum(r.shard == 1 for r in rows) / len(rows)
    assert 0.72 < share < 0.78 and not any(r.shard == 2 for r in rows)


def test_sharding_odd_rows(spark):
    docs = spark.createDataFrame([(None, None, "a", None), (None, "x", "b", None), (3, "é", "c", None), (3, "é", "c", None)], SCHEMA)
    rows = shard_documents(docs).collect()
    assert len(rows) == 4 and sorted(r["size"] for r in rows) == [8, 9, 10, 10]
    assert shard_documents(docs.limit(0)).count() == 0
