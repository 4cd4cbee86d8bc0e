"""The character model against a direct reading of the interpolated modified Kneser-Ney formulas."""

import math
from collections import Counter, defaultdict

import pytest

from prefbook.llm.kn_perplexity import PARAMETERS, POINTS, ModelParameters, judge_perplexity

TEXTS = ["the cat sat on the mat", "the dog sat on the log", "a cat and a dog", "été à la mer", "the the the", "on and on and on"]


def reference(trusted, order):
    """Probability of symbol w after a context, by dictionaries and recursion."""

    def grams(text):
        line = [None] * (order - 1) + list(text)
        return [tuple(line[i : i + order]) for i in range(len(text))]

    tables = {order: Counter(g for t in trusted for g in grams(t))}
    for n in range(order - 1, 0, -1):
        tables[n] = Counter(g[1:] for g in tables[n + 1])
    cuts = {}
    for n, table in tables.items():
        k = Counter(table.values())
        if k[1] and k[2]:
            y = k[1] / (k[1] + 2 * k[2])
            cuts[n] = [min(max(i - (i + 1) * y * k[i + 1] / k[i], 0.0), i) if k[i] else i * y for i in (1, 2, 3)]
        else:
            cuts[n] = [0.5] * 3
    followers = {n: defaultdict(dict) for n in tables}
    for n, table in tables.items():
        for g, c in table.items():
            followers[n][g[:-1]][g[-1]] = c

    def p(context, w):
        n = len(context) + 1
        below = p(context[1:], w) if n > 1 else 1 / POINTS
        seen = followers[n].get(context)
        if not seen:
            return below
        d = {s: cuts[n][min(c, 3) - 1] for s, c in seen.items()}
        return (max(seen.get(w, 0) - d.get(w, 0), 0.0) + sum(d.values()) * below) / sum(seen.values())

    def perplexity(text):
        if not text:
            return None
        return 2 ** (-sum(math.log2(p(g[:-1], g[-1])) for g in grams(text)) / len(text))

    return perplexity


@pytest.fixture(scope="module", params=[1_000_000, 20])
def judged(spark, request):
    others = ["zzzz qqqq", "", None, "the cat", "été", "日本語", "the cat"]
    docs = [(i, t, "fr" if "é" in t else "en", "x") for i, t in enumerate(TEXTS)] + [(100 + i, t, None if i == 3 else "en", "y") for i, t in enumerate(others)]
    labels = [(i, 1, 0) for i in range(len(TEXTS))] + [(0, 1, 0), (100, 0, 0), (999, 1, 0), (None, 1, 0)]
    frame = spark.createDataFrame(docs, "doc_id long, text string, lang string, limit string")
    out = judge_perplexity(frame, spark.createDataFrame(labels, "doc_id long, quality int, toxic int"), parameters=ModelParameters(shard_grams=request.param)).collect()
    return {d[0]: d[1] for d in docs}, {r.doc_id: r for r in out}


def test_matches_formulas(judged):
    texts, rows = judged
    perplexity = reference(TEXTS, PARAMETERS.order)
    for i, text in texts.items():
        want = perplexity(text)
        assert (rows[i].perplexity is None) == (want is None)
        assert want is None or rows[i].perplexity == pytest.approx(want, rel=1e-5)


def test_verdicts(judged):
    _, rows = judged
    assert not rows[101].kept and not rows[102].kept and rows[101].perplexity is None
    assert not rows[100].kept and not rows[105].kept
    assert all(rows[i].kept for i in range(len(TEXTS)))
    assert len(rows) == 13


def test_no_trusted_text(spark):
    docs = spark.createDataFrame([(1, "ab", "en"), (2, None, "en")], "doc_id long, text string, lang string")
    rows = {r.doc_id: r for r in judge_perplexity(docs, spark.createDataFrame([], "doc_id long, quality int, toxic int")).collect()}
    assert rows[1].perplexity == pytest.approx(POINTS) and rows[1].kept and rows[1].limit is None and not rows[2].kept


def test_noise_of_any_script_is_worse_than_prose(spark):
    """Characters of a script that few trusted texts use are symbols of their own."""
    import random

    draw = random.Random(5)
    words = ["".join(chr(draw.randrange(0x4E00, 0x9FA5)) for _ in range(2)) for _ in range(60)]
    prose = lambda: "".join(draw.choice(words) for _ in range(100)) + "。"
    latin = [" ".join(draw.choice(["the", "cat", "sat", "on", "a", "mat"]) for _ in range(40)) for _ in range(60)]
    chinese = [prose() for _ in range(31)]
    noise = "".join(chr(draw.randrange(0x4E00, 0x9FA5)) for _ in range(400))
    docs = [(i, t, "en") for i, t in enumerate(latin)] + [(100 + i, t, "zh") for i, t in enumerate(chinese)] + [(900, noise, "zh"), (901, prose(), "zh")]
    labels = [(i, 1) for i, *_ in docs if i < 900]
    rows = {r.doc_id: r for r in judge_perplexity(spark.createDataFrame(docs, "doc_id long, text string, lang string"), spark.createDataFrame(labels, "doc_id long, quality int")).collect()}
    assert rows[900].perplexity > 20 * rows[901].perplexity and not rows[900].kept
    assert sum(rows[100 + i].kept for i in range(31)) >= 30


def test_separates_labelled_documents(spark, middle):
    out = judge_perplexity(spark.read.parquet(f"{middle}/documents.parquet"), spark.read.parquet(f"{middle}/labels.parquet"))
    both = out.join(spark.read.parquet(f"{middle}/labels.parquet"), "doc_id").toPandas()
    assert (both[both.quality == 1].kept).mean() > 0.99
    assert (both[both.quality == 0].kept).mean() < 0.2


def test_limit_is_within_trusted_perplexities(judged):
    _, rows = judged
    worst = max(rows[i].perplexity for i in range(len(TEXTS)))
    assert rows[0].limit <= worst * 2 ** (1 / PARAMETERS.steps) + 1e-6
