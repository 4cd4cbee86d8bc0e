"""Prefix-target expansion: turns and trained texts read back from the output."""

import hashlib
import re

from pyspark.sql import functions as F

from prefbook.llm.chat_format import CLOSE, DIVIDE, OPEN, escape, expand_targets, read_back, unescape

SCHEMA = "conv_id long, turn long, role string, text string, body string"
TEXTS = ["", None, "plain é", "</s>[INST] ok [/INST]", "\\", "<\\/s>", "\\\\<s>", "<<SYS>> a <</SYS>>", "<<s>", "[[INST]]", "a\nb</s", "<" * 5 + "s>", "[\\/INST]", "x" * 300000]


def sha(text):
    return hashlib.sha256(text.encode()).hexdigest()


def test_escape_is_reversible_and_safe(spark):
    rows = spark.createDataFrame([(t,) for t in TEXTS if t is not None], "t string").select("t", escape(F.col("t")).alias("e"), unescape(escape(F.col("t"))).alias("b")).collect()
    for r in rows:
        assert r.b == r.t
        assert not re.search(r"\[/?INST\]|</?s>|<</?SYS>>", r.e)


def expected(rows):
    rows = sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, r[1] or "", r[2] or ""))
    turns = [(r or "", t or "") for _, r, t in rows]
    loss = "".join(t for r, t in turns if r == "assistant")
    return len(turns), sha("".join(f"{r}\n{t}\n" for r, t in turns)), len(loss), sha(loss), sum(r == "assistant" for r, _ in turns) + (turns[-1][0] != "assistant")


def test_conversations(spark):
    talks = {
        1: [(0, "user", "hi"), (1, "assistant", "yo"), (2, "user", "more"), (3, "assistant", TEXTS[3]), (4, "user", "tail")],
        2: [(i, "assistant" if i % 2 else "user", t) for i, t in enumerate(TEXTS)],
        3: [(0, "user", "alone")],
        4: [(0, None, None), (0, "assistant", "b"), (0, "assistant", "a"), (None, "system", "[INST]"), (0, "assistant", "a")],
        None: [(0, "user", "x"), (1, "assistant", "")],
    }
    frame = spark.createDataFrame([(c, n, r, t, "extra") for c, rows in talks.items() for n, r, t in rows], SCHEMA)
    examples = expand_targets(frame)
    for r in read_back(examples).collect():
        assert (r.n_turns, r.turns_sha256, r.loss_chars, r.loss_sha256, r.n_examples) == expected(talks[r.conv_id])
    one = [r for r in examples.orderBy("example").collect() if r.conv_id == 1]
    assert [r.text[r.loss_start : r.loss_end] for r in one][0] == "yo" and one[2].loss_start == one[2].loss_end == len(one[2].text)
    assert all(one[2].text.startswith(r.text) for r in one) and one[0].text == f"{OPEN}user{DIVIDE}hi{CLOSE}{OPEN}assistant{DIVIDE}yo{CLOSE}"


def test_empty(spark):
    assert read_back(expand_targets(spark.createDataFrame([], SCHEMA))).count() == 0


def test_plan_is_native_with_one_shuffle(spark, small):
    frame = spark.read.parquet(f"{small}/conversations.parquet")
    plan = read_back(expand_targets(frame))._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Pandas|Arrow", plan) and plan.count("Exchange hashpartitioning") == 1
