"""Chat formatting by prefix-target expansion. DataFrame functions only.

Each assistant turn becomes an example of its own: all turns before it are context, and
only its text lies under the loss mask. Turns after the last assistant turn make a last
example without a target, so that nothing of a conversation is lost.

A turn is written as ``[INST]role[/INST]text</s>``. A control string inside a role or text
gets a backslash after its first character, and each backslash of the source is doubled,
so what was written can be read back exactly, and no text can pose as a turn.

A conversation is written once as one string; examples are its prefixes and are cut from
it row by row, so the quadratic total of all prefixes streams through without a shuffle or
a collection. A conversation has to fit into one row, as its digests are over all of it.

Edge cases: null texts and roles are empty strings. Rows of equal conversation and turn
are ordered by role and then text. A null turn comes first; null conversation ids are one
conversation. An empty table gives no rows. Extra columns are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Fixed strings: they open a turn, divide role from text, and end a turn.
OPEN, DIVIDE, CLOSE = "[INST]", "[/INST]", "</s>"
_CONTROL = r"\[(?=/?INST\])|<(?=/?s>|<SYS>>|</SYS>>)"


def escape(text: Column) -> Column:
    doubled = F.replace(F.coalesce(text, F.lit("")), F.lit("\\"), F.lit("\\\\"))
    return F.regexp_replace(doubled, _CONTROL, r"$0\\")


def unescape(text: Column) -> Column:
    """A pair of backslashes is one, a single one is none."""
    return F.regexp_replace(text, r"\\(\\?)", "$1")


def written(conversations: DataFrame) -> DataFrame:
    """conv_id, body (all turns as one string) and targets (position after each assistant turn, start and end of its text)."""
    turn = F.struct("turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    gathered = conversations.groupBy("conv_id").agg(F.array_sort(F.collect_list(turn)).alias("turns"))
    pieces = F.transform("turns", lambda t: F.struct(t["role"].alias("role"), F.concat(F.lit(OPEN), escape(t["role"]), F.lit(DIVIDE)).alias("head"), escape(t["text"]).alias("body")))
    sized = F.transform(pieces, lambda t: F.struct((t["role"] == "assistant").alias("target"), F.char_length(t["head"]).alias("head"), F.char_length(t["body"]).alias("body")))
    zero = F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<start:int,end:int,stop:int>>").alias("spans"))

    def step(s: Column, t: Column) -> Column:
        start = s["at"] + t["head"]
        end = start + t["body"]
        stop = end + len(CLOSE)
        span = F.struct(start.alias("start"), end.alias("end"), stop.alias("stop"))
        return F.struct(stop.alias("at"), F.when(t["target"], F.array_append(s["spans"], span)).otherwise(s["spans"]).alias("spans"))

    rows = gathered.select("conv_id", pieces.alias("pieces"), F.aggregate(sized, zero, step).alias("walk"))
    body = F.array_join(F.transform("pieces", lambda t: F.concat(t["head"], t["body"], F.lit(CLOSE))), "")
    last = F.get(F.col("walk.spans"), F.size("walk.spans") - 1)
    rest = F.when((F.size("walk.spans") == 0) | (last["stop"] < F.col("walk.at")), F.array(F.struct(F.col("walk.at").alias("start"), F.col("walk.at").alias("end"), F.col("walk.at").alias("stop"))))
    return rows.select("conv_id", body.alias("body"), F.concat("walk.spans", F.coalesce(rest, F.array().cast("array<struct<start:int,end:int,stop:int>>"))).alias("targets"))


def expand_targets(conversations: DataFrame) -> DataFrame:
    """One row per example: conv_id, example, text, and the loss mask from loss_start to loss_end (code points)."""
    rows = written(conversations).select("conv_id", "body", F.posexplode("targets").alias("example", "span"))
    return rows.select("conv_id", "example", F.substring("body", F.lit(1), F.col("span.stop")).alias("text"), F.col("span.start").alias("loss_start"), F.col("span.end").alias("loss_end"))


def read_back(examples: DataFrame) -> DataFrame:
    """One row per conversation, from its examples alone: turns and trained texts in order, with digests."""
    target = F.substring("text", F.col("loss_start") + 1, F.col("loss_end") - F.col("loss_start"))
    own = examples.groupBy("conv_id").agg(
        F.max_by("text", "example").alias("longest"),
        F.array_sort(F.collect_list(F.struct("example", target.alias("target")))).alias("targets"),
        F.sum(F.char_length("text").cast("long")).alias("formatted_chars"),
        F.count("*").alias("n_examples"),
    )
    texts = F.filter(F.split("longest", CLOSE, -1), lambda t: t.startswith(OPEN))
    turns = F.transform(texts, lambda t: F.split(F.substring(t, F.lit(len(OPEN) + 1), F.char_length(t)), r"\[/INST\]", 2))
    plain = F.transform(turns, lambda t: F.concat(unescape(F.get(t, F.lit(0))), F.lit("\n"), unescape(F.get(t, F.lit(1))), F.lit("\n")))
    loss = F.array_join(F.transform("targets", lambda t: unescape(t["target"])), "")
    read = own.select("conv_id", plain.alias("turns"), loss.alias("loss"), "formatted_chars", "n_examples")
    return read.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(F.array_join("turns", ""), 256).alias("turns_sha256"),
        F.char_length("loss").cast("long").alias("loss_chars"),
        F.sha2("loss", 256).alias("loss_sha256"),
        "formatted_chars",
        "n_examples",
    )
