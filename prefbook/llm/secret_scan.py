"""Secret spans in whole texts: fixed shapes, and strings of high windowed entropy. DataFrame functions only.

Candidate strings are maximal runs of key characters that mix letters and digits. A window
of fixed length slides over each; counts of the characters inside change by the one that
enters and the one that leaves, and so does the sum that gives Shannon's entropy. A string
is a finding when its highest window reaches the limit of its character class (hexadecimal,
letters of one case with digits, letters of both cases with digits) and no entry of the
allow list speaks for it. Findings of fixed shape stay whatever the allow list says;
entropy findings that touch one of them add nothing and are left out.

Running sums and maxima go over arrays in chunks, and pieces of a text are taken from its
blocks, so that a text with very many matches takes time that follows its length.

Positions are code points, end exclusive. Edge cases: a null text is empty and has no
spans. Repeated rows get equal output. Extra columns pass through ``mask_secrets``.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from math import log2

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .session import column, fresh

#: Fixed patterns, by kind. ``least`` is compared with the length of ``group``.
KINDS = (
    ("assign", r"""(?:[Pp][Aa][Ss][Ss][Ww][Oo][Rr][Dd]|[Pp][Aa][Ss][Ss][Ww][Dd]|[Ss][Ee][Cc][Rr][Ee][Tt]|[Tt][Oo][Kk][Ee][Nn]|[Aa][Pp][Ii]_?[Kk][Ee][Yy])["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 1, 6),
    ("access", r"AKIA[A-Z0-9]+", 0, 20),
    ("hex", r"[0-9a-f]+", 0, 24),
)
#: Same matches of sufficient length, for runs where a shorter match can't hide a longer one.
_TIGHT = {"access": r"AKIA[A-Z0-9]{16,}+", "hex": r"(?<![0-9a-f])[0-9a-f]{24,}+"}


_PATH_WORD = "(?:[A-Z]?[a-z]+(?:[A-Z][a-z]+)*[0-9]{0,3}|[A-Z]+[0-9]{0,3}|[0-9]{1,8})"
_SEGMENT = f"{_PATH_WORD}(?:[_-]+{_PATH_WORD})*"


@dataclass(frozen=True)
class EntropyRules:
    window: int = 20
    #: Bits of a window of 20: random hexadecimal strings have about 3.4, base 64 about 4.1, words at most 3.6.
    hex_bits: float = 3.0
    single_case_bits: float = 3.7
    mixed_bits: float = 3.8
    #: Suppressing patterns over a candidate and the characters before it.
    allowed: tuple[str, ...] = (
        r"(?i)(example|sample|dummy|placeholder|changeme|your[_-]|xxxx|test[_-]?key)",
        r"(?i)[0-9a-f]{8}-[0-9a-f]{4}-[0-9a-f]{4}-[0-9a-f]{4}-[0-9a-f]{12}$",
        r"(?i)(sha-?(1|224|256|384|512)|md5|commit|revision|integrity|checksum|digest|etag)['\"]?\s*[:=@/-]?\s*\S*$",
        r"(0123456789|123456789|abcdefgh|ABCDEFGH)",
        r"(.)\1{7}",
        # A path of words and numbers; a random string with '/' among its characters isn't one.
        rf"(?:^|[^A-Za-z0-9+/_=-])(?=[^/]*/)/?{_SEGMENT}(?:/+{_SEGMENT})*/?$",
    )
    context: int = 24
    #: The host and path of an address with its scheme or www. in front, up to the candidate's end; a value after '=' or '?' is no part of it.
    address: str = r"(?i)(?:https?://|\bwww\.)[a-z0-9._-]+(?::[0-9]{1,5})?(?:/[a-z0-9+/_.~%-]*=*)?$"
    #: Characters that may lie between an address's begin and a candidate; beyond that the entropy decides.
    address_context: int = 2000


RULES = EntropyRules()
_CANDIDATE = r"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9+/_=-]{%d,}+"


#: Elements of an array that are walked at once: what a walk appends to stays short.
CHUNK = 128
#: Characters of a block of a text.
BLOCK = 4096
_SPAN = "array<struct<start:int,rank:int,end:int,kind:string,match:string>>"


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of a value that is computed once, however often the body and its lambdas name it."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def chunked(values: Column) -> Column:
    """An array, given by name or as a lambda's variable, cut into arrays of CHUNK elements."""
    starts = F.sequence(F.lit(0), F.greatest(F.lit(0), F.floor((F.size(values) - 1) / CHUNK).cast("int")))
    return F.transform(starts, lambda k: F.slice(values, k * CHUNK + 1, F.lit(CHUNK)))


def running(values: Column, combine) -> Column:
    """For each element of an array of ints what ``combine``, a sum or maximum, makes of 0 and all before it."""
    none = F.array().cast("array<int>")

    def walk(part: Column, at: Column) -> Column:
        step = lambda s, x: F.struct(combine(s["at"], x).alias("at"), F.array_append(s["out"], s["at"]).alias("out"))
        return F.aggregate(part, F.struct(at.alias("at"), none.alias("out")), step, lambda s: s["out"])

    def walked(parts: Column) -> Column:
        totals = F.transform(parts, lambda part: F.aggregate(part, F.lit(0), combine))
        return F.flatten(F.zip_with(parts, walk(totals, F.lit(0)), walk))

    return let(values, lambda v: let(chunked(v), walked))


def located(text: Column, pattern: str, kind: str, rank: int, group: int = 0, least: int = 0) -> Column:
    """Array of spans of a pattern's matches, leftmost and not overlapping; matches with a group shorter than ``least`` are dropped."""
    whole = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    inner = F.regexp_extract_all(text, F.lit(pattern), F.lit(group)) if group else whole
    gaps = lambda w: F.zip_with(F.slice(F.split(text, pattern, -1), F.lit(1), F.size(w)), w, lambda gap, m: F.struct(F.char_length(gap).alias("gap"), F.char_length(m).alias("long"), m.alias("m")))

    def span(s: Column, at: Column) -> Column:
        begin = at + s["gap"]
        return F.struct(begin.alias("start"), F.lit(rank).alias("rank"), (begin + s["long"]).alias("end"), F.lit(kind).alias("kind"), s["m"].alias("match"))

    spans = let(let(whole, gaps), lambda steps: F.zip_with(steps, running(F.transform(steps, lambda s: s["gap"] + s["long"]), lambda a, b: a + b), span))
    if least:
        kept = F.filter(F.zip_with(spans, inner, lambda s, g: F.struct(s.alias("s"), g.alias("g"))), lambda x: F.char_length(x["g"]) >= least)
        spans = F.transform(kept, lambda x: x["s"])
    return F.when(text.rlike(pattern), spans.cast(_SPAN)).otherwise(F.array().cast(_SPAN))


def blocks(text: Column) -> Column:
    """The text in pieces of BLOCK characters."""
    return F.when(F.char_length(text) <= BLOCK, F.array(text)).otherwise(F.regexp_extract_all(text, F.lit("(?s).{1,%d}" % BLOCK), F.lit(0)))


def piece(parts: Column, start: Column, end: Column) -> Column:
    """Characters from start to end (exclusive) of a text in blocks, reading the blocks that hold them only."""
    first = F.floor(start / BLOCK).cast("int")
    last = F.floor(F.greatest(start, end - 1) / BLOCK).cast("int")
    return F.substring(F.array_join(F.slice(parts, first + 1, last - first + 1), ""), start - first * BLOCK + 1, F.greatest(F.lit(0), end - start))


#: Characters of a candidate begin with the plus sign; counts of at most a window take five bits, and twelve of them a long.
_FIRST, _BITS, _PACKED, _WORDS = ord("+"), 5, 12, 7


def window_bits(text: Column, window: int) -> Column:
    """Highest Shannon entropy, in bits, of the windows of a string of key characters that is at least one window long.

    The counts of the characters in a window lie packed in a few longs; as the window moves, one count goes up and one
    goes down, and the sum behind the entropy changes by their terms.
    """
    if not 1 < window < 1 << _BITS:
        raise ValueError(f"a window has 2 to {(1 << _BITS) - 1} characters")
    weights = F.array(*(F.lit(0.0 if c < 2 else c * log2(c)) for c in range((1 << _BITS) + 1)))
    units = F.array(*(F.lit(1 << _BITS * k).cast("long") for k in range(_PACKED)))
    state = F.struct(F.array_repeat(F.lit(0).cast("long"), _WORDS).alias("counts"), F.lit(0.0).alias("sum"), F.lit(0.0).alias("best"))
    codes = F.transform(F.split(text, ""), lambda c: F.ascii(c) - _FIRST)
    at = lambda c: F.struct(F.floor(c / _PACKED).cast("int").alias("word"), F.get(units, F.pmod(c, F.lit(_PACKED))).alias("unit"))
    places = F.transform(codes, at)

    def count(counts: Column, place: Column) -> Column:
        return F.call_function("div", F.get(counts, place["word"]), place["unit"]).bitwiseAND((1 << _BITS) - 1).cast("int")

    def step(s: Column, pair: Column) -> Column:
        enters, leaves = pair["enters"], pair["leaves"]
        same = leaves.isNotNull() & (enters == leaves)
        into, out = count(s["counts"], enters), count(s["counts"], leaves)
        gain = F.get(weights, into + 1) - F.get(weights, into)
        loss = F.when(leaves.isNull(), F.lit(0.0)).otherwise(F.get(weights, out) - F.get(weights, out - 1))
        total = F.when(same, s["sum"]).otherwise(s["sum"] + gain - loss)
        none = F.lit(0).cast("long")
        counts = F.transform(s["counts"], lambda c, j: c + F.when(enters["word"] == j, enters["unit"]).otherwise(none) - F.when(leaves["word"] == j, leaves["unit"]).otherwise(none))
        bits = F.when(pair["full"], F.lit(log2(window)) - total / window).otherwise(F.lit(0.0))
        return F.struct(counts.alias("counts"), total.alias("sum"), F.greatest(s["best"], bits).alias("best"))

    def pairs(held: Column) -> Column:
        return F.transform(held, lambda c, i: F.struct(c.alias("enters"), F.when(i >= window, F.get(held, i - window)).alias("leaves"), (i >= window - 1).alias("full")))

    return F.aggregate(let(places, pairs), state, step, lambda s: s["best"])


def _suspicious(parts: Column, span: Column, r: EntropyRules) -> Column:
    match = span["match"]
    limit = F.when(match.rlike("^[0-9a-fA-F]+$"), F.lit(r.hex_bits)).when(match.rlike("[a-z]") & match.rlike("[A-Z]"), F.lit(r.mixed_bits)).otherwise(F.lit(r.single_case_bits))

    def seen_with(context: int) -> Column:
        return F.concat(piece(parts, F.greatest(F.lit(0), span["start"] - context), span["start"]), match)

    seen = seen_with(r.context)
    allowed = match.contains("/") & seen_with(r.address_context).rlike(r.address)
    for pattern in r.allowed:
        allowed = allowed | seen.rlike(pattern)
    mixes = match.rlike("[0-9]") & match.rlike("[A-Za-z]")
    return F.when(mixes & ~allowed, window_bits(match, r.window) >= limit).otherwise(F.lit(False))


def _apart(spans: Column, others: Column) -> Column:
    """The spans that overlap none of ``others``; whole chunks of those are passed over."""
    over = lambda t, s: (t["start"] < s["end"]) & (s["start"] < t["end"])
    held = F.transform(let(F.array_sort(others), chunked), lambda c: F.struct(c.alias("c"), c[0]["start"].alias("start"), F.array_max(F.transform(c, lambda t: t["end"])).alias("end")))
    clear = let(held, lambda held: F.filter(spans, lambda s: ~F.exists(held, lambda h: over(h, s) & F.exists(h["c"], lambda t: over(t, s)))))
    return F.when(F.size(others) == 0, spans).otherwise(clear)


def scan_secrets(docs: DataFrame, text_column: str = "text", rules: EntropyRules = RULES, into: str = "secrets") -> DataFrame:
    """``docs`` with an array of (start, rank, end, kind) by start and then kind; narrow, no shuffle."""
    text = F.coalesce(column(text_column), F.lit(""))
    base = F.concat(*(located(text, _TIGHT.get(kind, pattern), kind, rank, group, least) for rank, (kind, pattern, group, least) in enumerate(KINDS)))
    b, e, t = fresh([*docs.columns, into], f"{into}_base", f"{into}_entropy", f"{into}_blocks")
    marked = docs.select("*", base.alias(b), located(text, _CANDIDATE % rules.window, "entropy", len(KINDS)).alias(e))
    parted = marked.withColumn(e, _apart(F.col(e), F.col(b))).withColumn(t, F.when(F.size(e) > 0, blocks(text)))
    clear = F.filter(e, lambda s: _suspicious(F.col(t), s, rules))
    spans = F.array_sort(F.concat(b, clear))
    return parted.select(*(column(n) for n in docs.columns), F.transform(spans, lambda s: F.struct(s["start"].alias("start"), s["rank"].alias("rank"), s["end"].alias("end"), s["kind"].alias("kind"))).alias(into))


def listed(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def secret_report(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", rules: EntropyRules = RULES) -> DataFrame:
    """id, n_assign, n_access, n_hex, n_entropy, base_sha256 and spans of each row."""
    found = scan_secrets(docs.select(column(id_column).alias("id"), column(text_column).alias("text")), "text", rules, "secrets")
    count = lambda kind: F.size(F.filter("secrets", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    base = F.filter("secrets", lambda s: s["rank"] < len(KINDS))
    return found.select(F.col("id").alias(id_column), *(count(kind) for kind, *_ in KINDS), count("entropy"), F.sha2(listed(base), 256).alias("base_sha256"), listed(F.col("secrets")).alias("spans"))


def mask_secrets(docs: DataFrame, text_column: str = "text", mask: str = "[SECRET]", rules: EntropyRules = RULES) -> DataFrame:
    """``docs`` with each run of overlapping spans replaced by ``mask``; a column n_chars follows the new text."""
    name, parts = fresh(docs.columns, "secrets", "blocks")
    text = column(text_column)
    found = scan_secrets(docs, text_column, rules, name).withColumn(parts, F.when(F.size(name) > 0, blocks(text)))
    ends = running(F.transform(name, lambda s: s["end"]), lambda a, b: F.greatest(a, b))

    def kept(span: Column, at: Column) -> Column:
        return F.when(span["start"] < at, F.lit("")).otherwise(F.concat(piece(F.col(parts), at, span["start"]), F.lit(mask)))

    rest = piece(F.col(parts), F.array_max(F.transform(name, lambda s: s["end"])), F.char_length(text))
    masked = F.concat(F.array_join(F.zip_with(name, ends, kept), ""), rest)
    out = found.withColumn(text_column, F.when(F.size(name) > 0, masked).otherwise(text))
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.size(name) > 0, F.char_length(text).cast(dict(docs.dtypes)["n_chars"])).otherwise(F.col("n_chars")))
    return out.select(*(column(n) for n in docs.columns))
