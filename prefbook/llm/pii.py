"""Personal data in whole texts, disguised spellings included, with spans of the source.

Detectors for e-mail addresses, IP addresses, card and phone numbers read the text as it
is. A chain of transducers, each of which runs wherever it would change something, rewrites it: homoglyphs
and full-width forms become ASCII, invisible characters go, runs of spelled digits become
digits, as do letters of their shapes among digits, bracketed or spelled-out "at" and "dot" become their characters. Each transducer
carries for every character of its output the source span that it stands for. The same
detectors read the result, and what they find there by virtue of a rewriting is mapped
back and added. Where it touches spans of the plain text, it is added if it is wider than
all of them together: a plain span is then a part of it, and stays. It never touches
another added span.

Positions are code points, end exclusive. Edge cases: a null text is empty. Repeated rows
get equal output. Several matches of a kind don't overlap; the leftmost wins. An empty
table gives no rows. Only the id and the text are read, so other columns may have any name.
"""

from __future__ import annotations

import hashlib
import re
import unicodedata
from bisect import bisect_left, bisect_right
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .session import arrow_map, column, fields, process_cache

KINDS = ("email", "ip", "card", "phone")
Span = tuple[int, int]

_DOMAIN = re.compile(r"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")  # a match never begins within a run of digits
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_NOT_DIGIT = re.compile(r"[^0-9]+")


def luhn(digits: str) -> bool:
    odd, even = digits[-1::-2], digits[-2::-2]
    return (sum(map(int, odd)) + sum(2 * int(d) - 9 * (d > "4") for d in even)) % 10 == 0


def emails(text: str) -> Iterator[Span]:
    """Each domain with the local characters right before it, as far as the address before."""
    taken = 0
    for m in _DOMAIN.finditer(text) if "@" in text else ():
        at = m.start()
        while at > taken and text[at - 1] in _LOCAL:
            at -= 1
        if at < m.start():
            taken = m.end()
            yield at, taken


def addresses(text: str) -> Iterator[Span]:
    for m in _IP.finditer(text):
        if all(len(part.lstrip("0")) <= 3 and int(part) <= 255 for part in m[0].split(".")):
            yield m.span()


def cards(text: str) -> Iterator[Span]:
    for m in _CARD.finditer(text):
        if m.end() - m.start() >= 16:
            digits = _NOT_DIGIT.sub("", m[0])
            if 16 <= len(digits) <= 19 and luhn(digits):
                yield m.span()


def phones(text: str) -> Iterator[Span]:
    for m in _PHONE.finditer(text) if "+" in text else ():
        if 8 <= len(_NOT_DIGIT.sub("", m[0])) <= 15:
            yield m.span()


DETECTORS: dict[str, Callable[[str], Iterator[Span]]] = {"email": emails, "ip": addresses, "card": cards, "phone": phones}

# Spelled digits of four languages, and words for the two marks of an address.
_SPELLED = {
    "zero": "0", "one": "1", "two": "2", "three": "3", "four": "4", "five": "5", "six": "6", "seven": "7", "eight": "8", "nine": "9", "oh": "0",
    "null": "0", "eins": "1", "zwei": "2", "drei": "3", "vier": "4", "fünf": "5", "sechs": "6", "sieben": "7", "acht": "8", "neun": "9",
    "zéro": "0", "un": "1", "deux": "2", "trois": "3", "quatre": "4", "cinq": "5", "sept": "7", "huit": "8", "neuf": "9",
    "cero": "0", "uno": "1", "dos": "2", "tres": "3", "cuatro": "4", "cinco": "5", "seis": "6", "siete": "7", "ocho": "8", "nueve": "9",
}
_AT = "at|arobase|arroba|klammeraffe"
_DOT = "dot|point|punkt|punto"
_LOOKALIKE = dict(zip("аеорсухіјѕһԁԛԝАВЕКМНОРСТХІЈЅαοερνικΑΒΕΖΗΙΚΜΝΟΡΤΥΧ", "aeopcyxijshdqwABEKMHOPCTXIJSaoepvikABEZHIKMNOPTYX"))

#: Characters that the first transducer may change, and nothing that Latin-script prose uses.
_STRANGE = re.compile("[­Ͱ-ӿԀ-ԯ٠-٩۰-۹०-९​-‏․⁠⁰-ₜ①-⑳⒈-⒛﹒﹫﻿！-～｡\U0001d400-\U0001d7ff\U0001f100-\U0001f10a]")
_WORD = "|".join(sorted(_SPELLED, key=len, reverse=True))
_TIMES = {"double": 2, "triple": 3}
_MANY = "(?:" + "|".join(_TIMES) + r")[\x20-]"
_DIGIT_RUN = re.compile(rf"(?i)(?<!\w)(?:plus[\x20,-]+|\+\x20?)?(?:(?:{_MANY})?(?:{_WORD})|[0-9]{{1,4}})(?:[\x20.,-]{{1,2}}(?:(?:{_MANY})?(?:{_WORD})|{_DOT}|[0-9]{{1,4}})(?!\w)){{3,}}")
_DIGIT_WORD = re.compile(rf"(?i)(plus)|({_WORD})|([0-9+])|({_DOT})|({'|'.join(_TIMES)})|[^0-9+]")
#: Digits with some letters of their shapes among them; no letter or digit stands before or after.
_MIXED_RUN = re.compile(r"(?<![A-Za-z0-9])\+?[0-9OolI](?:[\x20().-]{0,2}[0-9OolI]){5,}(?![A-Za-z0-9])")
_SHAPES = str.maketrans("OolI", "0011")
_BRACKETS = re.compile(rf"(?i)\s?[(\[{{<]\s?(?:(?P<at>{_AT}|@)|(?P<dot>{_DOT}|\.))\s?[)\]}}>]\s?")
_SPOKEN = re.compile(rf"(?i)(?<=[A-Za-z0-9._%+-])\x20(?P<at>{_AT})\x20(?=[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)*\x20(?:{_DOT})\x20[A-Za-z0-9-]+)|(?<=[A-Za-z0-9-])\x20(?P<dot>{_DOT})\x20(?=[A-Za-z0-9-]+)")
#: Marks as they stand in addresses and pages, and words between equal signs.
_CODED = re.compile(r"(?i)(?P<at>(?<=[A-Za-z0-9])%40(?=[A-Za-z0-9-]+\.)|&#0*64;|&#x0*40;|&commat;)|(?P<dot>&#0*46;|&#x0*2e;|&period;)")
_JOINED = re.compile(r"(?i)(?<![A-Za-z0-9.+])([A-Za-z0-9.+]++)([-_*~])at\2([A-Za-z0-9.]++)((?:\2dot\2[A-Za-z0-9]++)++)")
#: One plain word or sign between a local part and a whole domain; prose has that too, so the local part decides.
_ONE_SIDED = re.compile(rf"(?i)(?<=[A-Za-z0-9])\x20(?:{_AT}|@)\x20(?=[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)*+(?<=\.[A-Za-z][A-Za-z]|[A-Za-z]{{3}})(?<!\.))(?=[^\x20]*\.)")
_LOCAL_END = re.compile(r"[A-Za-z0-9._%+-]{1,64}$")


class Rewriting:
    """A text with the source span that each of its characters stands for."""

    def __init__(self, text: str):
        self.text = text
        self.starts = np.arange(len(text), dtype=np.int64)
        self.ends = self.starts + 1

    def replace(self, pattern: re.Pattern, by: Callable[[re.Match], str | None]) -> Rewriting:
        """Each match becomes ``by(match)``, all of whose characters stand for the whole match; None leaves it."""
        texts, starts, ends, at = [], [], [], 0
        for m in pattern.finditer(self.text):
            new = by(m)
            if new is None or m.end() == m.start():
                continue
            a, b = m.span()
            texts += [self.text[at:a], new]
            starts += [self.starts[at:a], np.full(len(new), self.starts[a])]
            ends += [self.ends[at:a], np.full(len(new), self.ends[b - 1])]
            at = b
        if not texts:
            return self
        out = Rewriting("")
        out.text = "".join([*texts, self.text[at:]])
        out.starts = np.concatenate([*starts, self.starts[at:]])
        out.ends = np.concatenate([*ends, self.ends[at:]])
        return out

    def source(self, start: int, end: int) -> Span:
        return int(self.starts[start]), int(self.ends[end - 1])


def _plain(m: re.Match) -> str | None:
    """ASCII form of one character; nothing for an invisible one, None where there is no such form."""
    c = m[0]
    if c in _LOOKALIKE:
        return _LOOKALIKE[c]
    if unicodedata.category(c) == "Cf":
        return ""
    digit = unicodedata.decimal(c, None)
    if digit is not None:
        return str(digit)
    folded = unicodedata.normalize("NFKC", c)
    return folded if folded.isascii() else None


def _digits(run: re.Match) -> str | None:
    """Digits of a run in which at least three are spelled; None leaves other runs as they are."""
    parts = list(_DIGIT_WORD.finditer(run[0]))
    if sum(m[2] is not None for m in parts) < 3:
        return None
    out, times = [], 1
    for m in parts:
        if m[2]:
            out.append(_SPELLED[m[2].lower()] * times)
        elif not m[5]:
            out.append("+" if m[1] else m[3] or ("." if m[4] else ""))
        if m[0].isalnum():
            times = _TIMES[m[5].lower()] if m[5] else 1
    return "".join(out)


def _shaped(run: re.Match) -> str | None:
    """The run with letters read as digits, if most of it are digits and some are not."""
    digits, letters = sum(c.isdigit() for c in run[0]), sum(c.isalpha() for c in run[0])
    return run[0].translate(_SHAPES) if letters and digits > 2 * letters else None


def _mark(m: re.Match) -> str:
    return "@" if m["at"] else "."


def _joined(m: re.Match) -> str:
    return f"{m[1]}@{m[3]}{re.sub(f'(?i){re.escape(m[2])}dot{re.escape(m[2])}', '.', m[4])}"


def _one_sided(m: re.Match) -> str | None:
    """Prose says that somebody looks at a site; a name with a mark or a digit in it is no plain word."""
    local = _LOCAL_END.search(m.string, max(0, m.start() - 64), m.start())
    return "@" if local and re.search("[A-Za-z]", local[0]) and re.search(r"[A-Za-z0-9][._+0-9][A-Za-z0-9]|[0-9]$", local[0]) else None


def rewritten(text: str) -> Rewriting | None:
    """The text behind its disguises, or None where no transducer changes anything."""
    now = first = Rewriting(text)
    if not text.isascii():
        now = now.replace(_STRANGE, _plain)
    now = now.replace(_DIGIT_RUN, _digits).replace(_MIXED_RUN, _shaped)
    now = now.replace(_CODED, _mark).replace(_JOINED, _joined).replace(_BRACKETS, _mark)
    now = now.replace(_SPOKEN, _mark).replace(_ONE_SIDED, _one_sided)
    return None if now is first else now


class Taken:
    """Spans that don't overlap, in order."""

    def __init__(self):
        self.starts: list[int] = []
        self.ends: list[int] = []

    def touching(self, start: int, end: int) -> tuple[int, int]:
        """Numbers of the first span that overlaps and of the one behind the last."""
        return bisect_right(self.ends, start), bisect_left(self.starts, end)

    def add(self, start: int, end: int) -> None:
        a, b = self.touching(start, end)
        if a < b:  # spans of the plain detectors may overlap across kinds: one wide span stands for them
            start, end = min(start, self.starts[a]), max(end, self.ends[b - 1])
        self.starts[a:b], self.ends[a:b] = [start], [end]


def find(text: str) -> tuple[dict[str, list[Span]], dict[str, list[Span]]]:
    """Spans by kind: those of the text as it is, and those added behind disguises."""
    base = {kind: list(detect(text)) for kind, detect in DETECTORS.items()}
    added: dict[str, list[Span]] = {kind: [] for kind in KINDS}
    behind = rewritten(text)
    if behind is not None:
        plain, taken = Taken(), Taken()
        for start, end in sorted(s for spans in base.values() for s in spans):
            plain.add(start, end)
        for kind, detect in DETECTORS.items():
            for a, b in detect(behind.text):
                start, end = behind.source(a, b)
                if text[start:end] == behind.text[a:b] or not _likely(kind, behind.text[a:b]):
                    continue
                first, last = plain.touching(start, end)
                wider = first == last or (start <= plain.starts[first] and plain.ends[last - 1] <= end and (last - first > 1 or (start, end) != (plain.starts[first], plain.ends[first])))
                first, last = taken.touching(start, end)
                if wider and first == last:
                    added[kind].append((start, end))
                    taken.add(start, end)
    return base, added


def _likely(kind: str, match: str) -> bool:
    """A rewritten address must end in letters, as top-level domains do."""
    return kind != "email" or re.search(r"\.[A-Za-z]{2,}$", match) is not None


def listed(spans: dict[str, list[Span]]) -> str:
    return ",".join(f"{kind}:{a}:{b}" for kind in KINDS for a, b in sorted(spans[kind]))


def personal_data(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """id, n_email, n_ip, n_card, n_phone (of the text as it is), n_added, base_sha256 and spans of each row; narrow."""
    counts = [f"n_{kind}" for kind in KINDS]
    schema = fields(docs, [id_column], *((c, "long") for c in [*counts, "n_added"]), ("base_sha256", "string"), ("spans", "string"))

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        look = process_cache("pii.find", lambda: find)
        for batch in batches:
            columns: list[list] = [[] for _ in range(len(KINDS) + 3)]
            for text in batch.column(1):
                base, added = look(text.as_py() or "")
                row = [*(len(base[k]) for k in KINDS), sum(map(len, added.values())), hashlib.sha256(listed(base).encode()).hexdigest(), listed({k: base[k] + added[k] for k in KINDS})]
                for column, value in zip(columns, row):
                    column.append(value)
            kinds = [pa.int64()] * (len(KINDS) + 1) + [pa.string()] * 2
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, t) for c, t in zip(columns, kinds))], names=[id_column, *counts, "n_added", "base_sha256", "spans"])

    return docs.select(column(id_column), column(text_column)).transform(arrow_map, scan, schema)
