"""Personal data: patterns on the raw text, then on a deobfuscated text whose characters remember their place.

Base spans are e-mail addresses, dotted quads, card numbers and phone numbers, each kind
leftmost and without overlaps; a match that fails its test (quad part over 255, card
length or check sum, phone length) is dropped.  A transducer then rewrites disguises:
full-width and look-alike letters and digits, zero-width characters, bracketed or
spelled "at" and "dot" in addresses and between digits, and spelled digits in runs or beside
digits.  Every character it writes carries the span of
source characters it came from, so a match in the rewritten text maps back exactly.
Matches there that overlap no base span, or strictly contain the ones they overlap, are
added, provided they touch a rewritten place or no base span; base spans always stay.
Patterns start once per run of characters and give none back, and addresses grow from their "at",
so time is linear in the text, whatever it holds.

Null and empty texts have no spans.  Offsets are code points, ends exclusive.  Texts
of any length are read whole.  Rows are judged one by one, so ties and repeated rows
agree; other columns are not read.
"""

from __future__ import annotations

import hashlib
import re
from bisect import bisect_left
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ship, table

# Kinds in order, and their patterns.
KINDS = ("email", "ip", "card", "phone")
EMAIL_TAIL = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
#: The contract's pattern, tried once per run of digits: from within a run it finds nothing that it does not find from the run's start.
IP = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++")
CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DIGITS = re.compile(r"[^0-9]")

# Look-alikes of Latin letters and digits in other scripts.
LOOKALIKES = {
    "а": "a", "А": "A", "В": "B", "с": "c", "С": "C", "ԁ": "d", "е": "e", "Е": "E", "Н": "H", "һ": "h", "і": "i", "І": "I", "ј": "j", "К": "K",
    "ӏ": "l", "М": "M", "о": "o", "О": "O", "р": "p", "Р": "P", "ѕ": "s", "Ѕ": "S", "Т": "T", "у": "y", "х": "x", "Х": "X", "α": "a", "ο": "o", "Ο": "O",
    "ν": "v", "ρ": "p", "ι": "i", "։": ":", "․": ".", "。": ".", "﹒": ".", "﹫": "@", "‐": "-", "‑": "-", "–": "-", "﹣": "-", "－": "-", "\u00a0": " ", "\u2007": " ", "\u2009": " ", "\u202f": " ",
}
LOOKALIKES |= {chr(0xFF01 + i): chr(0x21 + i) for i in range(94)}
for _zero in (0x0660, 0x06F0, 0x0966, 0x1D7CE, 0x1D7D8, 0x1D7E2, 0x1D7EC, 0x1D7F6):
    LOOKALIKES |= {chr(_zero + i): str(i) for i in range(10)}
DROPPED = "\u00ad\u200b\u200c\u200d\u2060\ufeff"

# Spelled digits.
SPELLED = {
    "zero": "0", "oh": "0", "one": "1", "two": "2", "three": "3", "four": "4", "five": "5", "six": "6", "seven": "7", "eight": "8", "nine": "9",
    "null": "0", "eins": "1", "zwei": "2", "drei": "3", "vier": "4", "fünf": "5", "sechs": "6", "sieben": "7", "acht": "8", "neun": "9",
    "un": "1", "deux": "2", "trois": "3", "quatre": "4", "cinq": "5", "sept": "7", "huit": "8", "neuf": "9",
    "cero": "0", "uno": "1", "dos": "2", "tres": "3", "cuatro": "4", "cinco": "5", "seis": "6", "siete": "7", "ocho": "8", "nueve": "9",
}

_ODD = re.compile("[" + re.escape("".join(LOOKALIKES) + DROPPED) + "]")
_DOT_WORD = r"(?:dot|punkt|point|punto|\.)"
#: Disguises with the blanks around them; they start where no blank is before them, so a run of blanks is tried once.
_DOT = rf"(?<!\s)(?:\s*+[\[({{<]\s*+{_DOT_WORD}\s*+[\])}}>]\s*+|\s++dot\s++)"
_AT_OR = re.compile(r"(?<!\s)(?:(?P<marked>\s*+[\[({<]\s*+(?:at|@|arroba)\s*+[\])}>]\s*+)|(?P<bare>\s++at\s++)|\s*+@\s*+)", re.IGNORECASE)
_LABEL = r"[A-Za-z0-9-]++"
_HOST = re.compile(rf"{_LABEL}(?:(?:\.|{_DOT}){_LABEL})+", re.IGNORECASE)
_HOST_END = re.compile(r"\.[a-z]{2,}\Z")
_HINT_ADDRESS = re.compile(r"[\[({<]\s*+(?:at|@|arroba|dot|punkt|point|punto|\.)\s*+[\])}>]|\sdot\s|\sat\s++[a-z0-9-]++\.[a-z0-9]", re.IGNORECASE)
_DOTS = re.compile(_DOT, re.IGNORECASE)
_WORDS = "|".join(sorted(SPELLED, key=len, reverse=True))
#: Spelled and plain digits with separators between; a run counts when it has two tokens or more, one of them spelled.
_SPELLED_RUN = re.compile(rf"(?<!\w)(?:plus\s++|\+\s*+)?(?:(?:{_WORDS})(?!\w)|[0-9]++(?!\w))(?:(?:[\s()-]++|\.(?=\w)|(?<=[^\W\d_])[,.]\s*+)++(?:(?:{_WORDS})(?!\w)|[0-9]++(?!\w)))++", re.IGNORECASE)
_HINT_SPELLED = re.compile(rf"(?<!\w)(?:{_WORDS})(?!\w)", re.IGNORECASE)
#: A disguised dot between digits, spelled or not.
_DIGIT = rf"(?:(?<!\w)(?:{_WORDS})|[0-9])"
_DIGIT_DOT = re.compile(rf"(?:{_DOT}|(?<!\s)\s++(?:punkt|point|punto)\s++)(?=(?:{_WORDS})(?!\w)|[0-9])", re.IGNORECASE)
_DIGIT_BEFORE = re.compile(rf"{_DIGIT}\Z", re.IGNORECASE)
_HINT_DIGIT_DOT = re.compile(r"[\[({<]\s*+(?:dot|punkt|point|punto|\.)\s*+[\])}>]|\s(?:dot|punkt|point|punto)\s", re.IGNORECASE)
_ONE_SPELLED = re.compile(rf"(?<!\w)(?:{_WORDS})(?!\w)", re.IGNORECASE)
_SPELLED_TOKEN = re.compile(rf"plus(?=\s)|\+|{_WORDS}|[0-9]++", re.IGNORECASE)

Span = tuple[str, int, int]


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if i % 2:
            d = d * 2 - 9 * (d > 4)
        total += d
    return total % 10 == 0


def _emails(text: str) -> Iterator[tuple[int, int]]:
    """Leftmost matches, found from each @ backwards: a scan from every letter would be quadratic."""
    end, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > end and text[start - 1] in _LOCAL:
            start -= 1
        found = EMAIL_TAIL.match(text, start) if start < at else None
        if found:
            yield found.span()
            end = found.end()
        at = text.find("@", max(at + 1, end))


def _small(part: str) -> bool:
    part = part.lstrip("0")
    return len(part) <= 3 and int(part or 0) <= 255


def detect(text: str) -> list[Span]:
    """Spans of all kinds, by start, then kind as listed."""
    out: list[tuple[int, int, int]] = [(a, 0, b) for a, b in _emails(text)]
    out += [(m.start(), 1, m.end()) for m in IP.finditer(text) if all(map(_small, m.group().split(".")))]
    for m in CARD.finditer(text):
        if m.end() - m.start() >= 14 and 14 <= len(d := _DIGITS.sub("", m.group())) <= 19 and luhn(d):
            out.append((m.start(), 2, m.end()))
    if "+" in text:
        out += [(m.start(), 3, m.end()) for m in PHONE.finditer(text) if 10 <= len(_DIGITS.sub("", m.group())) <= 15]
    return [(KINDS[k], a, b) for a, k, b in sorted(out)]


class Tape:
    """A rewritten text; character i came from the source's characters first[i] to last[i] - 1."""

    def __init__(self, text: str, first: np.ndarray | None = None, last: np.ndarray | None = None):
        self.text, self.first, self.last = text, first, last

    @property
    def changed(self) -> bool:
        return self.first is not None

    def span(self, start: int, end: int) -> tuple[int, int]:
        return (start, end) if self.first is None else (int(self.first[start]), int(self.last[end - 1]))

    def rewrite(self, edits: list[tuple[int, int, str]]) -> Tape:
        """Replace spans by texts; a written character stands for the whole span it replaces."""
        if not edits:
            return self
        old = (np.arange(len(self.text)), np.arange(1, len(self.text) + 1)) if self.first is None else (self.first, self.last)
        parts, first, last, at = [], [], [], 0
        for start, end, new in [*edits, (len(self.text), len(self.text), "")]:
            parts += [self.text[at:start], new]
            first.append(old[0][at:start])
            last.append(old[1][at:start])
            if new:
                a, b = self.span(start, end)
                first.append(np.full(len(new), a))
                last.append(np.full(len(new), b))
            at = end
        return Tape("".join(parts), np.concatenate(first), np.concatenate(last))


def _address_edits(text: str) -> list[tuple[int, int, str]]:
    """Edits that undo disguised addresses: each "at" is looked at once, its host to the right, its user back to the left."""
    dots = {m.end(): m.start() for m in _DOTS.finditer(text)}
    edits, floor = [], 0
    for m in _AT_OR.finditer(text):
        host = _HOST.match(text, m.end())
        if host is None or m.start() < floor:
            continue
        user, at = [], m.start()
        while True:
            start = at
            while start > floor and text[start - 1] in _LOCAL:
                start -= 1
            if start == at:
                break
            at = start
            if at not in dots or dots[at] < floor:
                break
            user.append((dots[at], at, "."))
            at = dots[at]
        if at == m.start() or (user and at == user[-1][0]):
            user = user[:-1]
            if at == m.start():
                continue
        within = [(d.start(), d.end(), ".") for d in _DOTS.finditer(text, host.start(), host.end())]
        if user or within or m["marked"] or (m["bare"] and _HOST_END.search(host.group())):
            edits += [*reversed(user), (m.start(), m.end(), "@"), *within]
            floor = host.end()
    return edits


def deobfuscate(text: str) -> Tape:
    """Undo look-alikes, then disguised addresses, then spelled digits."""
    tape = Tape(text)
    if not text.isascii() and _ODD.search(text):
        tape = tape.rewrite([(m.start(), m.end(), LOOKALIKES.get(m.group(), "")) for m in _ODD.finditer(text)])
    if _HINT_ADDRESS.search(tape.text):
        tape = tape.rewrite(_address_edits(tape.text))
    if _HINT_DIGIT_DOT.search(tape.text):
        held = tape.text
        tape = tape.rewrite([(m.start(), m.end(), ".") for m in _DIGIT_DOT.finditer(held) if _DIGIT_BEFORE.search(held, max(0, m.start() - 8), m.start())])
    if _HINT_SPELLED.search(tape.text):
        edits = []
        for run in _SPELLED_RUN.finditer(tape.text):
            tokens = list(_SPELLED_TOKEN.finditer(tape.text, run.start(), run.end()))
            if all(m.group()[0] in "+0123456789" for m in tokens):
                continue
            last, long_before = None, False
            for m in tokens:
                long = len(m.group()) > 1 and m.group().isdigit()
                if last is not None and m.start() > last and not (long or long_before) and tape.text[last : m.start()] != ".":
                    edits.append((last, m.start(), ""))
                long_before = long
                word = m.group().lower()
                edits.append((m.start(), m.end(), "+" if word == "plus" else SPELLED.get(word, word)))
                last = m.end()
        tape = tape.rewrite(edits)
    return tape


def _prose(text: str, start: int, end: int, over: list[tuple[int, int]]) -> bool:
    """Whether a span goes beyond those it contains by a single spelled digit, which after a whole number is rather a word."""
    return bool(over) and len(_ONE_SPELLED.findall(text[start : over[0][0]] + " " + text[over[-1][1] : end])) == 1


def find(text: str | None) -> tuple[list[Span], list[Span]]:
    """(base spans, all spans) of a text."""
    text = text or ""
    base = detect(text)
    tape = deobfuscate(text)
    if not tape.changed:
        return base, base
    starts = [s for _, s, _ in base]
    reach = np.maximum.accumulate([e for *_, e in base]).tolist() if base else []
    more, upto = [], 0
    for kind, a, b in detect(tape.text):
        start, end = tape.span(a, b)
        over, i = [], bisect_left(starts, end) - 1
        while i >= 0 and reach[i] > start:
            if base[i][2] > start:
                over.append(base[i][1:])
            i -= 1
        over.reverse()
        inside = all(start <= s and e <= end and (s, e) != (start, end) for s, e in over)
        if inside and (not over or text[start:end] != tape.text[a:b]) and not _prose(text, start, end, over) and start >= upto:
            more.append((kind, start, end))
            upto = end
    return base, sorted([*base, *more], key=lambda x: (x[1], KINDS.index(x[0]), x[2]))


def written(spans: list[Span]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in spans)


_SCHEMA = "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_added long"


def scan(docs: DataFrame) -> DataFrame:
    """One row per document; counts are those of the base spans."""
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for doc_id, text in zip(batch["doc_id"].to_pylist(), batch["text"], strict=True):
                base, spans = find(text.as_py())
                rows.append((doc_id, *(sum(k == kind for k, _, _ in base) for kind in KINDS), hashlib.sha256(written(base).encode()).hexdigest(), written(spans), len(spans) - len(base)))
            kinds = (*[pa.int64()] * 5, pa.string(), pa.string(), pa.int64())
            columns = zip(*rows, strict=True) if rows else [[] for _ in kinds]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=[f.split()[0] for f in _SCHEMA.split(", ")])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, _SCHEMA)


def mask(text: str | None, spans: list[Span]) -> str:
    """The text with each span replaced by its kind in angle brackets; overlapping spans are replaced as one, by the first and longest's kind."""
    out, at = [], 0
    for kind, a, b in sorted(spans, key=lambda x: (x[1], -x[2])):
        if a >= at:
            out += [(text or "")[at:a], f"<{kind}>"]
        at = max(at, b)
    return "".join([*out, (text or "")[at:]])


def op9_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(table(spark, sf_dir, "documents"))
