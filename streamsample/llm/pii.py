"""Personal data in whole texts, plain and disguised, with spans in the source text.

Plain identifiers (email, ip, card, phone) are found in the text as it is. A text with signs of disguise also goes through a chain
of transducers, each of which rewrites parts of the text and carries for every character the source range it stands for: look-alike
characters become ASCII and invisible ones vanish, bracketed or spelled "at" and "dot" become @ and ., spelled digits become digits. The
same detectors then run over the normalised text, and what they find there is mapped back to source characters. A find counts only
if a rewritten character lies in it and no plain span of its kind holds it already.
"""

from __future__ import annotations

import hashlib
import re
from bisect import bisect_right
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import read, trim
from .tokens import text_parts

#: The kinds in the order that breaks ties.
KINDS = ("email", "ip", "card", "phone")

_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++")
_CARD = re.compile(r"(?<![0-9])[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_DIGIT = re.compile(r"[0-9]")


def luhn(digits: str) -> bool:
    odd = sum(map(int, digits[-1::-2]))
    even = sum(2 * d - 9 * (d > 4) for d in map(int, digits[-2::-2]))
    return (odd + even) % 10 == 0


def _emails(text: str) -> list[tuple[int, int]]:
    """Anchored at each @: the local part is the longest run before it, so every character is looked at a few times only."""
    found, last, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > last and text[start - 1] in _LOCAL:
            start -= 1
        m = _DOMAIN.match(text, at + 1) if start < at else None
        if m:
            last = m.end()
            found.append((start, last))
        else:
            last = at + 1
        at = text.find("@", last)
    return found


def plain_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind number, end) of what is in the text as it stands, sorted."""
    out = [(a, 0, b) for a, b in _emails(text)]
    if _DIGIT.search(text):
        if text.count(".") > 2:
            out += [(m.start(), 1, m.end()) for m in _IP.finditer(text) if all(len(d := p.lstrip("0")) < 4 and int(d or "0") <= 255 for p in m.group().split("."))]
        for m in _CARD.finditer(text):
            if m.end() - m.start() > 11:
                d = m.group().replace(" ", "").replace("-", "")
                if 12 <= len(d) <= 19 and luhn(d):
                    out.append((m.start(), 2, m.end()))
        if "+" in text:
            out += [(m.start(), 3, m.end()) for m in _PHONE.finditer(text) if 9 <= sum(c.isdigit() for c in m.group()) <= 15]
    return sorted(out)


#: Look-alikes of ASCII characters outside the ranges that a rule gives below.
_ALIKE = {
    "а": "a", "в": "b", "е": "e", "к": "k", "м": "m", "н": "h", "о": "o", "р": "p", "с": "c", "т": "t", "у": "y", "х": "x", "і": "i", "ј": "j", "ѕ": "s", "ԁ": "d", "ԛ": "q", "ԝ": "w", "һ": "h", "ӏ": "l",
    "А": "A", "В": "B", "Е": "E", "К": "K", "М": "M", "Н": "H", "О": "O", "Р": "P", "С": "C", "Т": "T", "У": "Y", "Х": "X", "І": "I", "Ј": "J", "Ѕ": "S",
    "α": "a", "ο": "o", "ρ": "p", "ν": "v", "ι": "i", "κ": "k", "Α": "A", "Β": "B", "Ε": "E", "Ζ": "Z", "Η": "H", "Ι": "I", "Κ": "K", "Μ": "M", "Ν": "N", "Ο": "O", "Ρ": "P", "Τ": "T", "Υ": "Y", "Χ": "X",
    "ı": "i", "ɑ": "a", "ɡ": "g", "﹫": "@", "․": ".", "。": ".", "｡": ".", "﹒": ".", "−": "-", "﹣": "-", " ": " ", " ": " ", " ": " ", "　": " ",
    "­": "", "​": "", "‌": "", "‍": "", "⁠": "", "﻿": "",
}
_ALIKE |= {chr(0xFEE0 + c): chr(c) for c in range(0x21, 0x7F)}  # full width forms
_ALIKE |= {chr(0x1D7CE + k): str(k % 10) for k in range(50)}  # mathematical digits
_ALIKE |= {chr(0x2010 + k): "-" for k in range(6)}
_ALIKE |= {chr(base + k): str(k) for base in (0x660, 0x6F0, 0x966) for k in range(10)}
_ODD = re.compile("[" + "".join(map(re.escape, _ALIKE)) + "]")

_AT = re.compile(r"[(\[{<]\s*(?:at|@)\s*[)\]}>]", re.I)
_DOT = re.compile(r"[(\[{<]\s*(?:dot|\.)\s*[)\]}>]", re.I)
_BRACKETED = re.compile(r"[(\[{<]\s*(?:at|dot|@|\.)\s*[)\]}>]", re.I)
#: A spelled address: "at" and perhaps "dot" as words with blanks about them; it starts at the first of the parts joined by dots.
_SPOKEN = re.compile(r"(?<![A-Za-z0-9._%+-])(?<![A-Za-z0-9._%+-] dot )[A-Za-z0-9._%+-]++(?:[ ]dot[ ][A-Za-z0-9._%+-]++)*+[ ]at[ ][A-Za-z0-9-]++(?:(?:[ ]dot[ ]|\.)[A-Za-z0-9-]++)++", re.I)
_SPOKEN_AT = re.compile(r"[ ]at[ ][A-Za-z0-9-]++(?:[ ]dot[ ]|\.)[A-Za-z0-9-]", re.I)
#: A domain written plainly after a spoken at ends in letters, unlike a price or a time.
_PLAIN_END = re.compile(r"\.[A-Za-z]{2,}\Z")
_SPOKEN_PART = re.compile(r"[ ](at|dot)[ ]", re.I)

#: Digits in words, English, German, Spanish and French.
_SPELLED = {
    "zero": "0", "oh": "0", "one": "1", "two": "2", "three": "3", "four": "4", "five": "5", "six": "6", "seven": "7", "eight": "8", "nine": "9",
    "null": "0", "eins": "1", "zwei": "2", "drei": "3", "vier": "4", "fünf": "5", "sechs": "6", "sieben": "7", "acht": "8", "neun": "9",
    "cero": "0", "uno": "1", "dos": "2", "tres": "3", "cuatro": "4", "cinco": "5", "seis": "6", "siete": "7", "ocho": "8", "nueve": "9",
    "zéro": "0", "un": "1", "deux": "2", "trois": "3", "quatre": "4", "cinq": "5", "sept": "7", "huit": "8", "neuf": "9",
}
_UNIT = "(?:" + "|".join(sorted(_SPELLED, key=len, reverse=True)) + r"|[0-9]+)"
_GAP = r"(?:[ ]dot[ ]|[ ]?\.[ ]?|[ ]*-[ ]*|[ ]+)"
_RUN = re.compile(rf"(?<!\w)(?:(?:plus[ ]|\+[ ]?))?{_UNIT}(?:{_GAP}{_UNIT}){{3,}}(?!\w)", re.I)
_RUN_PART = re.compile(rf"plus[ ]?|{_GAP}|{'|'.join(sorted(_SPELLED, key=len, reverse=True))}", re.I)
#: What makes a run one of spelled digits: any word in it.
_SAID = re.compile(rf"(?<!\w)(?:dot|plus|{'|'.join(sorted(_SPELLED, key=len, reverse=True))})(?!\w)", re.I)

_SPELLED_WORDS = frozenset(_SPELLED) | {"dot", "plus"}
_APART = str.maketrans("-.+", "   ")


class Tape:
    """A text with, for each character, the source range it stands for, and whether it was rewritten."""

    def __init__(self, text: str):
        self.text, self.lo = text, np.arange(len(text))
        self.hi, self.changed = self.lo + 1, np.zeros(len(text), dtype=bool)

    def rewrite(self, edits: list[tuple[int, int, str]]) -> None:
        """Replace [a, b) by a string, for each of the edits, which are sorted and don't overlap."""
        if not edits:
            return
        texts, lo, hi, changed, at = [], [], [], [], 0
        for a, b, new in edits:
            texts += [self.text[at:a], new]
            lo += [self.lo[at:a], np.full(len(new), self.lo[a])]
            hi += [self.hi[at:a], np.full(len(new), self.hi[b - 1])]
            changed += [self.changed[at:a], np.ones(len(new), dtype=bool)]
            if not new:  # what vanished still marks its neighbours
                if changed[-2].size:
                    changed[-2] = changed[-2].copy()
                    changed[-2][-1] = True
            at = b
        self.text = "".join(texts) + self.text[at:]
        self.lo, self.hi = np.concatenate([*lo, self.lo[at:]]), np.concatenate([*hi, self.hi[at:]])
        self.changed = np.concatenate([*changed, self.changed[at:]])


def _spelled_run(said: str) -> list[tuple[int, int, str]]:
    """Edits within a run of spelled digits: words to digits, gaps between digits vanish, dots stay dots."""
    edits = []
    for m in _RUN_PART.finditer(said):
        part = m.group().lower()
        new = "+" if part.startswith("plus") else _SPELLED.get(part)
        if new is None:
            new = "." if "." in part or "dot" in part else ""
        edits.append((m.start(), m.end(), new))
    return edits


def _with_blanks(pattern: re.Pattern, text: str, new: str) -> list[tuple[int, int, str]]:
    """Edits that put ``new`` for each match and the blanks and tabs about it; blanks between two matches go with the first. Every blank is looked at twice at most."""
    edits, last = [], 0
    for m in pattern.finditer(text):
        a, b = m.span()
        while a > last and text[a - 1] in " \t":
            a -= 1
        while b < len(text) and text[b] in " \t":
            b += 1
        edits.append((a, b, new))
        last = b
    return edits


def normalised(text: str) -> Tape | None:
    """The text after all transducers; None if nothing in it looks disguised."""
    tape = Tape(text)
    if not text.isascii():
        tape.rewrite([(m.start(), m.end(), _ALIKE[m.group()]) for m in _ODD.finditer(text)])
    low = tape.text.lower()
    if _BRACKETED.search(low):
        tape.rewrite(_with_blanks(_AT, tape.text, "@"))
        tape.rewrite(_with_blanks(_DOT, tape.text, "."))
        low = tape.text.lower()
    if " at " in low and _SPOKEN_AT.search(tape.text):
        edits = []
        for m in _SPOKEN.finditer(tape.text):
            parts = list(_SPOKEN_PART.finditer(m.group()))
            if parts[-1].group(1).lower() == "dot" or _PLAIN_END.search(m.group()):
                edits += [(m.start() + p.start(), m.start() + p.end(), "@" if p.group(1).lower() == "at" else ".") for p in parts]
        tape.rewrite(edits)
        low = tape.text.lower()
    edits = []
    words = low.translate(_APART).split()
    for m in _RUN.finditer(tape.text) if len(words) > 3 and not _SPELLED_WORDS.isdisjoint(words) else ():
        if _SAID.search(m.group()):
            edits += [(m.start() + a, m.start() + b, new) for a, b, new in _spelled_run(m.group())]
    tape.rewrite(edits)
    return tape if tape.changed.any() else None


def all_spans(text: str) -> tuple[list[tuple[int, int, int]], list[tuple[int, int, int]]]:
    """(plain spans, plain and added ones), each (start, kind number, end), sorted."""
    base = plain_spans(text)
    tape = normalised(text)
    if tape is None:
        return base, base
    known, extra = [[(a, b) for a, k, b in base if k == kind] for kind in range(4)], set()
    begins = [[a for a, _ in spans] for spans in known]
    for a, kind, b in plain_spans(tape.text):
        if tape.changed[a:b].any():
            x, y = int(tape.lo[a]), int(tape.hi[b - 1])
            at = bisect_right(begins[kind], x) - 1  # plain spans of a kind don't overlap: only the last one that begins before can hold it
            if at < 0 or known[kind][at][1] < y:
                extra.add((x, kind, y))
    return base, sorted([*base, *extra])


def said(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in spans)


def redacted(text: str, spans: list[tuple[int, int, int]]) -> str:
    """The text with each span, overlapping ones joined, replaced by the first one's kind in brackets."""
    out, at = [], 0
    joined: list[list[int]] = []
    for a, k, b in spans:
        if joined and a < joined[-1][2]:
            joined[-1][2] = max(joined[-1][2], b)
        else:
            joined.append([a, k, b])
    for a, k, b in joined:
        out += [text[at:a], f"[{KINDS[k].upper()}]"]
        at = b
    return "".join(out) + text[at:]


OUT = "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_added long"


def _find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        counts, sums, spans, added = [], [], [], []
        for text in (t for _, _, texts in text_parts(batch.column(1)) for t in texts):
            base, every = all_spans(text)
            counts.append([sum(k == kind for _, k, _ in base) for kind in range(4)])
            sums.append(hashlib.sha256(said(base).encode()).hexdigest())
            spans.append(said(every))
            added.append(len(every) - len(base))
        cols = [pa.array([c[k] for c in counts], pa.int64()) for k in range(4)]
        yield pa.RecordBatch.from_arrays(
            [batch.column(0), *cols, pa.array(sums, pa.string()), pa.array(spans, pa.string()), pa.array(added, pa.int64())],
            names=["doc_id", "n_email", "n_ip", "n_card", "n_phone", "base_sha256", "spans", "n_added"],
        )


def find(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_added) for each row of ``docs``.

    The counts and base_sha256 are of the plain spans, ``spans`` lists those and the added ones, n_added the number of the latter. Null and empty
    texts have none. Each row stands alone, so repeated rows and null ids do no harm. Other columns are not read.
    """
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(_find, OUT)


def redact(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """``docs``, all its columns and rows, with every span of its texts replaced by its kind. Null texts stay null."""
    names = docs.columns
    spot = names.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trim()  # what earlier tasks of this worker held
        for batch in batches:
            for a, b, texts in text_parts(batch.column(spot)):
                part, clean = batch.slice(a, b - a), []
                for text, null in zip(texts, part.column(spot).is_null().to_pylist(), strict=True):
                    spans = all_spans(text)[1]
                    clean.append(None if null else redacted(text, spans) if spans else text)
                columns = part.columns
                columns[spot] = pa.array(clean, columns[spot].type)
                yield pa.RecordBatch.from_arrays(columns, schema=batch.schema)
        trim()

    return docs.select(names).mapInArrow(run, docs.schema)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find(read(spark, sf_dir, "documents"))
