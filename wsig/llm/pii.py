"""Operator 10, personal data: e-mail addresses, IP addresses, card and phone numbers, plain or disguised.

Plain ones are found by fixed patterns over the whole text, in time linear in its length. For disguised ones a chain of
transducers rewrites the text - look-alike and full-width characters, spelled digits, at/dot disguises - and carries, for
every character that it writes, the source span that it stands for. The detectors run on the rewritten text, and what
they find is mapped back to source characters; a find that no rewriting took part in, or that touches a plain one, adds
nothing, unless it is of the same kind and reaches over it on a side: then the wider span stands beside the plain one.
Texts that hold nothing to rewrite skip the chain.

Spans are half-open and count code points of the original text. Null and empty texts have none. Rows are judged each for
itself: repeated rows, null ids and other columns change nothing. An empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import re
import unicodedata
from bisect import bisect_left, bisect_right
from itertools import accumulate

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wsig.llm.textscan import steps

KINDS = ("email", "ip", "card", "phone")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_CHAIN = re.compile(r"[0-9]+(?:\.[0-9]+)+")
_PART = re.compile(r"[0-9]+")
_CARD = re.compile(r"[0-9](?:[ -]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_DIGIT = re.compile(r"[0-9]")

Span = tuple[int, int, str]


def emails(text: str) -> list[Span]:
    out, done, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > done and text[start - 1] in _LOCAL:
            start -= 1
        domain = _DOMAIN.match(text, at + 1) if start < at else None
        if domain:
            done = domain.end()
            out.append((start, done, "email"))
        at = text.find("@", max(at + 1, done))
    return out


def ips(text: str) -> list[Span]:
    out = []
    for chain in _CHAIN.finditer(text):
        parts = [p.span() for p in _PART.finditer(text, chain.start(), chain.end())]
        for i in range(0, len(parts) - 3, 4):
            four = parts[i : i + 4]
            if all(len(x) <= 3 and int(x or 0) <= 255 for x in (text[a:b].lstrip("0") for a, b in four)):
                out.append((four[0][0], four[3][1], "ip"))
    return out


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if i % 2:
            d = d * 2 - 9 * (d > 4)
        total += d
    return total % 10 == 0


def cards(text: str) -> list[Span]:
    out = []
    for m in _CARD.finditer(text):
        digits = m.group().replace(" ", "").replace("-", "")
        if 12 <= len(digits) <= 19 and luhn(digits):
            out.append((*m.span(), "card"))
    return out


def phones(text: str) -> list[Span]:
    return [(*m.span(), "phone") for m in _PHONE.finditer(text) if 9 <= len(_DIGIT.findall(m.group())) <= 15]


def plain(text: str) -> list[Span]:
    """Spans of the fixed patterns, by start and then kind."""
    out = emails(text) if "@" in text else []
    if _DIGIT.search(text):
        out += ips(text) + cards(text) + (phones(text) if "+" in text else [])
    return ordered(out)


def ordered(spans: list[Span]) -> list[Span]:
    return sorted(spans, key=lambda s: (s[0], KINDS.index(s[2]), s[1]))


# Look-alikes of ASCII letters and marks, by alphabet.
_LOOKALIKES = {
    "аеорсухіјѕԁһӏԛԝв": "aeopcyxijsdhlqwb",
    "АВЕКМНОРСТУХІЈЅ": "ABEKMHOPCTYXIJS",
    "αονρικτυχ": "aovpiktux",
    "ΑΒΕΖΗΙΚΜΝΟΡΤΥΧ": "ABEZHIKMNOPTYX",
    "‐‑‒–—−": "------",
    "․。｡": "...",
    "ıɑɡ": "iag",
}
_DELETED = "­​‌‍⁠﻿"
_SPELLED = {
    "0": "zero oh null cero zéro",
    "1": "one eins uno un",
    "2": "two zwei zwo dos deux",
    "3": "three drei tres trois",
    "4": "four vier cuatro quatre",
    "5": "five fünf cinco cinq",
    "6": "six sechs seis",
    "7": "seven sieben siete sept",
    "8": "eight acht ocho huit",
    "9": "nine neun nueve neuf",
}

_ONE = {a: b for row, plain_row in _LOOKALIKES.items() for a, b in zip(row, plain_row)} | dict.fromkeys(_DELETED, "")
_DIGITS = {w: d for d, words in _SPELLED.items() for w in words.split()}
_WORD = "|".join(sorted(_DIGITS, key=len, reverse=True))
#: Four digit words on end at least, which prose doesn't hold by chance.
_RUN = re.compile(rf"(?<!\w)(?:(?:plus)[ \t-]+)?(?:{_WORD})(?:[ \t,.-]{{1,3}}(?:(?:dot|point|punkt|punto)[ \t]+)?(?:{_WORD}|[0-9])){{3,}}(?!\w)", re.I)
_TOKEN = re.compile(rf"(?<!\w)(?:plus|dot|point|punkt|punto|{_WORD}|[0-9])(?!\w)", re.I)
_BRACKET = r"[\(\[\{<] ?(?:%s) ?[\)\]\}>]"
_DOT_WORD = "dot|punkt|punto|point"
_ANY_DOT = rf"\s?(?:[ _](?:{_DOT_WORD})[ _]|{_BRACKET % (_DOT_WORD + '|[.]')}\s?)"
#: Endings that make a bare "at ... dot ..." an address; other endings need brackets, as "at the dot on" is prose.
_ENDINGS = "com|org|net|edu|gov|info|biz|io|eu|de|fr|es|uk|ch|nl|pl"
_AT = re.compile(rf"\s?{_BRACKET % '(?:at|ät|arroba|arobase|@)'}\s?|(?<=[A-Za-z0-9])[ _](?:at|arroba|arobase)[ _](?=[A-Za-z0-9.-]+(?:{_ANY_DOT}[A-Za-z0-9-]+)*?{_ANY_DOT}(?:{_ENDINGS})(?![A-Za-z0-9]))|\s@\s(?=[A-Za-z0-9])", re.I)
# Words before "at" and a site's name that are no mailbox.
_NO_MAILBOX = frozenset(
    "a all also and any anyone anything are arrive arrived article articles at available back based be been blog book books buy by call check click code data details download everyone everything file files find for form found free from go guide have here home hosted house how info information is it join just listed live located look looked looking "
    "made meet met more much news now on one online only open or order out over page pages people place posted project published read register registered report see seen sell sent services shop sign site sites sold some something source staff start started stay stop store stored story talk team that them there these things this those time today tool us used visit was watch we website were what when where which work worked working world you".split()
)
_BARE_AT = re.compile(rf"(?<![A-Za-z0-9._%+@-])([A-Za-z0-9][A-Za-z0-9._%+-]*) at (?=(?:[A-Za-z0-9-]+\.)+(?:{_ENDINGS})(?![A-Za-z0-9-]|\.[A-Za-z0-9]))")
_DOT = re.compile(rf"\s?{_BRACKET % (_DOT_WORD + '|[.]')}\s?|(?<=[A-Za-z0-9])[ _](?:{_DOT_WORD})[ _](?=[A-Za-z0-9])", re.I)
_STRANGE = re.compile("[­ıƀ-\U0010ffff]")
_SIGNS = (" at ", "dot", "punkt", "punto", "point", "(at", "[at", "{at", "<at", "( at", "[ at", "(@", "[@", "{@", "arroba", "arobase", " @ ", "[.]", "(.)", "{.}")


class Tape:
    """Rewritten text and, for each of its characters, the source span and whether it was changed."""

    def __init__(self, text: str):
        self.text = text
        self.starts = list(range(len(text)))
        self.ends = list(range(1, len(text) + 1))
        self.changed = bytearray(len(text))

    def rewrite(self, edits: list[tuple[int, int, str]]) -> None:
        """Replaces spans of the current text, ascending and apart; a written character stands for its whole span."""
        if not edits:
            return
        text, starts, ends, changed, done = [], [], [], bytearray(), 0
        for a, b, new in edits:
            text.append(self.text[done:a])
            starts += self.starts[done:a]
            ends += self.ends[done:a]
            changed += self.changed[done:a]
            text.append(new)
            starts += [self.starts[a]] * len(new)
            ends += [self.ends[b - 1]] * len(new)
            changed += b"\1" * len(new)
            done = b
        text.append(self.text[done:])
        self.text = "".join(text)
        self.starts = starts + self.starts[done:]
        self.ends = ends + self.ends[done:]
        self.changed = changed + self.changed[done:]

    def source(self, a: int, b: int) -> tuple[int, int] | None:
        """The source span of text[a:b], if something in it was rewritten or deleted."""
        at = self.starts[a], self.ends[b - 1]
        return at if 1 in self.changed[a:b] or at[1] - at[0] != b - a else None


def same_look(c: str) -> str | None:
    """What a character is read as, if that differs: ASCII for look-alikes, full-width and styled forms and digits."""
    if c in _ONE:
        return _ONE[c]
    if c < "ƀ":
        return None
    folded = unicodedata.normalize("NFKC", c)
    if len(folded) == 1 and folded.isascii():
        return folded
    digit = unicodedata.digit(c, None)
    return str(digit) if digit is not None else None


def _unglyph(tape: Tape) -> None:
    edits = []
    for m in _STRANGE.finditer(tape.text):
        new = same_look(m.group())
        if new is not None:
            edits.append((*m.span(), new))
    tape.rewrite(edits)


def _unspell(tape: Tape) -> None:
    edits = []
    for run in _RUN.finditer(tape.text):
        tokens = list(_TOKEN.finditer(tape.text, run.start(), run.end()))
        for i, t in enumerate(tokens):
            word = t.group().lower()
            new = "+" if word == "plus" else _DIGITS.get(word, word if word.isdigit() else ".")
            edits.append((t.start(), tokens[i + 1].start() if i + 1 < len(tokens) else t.end(), new))
    tape.rewrite(edits)


def _undisguise(tape: Tape) -> None:
    for pattern, new in ((_AT, "@"), (_DOT, ".")):
        tape.rewrite([(*m.span(), new) for m in pattern.finditer(tape.text)])
    tape.rewrite([(m.end(1), m.end(), "@") for m in _BARE_AT.finditer(tape.text) if m.group(1).lower() not in _NO_MAILBOX])


_ALL_SPELLED = re.compile(r"(?<![0-9+.])[0-9]{9,15}(?![0-9])")


def disguised(text: str, known: list[Span]) -> list[Span]:
    """Spans that appear only after rewriting, none touching each other, nor a known one unless they widen it."""
    strange = not text.isascii() and _STRANGE.search(text)
    tape = Tape(text) if strange else None
    if strange:
        _unglyph(tape)
    low = (tape.text if tape else text).lower()
    spelled, signs = _RUN.search(low), any(s in low for s in _SIGNS)
    if tape is None and not (spelled or signs):
        return []
    tape = tape or Tape(text)
    if spelled:
        _unspell(tape)
    if signs:
        _undisguise(tape)
    found = plain(tape.text)
    if spelled:
        found += [(*m.span(), "phone") for m in _ALL_SPELLED.finditer(tape.text) if all(tape.changed[m.start() : m.end()])]
    known = sorted(known)
    starts, reach = [a for a, _, _ in known], list(accumulate((b for _, b, _ in known), max))
    taken: list[tuple[int, int]] = []  # apart and ascending
    out: list[Span] = []
    for a, b, kind in sorted(found, key=lambda s: (KINDS.index(s[2]), s[0])):
        at = tape.source(a, b)
        if not at:
            continue
        touched = [s for s in known[bisect_right(reach, at[0]) : bisect_left(starts, at[1])] if s[1] > at[0]]
        if any(k != kind or x < at[0] or y > at[1] or (x, y) == at for x, y, k in touched):
            continue
        place = bisect_left(taken, at)
        if (place and taken[place - 1][1] > at[0]) or (place < len(taken) and taken[place][0] < at[1]):
            continue
        taken.insert(place, at)
        out.append((*at, kind))
    return out


def digest(spans: list[Span]) -> str:
    return ",".join(f"{kind}:{a}:{b}" for a, b, kind in spans)


def mask(text: str, spans: list[Span]) -> str:
    """The text with each stretch of overlapping spans replaced by its first span's kind in angle brackets."""
    out, done, i = [], 0, 0
    while i < len(spans):
        a, b, kind = spans[i]
        i += 1
        while i < len(spans) and spans[i][0] < b:
            b = max(b, spans[i][1])
            i += 1
        out += [text[done:a], f"<{kind.upper()}>"]
        done = b
    return "".join([*out, text[done:]])


def find(text: str) -> tuple[list[Span], list[Span]]:
    """Plain spans and all spans."""
    base = plain(text)
    return base, ordered(base + disguised(text, base))


def find_pii(docs: DataFrame) -> DataFrame:
    """doc_id, counts of plain spans by kind, their digest, all spans and the number of disguised ones, for each row."""

    def run(batches):
        for batch in steps(batches):
            rows = [find(t or "") for t in batch.column("text").to_pylist()]
            counts = [pa.array([sum(s[2] == kind for s in base) for base, _ in rows], pa.int64()) for kind in KINDS]
            sha = pa.array([hashlib.sha256(digest(base).encode()).hexdigest() for base, _ in rows])
            spans = pa.array([digest(every) for _, every in rows])
            more = pa.array([len(every) - len(base) for base, every in rows], pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *counts, sha, spans, more], ["doc_id", *(f"n_{k}" for k in KINDS), "base_sha256", "spans", "n_disguised"])

    schema = "doc_id long, " + ", ".join(f"n_{k} long" for k in KINDS) + ", base_sha256 string, spans string, n_disguised long"
    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, schema)


def mask_pii(docs: DataFrame) -> DataFrame:
    """``docs`` with personal data masked in ``text``; a null text stays null, and n_chars, if there, is counted anew."""
    at = docs.columns.index("text")

    def run(batches):
        for batch in steps(batches):
            new = pa.array([None if t is None else mask(t, find(t)[1]) for t in batch.column(at).to_pylist()], pa.string())
            yield batch.set_column(at, "text", new)

    out = docs.mapInArrow(run, docs.schema)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return out
