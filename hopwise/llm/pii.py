"""Personal data in texts, disguised or not, with spans in the source text.

Base identifiers (email, ip, card, phone) are found in the text as it is, leftmost and non-overlapping for
each kind; a match that fails its test (parts of an address over 255, digits of a card by Luhn, digits of a
phone) is dropped. Then transducers rewrite the text and keep, for every character written, the span of
source characters it stands for: full-width and other look-alike letters and digits become ASCII, invisible
characters vanish, spelled digits become digits (a run of three or more; one or two where an identifier that
passes its test needs them), and disguised marks become marks ("[at]", "(dot)", " at ... dot ..."). Identifiers are detected again in the rewritten
text, and their spans are mapped back. A span found so is added unless a span of its kind holds it already;
base spans stay, also inside a longer span that the method adds.

The transducers run on whole texts, but only where something can be found: a text without a look-alike, a
spelled digit run or a disguised mark is its own rewriting. Null is empty; an empty text has no span; the
empty list of spans has the digest of the empty string. Rows are independent: repeats, ties and extra columns
change nothing, an empty table gives an empty table.
"""

from __future__ import annotations

import hashlib
import re
import unicodedata
from collections.abc import Iterator
from itertools import groupby

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import id_as_string, id_back

# The patterns of the base identifiers.
KINDS = ("email", "ip", "card", "phone")
PATTERNS = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    "card": r"[0-9]([\x20-]?[0-9])+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: the same matches, found in time proportional to the text: no attempt starts inside a run that has failed already
_CARD, _PHONE = re.compile(PATTERNS["card"]), re.compile(PATTERNS["phone"])
_IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
_HOST = re.compile(r"[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++")
_NAME_CHARACTERS = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
#: what a text must hold for a kind to be looked for
_NEEDS = {"email": re.compile("@"), "ip": re.compile(r"[0-9]\.[0-9]+\."), "card": re.compile(r"[0-9](?:[\x20-]?[0-9]){15}"), "phone": re.compile(r"\+[0-9]")}
_DIGITS = re.compile("[0-9]")


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if i % 2:
            d = d * 2 - 9 if d > 4 else d * 2
        total += d
    return total % 10 == 0


def valid(kind: str, found: str) -> bool:
    if kind == "ip":
        return all(len(p.lstrip("0")) <= 3 and int(p) <= 255 for p in found.split("."))
    if kind == "card":
        digits = "".join(_DIGITS.findall(found))
        return 16 <= len(digits) <= 19 and luhn(digits)
    if kind == "phone":
        return 8 <= len(_DIGITS.findall(found)) <= 15
    return True


def emails(text: str) -> Iterator[tuple[int, int]]:
    """Spans of PATTERNS["email"]: from each @, back over the name and on over the host."""
    last, at = 0, text.find("@")
    while at >= 0:
        host = _HOST.match(text, at + 1)
        if host is not None:
            start = at
            while start > last and text[start - 1] in _NAME_CHARACTERS:
                start -= 1
            if start < at:
                last = host.end()
                yield start, last
        at = text.find("@", max(at + 1, last))


def matches(kind: str, text: str) -> Iterator[tuple[int, int]]:
    if kind == "email":
        return emails(text)
    return (m.span() for m in {"ip": _IP, "card": _CARD, "phone": _PHONE}[kind].finditer(text))


def base_spans(text: str) -> list[tuple[str, int, int]]:
    """(kind, start, end) by kind, then start."""
    out = []
    for kind in KINDS:
        if _NEEDS[kind].search(text):
            out += [(kind, s, e) for s, e in matches(kind, text) if valid(kind, text[s:e])]
    return out


class Rewritten:
    """A text with the source span of each of its characters: starts[i]..ends[i]."""

    __slots__ = ("text", "starts", "ends")

    def __init__(self, text: str, starts: np.ndarray, ends: np.ndarray):
        self.text, self.starts, self.ends = text, starts, ends

    @classmethod
    def of(cls, text: str) -> Rewritten:
        at = np.arange(len(text) + 1, dtype=np.int32)
        return cls(text, at[:-1], at[1:])

    def source(self, start: int, end: int) -> tuple[int, int]:
        return int(self.starts[start]), int(self.ends[end - 1])

    def replaced(self, edits: list[tuple[int, int, str]]) -> Rewritten:
        """``edits``: (start, end, new) in order, not overlapping. New characters stand for the whole edited span."""
        if not edits:
            return self
        text, starts, ends, last = [], [], [], 0
        for s, e, new in edits:
            text += [self.text[last:s], new]
            starts.append(self.starts[last:s])
            ends.append(self.ends[last:s])
            if e > s and new:
                starts.append(np.full(len(new), self.starts[s]))
                ends.append(np.full(len(new), self.ends[e - 1]))
            last = e
        text.append(self.text[last:])
        return Rewritten("".join(text), np.concatenate([*starts, self.starts[last:]]), np.concatenate([*ends, self.ends[last:]]))


# Letters of other scripts that look like ASCII letters, each string against the ASCII one below it.
_CYRILLIC = "аеорсухіјѕһԁԛԝкмтвнАВЕКМНОРСТУХІЈЅ"
_CYRILLIC_AS = "aeopcyxijshdqwkmtbhABEKMHOPCTYXIJS"
_GREEK = "οανρικτυχγΑΒΕΖΗΙΚΜΝΟΡΤΥΧ"
_GREEK_AS = "oavpiktuxyABEZHIKMNOPTYX"
_MARKS = "․﹒。．﹫＠＋‐‑‒–—−﹣－"
_MARKS_AS = "....@@+--------"
#: written but not seen
_UNSEEN = "­​‌‍⁠﻿"

HOMOGLYPHS = dict(zip(_CYRILLIC + _GREEK + _MARKS, _CYRILLIC_AS + _GREEK_AS + _MARKS_AS, strict=True)) | dict.fromkeys(_UNSEEN, "")
for _c in range(0xFF01, 0xFF5F):  # full width
    HOMOGLYPHS[chr(_c)] = chr(_c - 0xFEE0)
_LOOK = re.compile("[^\\x00-\\xAC\\xAE-\\u024F‘’“”…€]")  # the soft hyphen is in
#: a look-alike matters only in a run that also holds ASCII, a digit or a mark of an identifier
_RUN = re.compile(r"\S+")


def homoglyphs(x: Rewritten) -> Rewritten:
    """Look-alike letters, digits and marks as ASCII; letters only where they stand in one run with ASCII."""
    if not _LOOK.search(x.text):
        return x
    edits = []
    for run in _RUN.finditer(x.text):
        word = run[0]
        if not _LOOK.search(word):
            continue
        # a run wholly in another script is a word of that script
        letters = [c for c in word if c.isalpha()]
        mixed = any(c.isascii() for c in letters) or not letters or "@" in word or "＠" in word or "﹫" in word
        for i, c in enumerate(word, run.start()):
            if c.isascii():
                continue
            new = HOMOGLYPHS.get(c)
            if new is None and unicodedata.category(c) == "Nd":
                new = str(unicodedata.digit(c))
            if new is None and "MATHEMATICAL" in unicodedata.name(c, ""):
                plain = unicodedata.normalize("NFKC", c)
                new = plain if plain.isascii() and len(plain) == 1 else None
            if new is not None and (mixed or not c.isalpha()):
                edits.append((i, i + 1, new))
    return x.replaced(edits)


# Digits spelled in the four languages of the corpora at hand.
SPELLED = {
    "zero": "0", "oh": "0", "one": "1", "two": "2", "three": "3", "four": "4", "five": "5", "six": "6", "seven": "7", "eight": "8", "nine": "9",
    "null": "0", "eins": "1", "zwei": "2", "drei": "3", "vier": "4", "fünf": "5", "sechs": "6", "sieben": "7", "acht": "8", "neun": "9",
    "zéro": "0", "un": "1", "deux": "2", "trois": "3", "quatre": "4", "cinq": "5", "sept": "7", "huit": "8", "neuf": "9",
    "cero": "0", "uno": "1", "dos": "2", "tres": "3", "cuatro": "4", "cinco": "5", "seis": "6", "siete": "7", "ocho": "8", "nueve": "9",
}
_ONE = "|".join(sorted(SPELLED, key=len, reverse=True))
_UNIT = rf"(?:(?<!\w)(?:{_ONE})(?!\w)|[0-9]+)"
_PLUS = r"(?:\+|(?<!\w)plus(?!\w))"
#: a run of at least three units, one of them spelled, with separators of identifiers between
_RUN_OF_DIGITS = re.compile(rf"(?:{_PLUS}[ ]?)?{_UNIT}(?:[ ,./()-]{{0,3}}(?:(?<!\w)(?:dot|point|dash)(?!\w)[ ]?)?{_UNIT}){{2,}}", re.I)
_SPELLED = re.compile(rf"(?<!\w)(?:{_ONE})(?!\w)", re.I)
_JOIN = re.compile(rf"({_UNIT})|({_PLUS})|(?<!\w)(dot|point|dash)(?!\w)", re.I)


def spelled_digits(x: Rewritten) -> Rewritten:
    """Runs of spelled digits as digits without the spaces between; other runs stay."""
    if not _SPELLED.search(x.text):
        return x
    edits = []
    for run in _RUN_OF_DIGITS.finditer(x.text):
        n = len(_SPELLED.findall(run[0]))
        if n >= 3:
            edits += joined(x.text, run.start(), run.end())
        elif n:
            edits += identifying(x.text, run.start(), run.end())
    return x.replaced(edits)


def joined(text: str, start: int, end: int, tight: bool = True) -> list[tuple[int, int, str]]:
    """Edits that spell a run's digits and marks, and (``tight``) take out spaces and commas between."""
    edits, last = [], None
    for m in _JOIN.finditer(text, start, end):
        if tight and last is not None and m.start() > last:
            between = text[last : m.start()]
            if not between.strip(" ,"):
                edits.append((last, m.start(), ""))
        word = m[0].lower()
        new = SPELLED.get(word, "+" if m[2] else "." if word in ("dot", "point") else "-" if word == "dash" else None)
        if new is not None and new != m[0]:
            edits.append((m.start(), m.end(), new))
        last = m.end()
    return edits


def identifying(text: str, start: int, end: int) -> list[tuple[int, int, str]]:
    """The edits of a run with one or two spelled digits, if an identifier that passes its test needs one of them."""
    run = text[start:end]
    spelled = [m.span() for m in _SPELLED.finditer(run)]
    plain = base_spans(run)
    for tight in (False, True):
        edits = joined(run, 0, len(run), tight)
        x = Rewritten.of(run).replaced(edits)
        for _, s, e in base_spans(x.text):
            a, b = x.source(s, e)
            needed = [w for w in spelled if a <= w[0] and w[1] <= b]
            # a word before or behind what is an identifier without it is a word
            edge = any(w[0] == a or w[1] == b for w in needed) and any(a <= p and q <= b for _, p, q in plain)
            if needed and not edge:
                return [(start + p, start + q, new) for p, q, new in edits if a <= p and q <= b]
    return []


# Disguises of @ and of the dot.
_AT_WORD = r"(?:at|ät|arroba|arobase|chez|bei|klammeraffe)"
_DOT_WORD = r"(?:dot|punkt|point|punto|d0t)"
_O, _C = r"[\[({<]", r"[\])}>]"
#: in brackets, or set apart by marks
_AT_MARK = re.compile(rf"(?<!\s)\s*(?:{_O}\s*(?:{_AT_WORD}|@)\s*{_C}|(?<=[A-Za-z0-9])\s*[_*-]+\s*{_AT_WORD}\s*[_*-]+|&#0*64;|&commat;|%40)\s*", re.I)
_DOT_MARK = re.compile(rf"(?<!\s)\s*(?:{_O}\s*(?:{_DOT_WORD}|\.)\s*{_C}|(?<=[A-Za-z0-9])\s*[_*-]+\s*{_DOT_WORD}\s*[_*-]+|&#0*46;|&period;)\s*", re.I)
#: as plain words: only name AT host DOT end, in that order
_PLAIN = re.compile(rf"(?<![A-Za-z0-9._%+-])([A-Za-z0-9._%+-]{{1,64}}(?:\s+{_DOT_WORD}\s+[A-Za-z0-9_%+-]{{1,64}}){{0,3}})\s+{_AT_WORD}\s+([A-Za-z0-9-]{{1,63}}(?:(?:\s+{_DOT_WORD}\s+|\.)[A-Za-z0-9-]{{1,63}}){{0,4}}\s+{_DOT_WORD}\s+[A-Za-z]{{2,24}})(?![A-Za-z0-9-])", re.I)
_HALF = re.compile(rf"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]{{1,64}}(@|\s+@\s*|\s*@\s+|\s+{_AT_WORD}\s+)[A-Za-z0-9-]{{1,63}}((?:\s+{_DOT_WORD}\s+|\.)[A-Za-z0-9-]{{1,63}})+(?![A-Za-z0-9-])", re.I)
_DOT = re.compile(rf"(?<!\s)\s+{_DOT_WORD}\s+", re.I)
_HINT = re.compile(rf"(?<!\w){_AT_WORD}(?!\w)[^\n]{{1,200}}?(?<!\w){_DOT_WORD}(?!\w)|{_O}\s*(?:{_AT_WORD}|{_DOT_WORD}|@|\.)\s*{_C}|[_*-]{_AT_WORD}[_*-]|&#0*(?:64|46);|&commat;|&period;|%40|@[^\n]{{1,100}}?\s{_DOT_WORD}\s|[A-Za-z0-9] @|@ [A-Za-z0-9]|(?<!\w){_AT_WORD}\s+[A-Za-z0-9-]+\.[A-Za-z]", re.I)
#: top-level names after which "name at host.end" is taken for an address
_ENDS = re.compile(r"(?:\.|\s)(?:com|net|org|edu|gov|info|biz|io|co|de|fr|es|eu|uk|us|at|ch|example|test)$", re.I)


def at_and_dot(x: Rewritten) -> Rewritten:
    """Disguised @ and dots as marks; plain words only where the whole shape of an address stands."""
    if not _HINT.search(x.text):
        return x
    near = lambda m: 0 < m.start() and m.end() < len(x.text) and x.text[m.start() - 1].isalnum() and x.text[m.end()].isalnum()
    edits = [(m.start(), m.end(), "@") for m in _AT_MARK.finditer(x.text) if near(m)]
    edits += [(m.start(), m.end(), ".") for m in _DOT_MARK.finditer(x.text) if near(m)]
    edits.sort()
    x = x.replaced([e for i, e in enumerate(edits) if not i or e[0] >= edits[i - 1][1]])
    for pattern in (_PLAIN, _HALF):
        edits = []
        for m in pattern.finditer(x.text):
            if pattern is _HALF:
                if not (_ENDS.search(m[0]) or "@" in m[1]):
                    continue
                if "@" not in m[1] and not _DOT.search(m[0]) and not _ENDS.search(m[0]):
                    continue
                edits.append((m.start(1), m.end(1), "@"))
                edits += [(d.start(), d.end(), ".") for d in _DOT.finditer(x.text, m.end(1), m.end())]
            else:
                at = m.end(1)
                edits += [(d.start(), d.end(), ".") for d in _DOT.finditer(x.text, m.start(1), at)]
                edits.append((at, m.start(2), "@"))
                edits += [(d.start(), d.end(), ".") for d in _DOT.finditer(x.text, m.start(2), m.end())]
        x = x.replaced(sorted(edits))
    return x


def all_spans(text: str) -> tuple[list[tuple[str, int, int]], list[tuple[str, int, int]]]:
    """Base spans, and all spans: both by kind, then start."""
    base = base_spans(text)
    x = at_and_dot(spelled_digits(homoglyphs(Rewritten.of(text) if _suspect(text) else _SAME)))
    if x is _SAME or x.text == text:
        return base, base
    out = []
    for kind, spans in groupby(sorted([*base, *((k, *x.source(s, e)) for k, s, e in base_spans(x.text))], key=lambda f: KINDS.index(f[0])), key=lambda f: f[0]):
        out += outermost([f[1:] for f in spans], {f[1:] for f in base if f[0] == kind}, kind)
    return base, out


def outermost(spans: list[tuple[int, int]], base: set[tuple[int, int]], kind: str) -> list[tuple[str, int, int]]:
    """The spans of a kind, in order: those of ``base``, and others that no longer or earlier span holds."""
    out, reach = [], -1
    for s, e in sorted(set(spans), key=lambda x: (x[0], -x[1])):
        if (s, e) in base or e > reach:
            out.append((kind, s, e))
        reach = max(reach, e)
    return sorted(out, key=lambda x: x[1:])


_SAME = Rewritten.of("")


def _suspect(text: str) -> bool:
    if not text.isascii() and _LOOK.search(text):
        return True
    return bool(_SUSPECT.search(text))


_BETWEEN = r"[ ,./()-]{0,3}(?:(?:dot|point|dash)[ ]?)?"
#: something that a transducer could rewrite: an at and a dot on one line, a spelled digit beside a digit, or three spelled digits
_SUSPECT = re.compile(rf"{_HINT.pattern}|[0-9]{_BETWEEN}(?<!\w)(?:{_ONE})(?!\w)|(?<!\w)(?:{_ONE})(?!\w){_BETWEEN}[0-9]|(?:(?<!\w)(?:{_ONE})(?!\w)[ ,./()+-]{{0,3}}(?:[0-9 ,./()-]|(?:dot|point|dash)\s)*){{3}}", re.I)


def spans_text(spans: list[tuple[str, int, int]]) -> str:
    return ",".join(f"{k}:{s}:{e}" for k, s, e in spans)


def redacted(text: str, spans: list[tuple[str, int, int]]) -> str:
    """``text`` with each span replaced by its kind; overlapping spans are replaced as one, by the first's kind."""
    out, last = [], 0
    for s, e, kind in sorted((s, e, k) for k, s, e in spans):
        if s >= last:
            out += [text[last:s], f"<{kind.upper()}>"]
        last = max(last, e)
    out.append(text[last:])
    return "".join(out)


def find_pii(docs: DataFrame, redact: bool = False) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone, base_sha256 (base spans), spans and n_spans (all), and ``redacted`` if asked for."""

    def find(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            rows = []
            for text in frame["text"]:
                text = text or ""
                base, spans = all_spans(text)
                kinds = [k for k, _, _ in base]
                row = [*map(kinds.count, KINDS), hashlib.sha256(spans_text(base).encode()).hexdigest(), spans_text(spans), len(spans)]
                rows.append(row + [redacted(text, spans)] * redact)
            names = [*(f"n_{k}" for k in KINDS), "base_sha256", "spans", "n_spans", *["redacted"] * redact]
            out = pd.DataFrame(rows, columns=names)
            out.insert(0, "doc_id", frame["doc_id"].to_numpy())
            yield out

    counts = ", ".join(f"n_{k} long" for k in KINDS)
    schema = f"doc_id string, {counts}, base_sha256 string, spans string, n_spans long{', redacted string' * redact}"
    found = docs.select(id_as_string(docs, "doc_id"), "text").mapInPandas(find, schema)
    return found.withColumn("doc_id", id_back(docs, "doc_id"))


def redact_documents(docs: DataFrame, column: str = "text") -> DataFrame:
    """``docs`` with personal data in ``column`` replaced; null stays null. Only rows with a find are changed."""

    @F.pandas_udf("string")
    def clean(texts: pd.Series) -> pd.Series:
        return texts.map(lambda t: t if not t else redacted(t, all_spans(t)[1]))

    return docs.withColumn(column, clean(F.col(column)))
