"""Personal data in whole texts, plain and disguised.

Base patterns run on the text as it is. Disguises are undone by a chain of transducers, each of
which rewrites its input and keeps, for every character that it writes, the span of source
characters that it stands for: look-alike characters and full-width forms become ASCII, invisible
ones go, spelled digits become digits, and at/dot phrases become signs. What the patterns find in
the rewritten text is mapped back to source spans. Such a span is added if it holds a rewritten
character and each base span of its kind that it overlaps is a part of it and shorter.

Offsets are code points, ends exclusive. Null and empty texts hold nothing. Rows are searched one
by one, so repeated rows give repeated results. An empty table gives no row. Columns but doc_id and
text are not read.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from strel.llm.encode import each
from strel.runtime import ship

KINDS = ("email", "ip", "card", "phone")

# The base patterns.
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])[0-9]+(?:\.[0-9]+){3}")
_CARD = re.compile(r"[0-9](?:[ -]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")

_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DIGIT = re.compile("[0-9]")
_DIGITS = re.compile("[0-9]+")


def luhn(digits: str) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if k % 2:
            d = d * 2 - 9 * (d > 4)
        total += d
    return total % 10 == 0


def _emails(t: str) -> list[tuple[int, int]]:
    """Each match has one @: its local part runs back from it, its domain ahead."""
    out, free, at = [], 0, t.find("@")
    while at >= 0:
        s = at
        while s > free and t[s - 1] in _LOCAL:
            s -= 1
        m = _DOMAIN.match(t, at + 1) if s < at else None
        free = m.end() if m else at + 1
        if m:
            out.append((s, free))
        at = t.find("@", free)
    return out


def find_base(t: str) -> dict[str, list[tuple[int, int]]]:
    """Leftmost, non-overlapping matches of each kind that pass its checks."""
    out: dict[str, list[tuple[int, int]]] = {k: [] for k in KINDS}
    if "@" in t:
        out["email"] = _emails(t)
    if not _DIGIT.search(t):
        return out
    if "." in t:
        out["ip"] = [m.span() for m in _IP.finditer(t) if all(len(p.lstrip("0")) <= 3 and int(p[-3:] if len(p) > 3 else p) <= 255 for p in m.group().split("."))]
    for m in _CARD.finditer(t):
        if m.end() - m.start() >= 16:
            d = "".join(_DIGITS.findall(m.group()))
            if 16 <= len(d) <= 19 and luhn(d):
                out["card"].append(m.span())
    if "+" in t:
        out["phone"] = [m.span() for m in _PHONE.finditer(t) if 8 <= sum(map(len, _DIGITS.findall(m.group()))) <= 15]
    return out


# Look-alikes of ASCII letters and signs (full-width forms follow by rule).
_LOOKALIKE = dict(
    zip(
        "аеорсухіјѕһԁԛԝАВЕКМНОРСТХІЈЅοανΑΒΕΖΗΙΚΜΝΟΡΤΥΧıɡ․。﹫‐‑‒–−⁄",
        "aeopcyxijshdqwABEKMHOPCTXIJSoavABEZHIKMNOPTYXig..@-----/",
        strict=True,
    )
)
_LOOKALIKE |= {chr(0xFEE0 + c): chr(c) for c in range(33, 127)}  # full-width forms
_LOOKALIKE |= {chr(base + d): str(d) for base in (0x0660, 0x06F0, 0x0966, 0x1D7CE, 0x1D7D8, 0x1D7E2, 0x1D7EC, 0x1D7F6) for d in range(10)}
# Characters that leave no mark.
_INVISIBLE = "­​‌‍⁠﻿"
# Digits in words.
_SPELLED = {
    "zero": "0", "oh": "0", "one": "1", "two": "2", "three": "3", "four": "4", "five": "5", "six": "6", "seven": "7", "eight": "8", "nine": "9",
    "null": "0", "eins": "1", "zwei": "2", "drei": "3", "vier": "4", "fünf": "5", "sechs": "6", "sieben": "7", "acht": "8", "neun": "9",
    "un": "1", "deux": "2", "trois": "3", "quatre": "4", "cinq": "5", "sept": "7", "huit": "8", "neuf": "9",
    "cero": "0", "uno": "1", "dos": "2", "tres": "3", "cuatro": "4", "cinco": "5", "seis": "6", "siete": "7", "ocho": "8", "nueve": "9",
}
# Words for the signs.
_AT_WORD, _DOT_WORD = "at|arobase|arroba|klammeraffe", "dot|punkt|point|punto"

_HAS_LOOKALIKE = re.compile("[" + re.escape("".join(_LOOKALIKE) + _INVISIBLE) + "]")
_WORDS = "|".join(sorted(_SPELLED, key=len, reverse=True))
_NUMBER = rf"(?:(?:{_WORDS})(?!\w)|[0-9]+)"
_GAP = rf"(?:[ ().-]*(?<!\w)(?:{_DOT_WORD})[ .-]+|[ ().-]+)"
#: Numbers one after the other, of which at least one is spelled or which begin with a spelled plus.
_DIGIT_RUN = re.compile(rf"(?<!\w)(?:plus[ -]+|\+[ (-]*)?{_NUMBER}(?:{_GAP}{_NUMBER})+(?!\w)", re.I)
_PIECE = re.compile(rf"(?P<plus>plus[ -]+)|(?P<word>(?<!\w)(?:{_WORDS})(?!\w))|(?P<digits>[0-9]+)|(?P<dot>[ -]*(?<!\w)(?:{_DOT_WORD})(?!\w)[ -]*|\.)|(?P<gap>[ ()-]+)", re.I)
_SPELLED_NEAR = re.compile(rf"(?<!\w)(?:(?:{_WORDS}){_GAP}{_NUMBER}|plus[ -]+{_NUMBER})(?!\w)|[0-9]{_GAP}(?:{_WORDS})(?!\w)", re.I)
_MARK = r"[\[({{<]\s*(?:{})\s*[\])}}>]"
_AT = re.compile(r"(?<=[A-Za-z0-9_%+-])\s*" + _MARK.format(_AT_WORD + "|@|ät") + r"\s*(?=[A-Za-z0-9])", re.I)
_DOT = re.compile(r"(?<=[A-Za-z0-9])\s*" + _MARK.format(_DOT_WORD + r"|\.") + r"\s*(?=[A-Za-z0-9])", re.I)
_BARE = re.compile(rf"(?<![\w.@-])[A-Za-z0-9_%+-]+(?:(?:\.|\s(?:{_DOT_WORD})\s)[A-Za-z0-9_%+-]+)*(\s(?:{_AT_WORD})\s|@)(?:[A-Za-z0-9-]+(?:\.|\s(?:{_DOT_WORD})\s))+[A-Za-z][A-Za-z0-9-]*[A-Za-z0-9](?![\w@])", re.I)
_BARE_AT, _BARE_DOT = re.compile(rf"\s(?:{_AT_WORD})\s", re.I), re.compile(rf"\s(?:{_DOT_WORD})\s", re.I)
_BARE_IP = re.compile(rf"(?<![0-9.])[0-9]{{1,3}}(?:\s(?:{_DOT_WORD})\s[0-9]{{1,3}}){{3}}(?![0-9])", re.I)
_TRIGGER = re.compile(rf"[\[({{<]\s*(?:{_AT_WORD}|{_DOT_WORD}|@|\.|ät)\s*[\])}}>]|\s(?:{_DOT_WORD})\s|\s(?:{_AT_WORD})\s[A-Za-z0-9-]+\.[A-Za-z0-9-]", re.I)
#: What every bare address holds: a bare at-word before a dotted name, or a bare dot word.
_BARE_START = re.compile(rf"\s(?:{_DOT_WORD})\s|\s(?:{_AT_WORD})\s[A-Za-z0-9-]+\.[A-Za-z0-9-]", re.I)


class Aligned:
    """A rewritten text; each of its characters knows its source span and whether it was rewritten."""

    def __init__(self, text: str):
        self.text = text
        self.begin = list(range(len(text)))
        self.end = list(range(1, len(text) + 1))
        self.new = [False] * len(text)

    def rewrite(self, edits: list[tuple[int, int, str]]) -> None:
        """Replaces the given spans, in rising order and apart from each other."""
        if not edits:
            return
        text, begin, end, new, at = [], [], [], [], 0
        for a, b, to in [*edits, (len(self.text), len(self.text), "")]:
            text.append(self.text[at:a])
            begin += self.begin[at:a]
            end += self.end[at:a]
            new += self.new[at:a]
            if to:
                text.append(to)
                begin += [self.begin[a]] * len(to)
                end += [self.end[b - 1]] * len(to)
                new += [True] * len(to)
            elif b > a and new:
                new[-1] = True
            at = b
        self.text, self.begin, self.end, self.new = "".join(text), begin, end, new

    def source(self, a: int, b: int) -> tuple[int, int]:
        return self.begin[a], self.end[b - 1]


def _inner(outer: re.Pattern, *parts: tuple[re.Pattern, str]):
    def edits(t: str) -> list[tuple[int, int, str]]:
        found = [(m.start() + a.start(), m.start() + a.end(), to) for m in outer.finditer(t) for p, to in parts for a in p.finditer(m.group())]
        return sorted(found)

    return edits


def _spelled(t: str) -> list[tuple[int, int, str]]:
    """Spelled digits and the words for signs between them, wherever a pattern could hold them."""
    if not _SPELLED_NEAR.search(t):
        return []
    out: list[tuple[int, int, str]] = []
    for r in _DIGIT_RUN.finditer(t):
        pieces = [(m.lastgroup, r.start() + m.start(), r.start() + m.end()) for m in _PIECE.finditer(r.group())]
        kinds = [k for k, _, _ in pieces]
        ends = [k for k in range(2, len(pieces)) if kinds[k] == "word" and _begins(t, pieces[k]) and _parted(t, pieces, k)]
        for a, b in zip([0, *ends], [*ends, len(pieces)], strict=True):
            if "word" in kinds[a:b] or "plus" in kinds[a:b]:
                out += _numbers(t, pieces[a:b])
    return out


def _begins(t: str, piece: tuple[str, int, int]) -> bool:
    """Whether a word is written like the first of a sentence."""
    return t[piece[1]].isupper() and t[piece[2] - 1].islower()


def _parted(t: str, pieces: list[tuple[str, int, int]], k: int) -> bool:
    """Whether a capital word after a full stop, or as the last one after digits, is of another sentence."""
    kinds = [x for x, _, _ in pieces[:k]]
    if kinds[-1] != "gap":
        return False
    if len(kinds) > 2 and kinds[-2] == "dot":
        return not _begins(t, pieces[k - 3])
    return k == len(pieces) - 1 and kinds[-2] == "digits"


def _numbers(t: str, pieces: list[tuple[str, int, int]]) -> list[tuple[int, int, str]]:
    """Edits of one run. Between dots of an address the digits close up."""
    groups: list[list[tuple[str, int, int]]] = [[]]
    dots: list[tuple[int, int]] = []
    for p in pieces:
        if p[0] == "dot":
            dots.append(p[1:])
            groups.append([])
        else:
            groups[-1].append(p)
    digits = [sum(b - a if k == "digits" else 1 for k, a, b in g if k in ("digits", "word")) for g in groups]
    # no pattern holds fewer digits: 8 of a phone, or four numbers with dots between them
    if sum(digits) < 8 and sum(n > 0 for n in digits) < 4:
        return []
    closed = _address(t, groups, dots, digits)
    out = []
    for k, g in enumerate(groups):
        for n, (kind, a, b) in enumerate(g):
            if kind == "word":
                out.append((a, b, _SPELLED[t[a:b].lower()]))
            elif kind == "plus":
                out.append((a, b, "+"))
            elif kind == "gap" and k in closed and 0 < n < len(g) - 1:
                out.append((a, b, ""))
        if k < len(dots) and t[slice(*dots[k])] != ".":
            out.append((*dots[k], "."))
    return out


def _address(t: str, groups: list, dots: list[tuple[int, int]], digits: list[int]) -> set[int]:
    """Groups, four in turn with a dot right between them, whose spelled digits make numbers of an IP."""
    tight = [not (groups[k] and groups[k][-1][0] == "gap") and not (groups[k + 1] and groups[k + 1][0][0] == "gap") for k in range(len(dots))]
    worded = [t[slice(*d)] != "." for d in dots]
    out: set[int] = set()
    k = 0
    while k + 4 <= len(groups):
        four = range(k, k + 4)
        mixed = [{"word", "digits"} <= {x[0] for x in groups[j]} for j in four]
        if all(0 < digits[j] <= 3 for j in four) and all(tight[k : k + 3]) and (any(worded[k : k + 3]) or not any(mixed)):
            out |= {j for j in four if any(x[0] == "word" for x in groups[j])}
            k += 4
        else:
            k += 1
    return out


def _bare(t: str) -> list[tuple[int, int, str]]:
    """Bare at and dot words of addresses; a sentence that begins right after a full stop is no ending."""
    out = []
    for m in _BARE.finditer(t) if _BARE_START.search(t) else ():
        last = re.search(r"([A-Za-z0-9-]+)\.([A-Za-z0-9-]+)$", m.group())
        if last and last[1][0].islower() and last[2][0].isupper() and last[2][1:].islower():
            continue
        parts = [(m.start() + a.start(), m.start() + a.end(), to) for p, to in ((_BARE_AT, "@"), (_BARE_DOT, ".")) for a in p.finditer(m.group())]
        out += sorted(parts)
    return out


#: The chain: each member gives the edits of its step.
_CHAIN = (
    lambda t: [(m.start(), m.end(), _LOOKALIKE.get(m.group(), "")) for m in _HAS_LOOKALIKE.finditer(t)],
    lambda t: [(*m.span(), "@") for m in _AT.finditer(t)],
    lambda t: [(*m.span(), ".") for m in _DOT.finditer(t)],
    _bare,
    _inner(_BARE_IP, (_BARE_DOT, ".")),
    _spelled,
)


def find_disguised(t: str, base: dict[str, list[tuple[int, int]]]) -> dict[str, list[tuple[int, int]]]:
    """Spans that only the rewritten text shows, by kind."""
    out: dict[str, list[tuple[int, int]]] = {k: [] for k in KINDS}
    if not (_TRIGGER.search(t) or (not t.isascii() and _HAS_LOOKALIKE.search(t)) or _SPELLED_NEAR.search(t)):
        return out
    plain = Aligned(t)
    for step in _CHAIN:
        plain.rewrite(step(plain.text))
    if not any(plain.new):
        return out
    for kind, spans in find_base(plain.text).items():
        for a, b in spans:
            s, e = plain.source(a, b)
            if any(plain.new[a:b]) and all(e <= x or s >= y or (s <= x and y <= e and (s, e) != (x, y)) for x, y in base[kind]):
                out[kind].append((s, e))
    return out


def _listed(spans: dict[str, list[tuple[int, int]]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k in KINDS for a, b in sorted(spans[k]))


def _task(batches: Iterator) -> Iterator:
    import pyarrow as pa

    for b in batches:
        cols: list[list] = [[] for _ in range(8)]
        for i, t in zip(each(b.column("doc_id")), each(b.column("text")), strict=True):
            t = t or ""
            base = find_base(t)
            more = find_disguised(t, base)
            both = {k: base[k] + more[k] for k in KINDS}
            row = [i, *(len(base[k]) for k in KINDS), hashlib.sha256(_listed(base).encode()).hexdigest(), _listed(both), sum(map(len, more.values()))]
            for c, v in zip(cols, row, strict=True):
                c.append(v)
        kinds = [pa.int64()] * 5 + [pa.string()] * 2 + [pa.int64()]
        names = ["doc_id", *(f"n_{k}" for k in KINDS), "base_sha256", "spans", "n_disguised"]
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names)


def find(docs: DataFrame) -> DataFrame:
    """Counts and spans of personal data in every text of ``docs`` (doc_id, text).

    Columns: doc_id; n_email, n_ip, n_card, n_phone (base matches); base_sha256 of the listed base
    spans; spans (base and disguised, ``kind:start:end`` joined by commas); n_disguised.
    """
    ship(docs.sparkSession)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(_task, "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_disguised long")
