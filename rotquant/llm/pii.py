"""Personal data, with disguises undone and places kept.

Plain identifiers are found in the source text. Where a text shows signs of disguise, small
transducers rewrite it and keep for every character of their output the source span it came
from: look-alike letters and full-width or other decimal digits become ASCII, bracketed or
spelled "at" and "dot" become their signs, and runs of spelled digits become digits.
Identifiers found in the output are mapped back to source spans; they are added where they
overlap no plain one.

Offsets are in code points, ends exclusive. Defined cases: a null text is empty; empty texts
have no span; repeated rows each give a row; very long texts are scanned whole; an empty
table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import re
import unicodedata
from bisect import bisect_left
from itertools import accumulate

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_slices, table
from .spans import digests

KINDS = ("email", "ip", "card", "phone")

_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")  # a match begins where a run of digits does; runs are taken whole
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_DIGIT = re.compile(r"[0-9]")


def luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        v = ord(d) - 48
        if i % 2:
            v = v * 2 - 9 * (v > 4)
        total += v
    return total % 10 == 0


def emails(text: str) -> list[tuple[int, int]]:
    """Leftmost matches, each found from its @ sign, so long words cost nothing."""
    out, floor = [], 0
    at = text.find("@")
    while at >= 0:
        a = at
        while a > floor and text[a - 1] in _LOCAL:
            a -= 1
        m = _DOMAIN.match(text, at + 1) if a < at else None
        if m:
            out.append((a, m.end()))
            floor = m.end()
        at = text.find("@", max(at + 1, floor))
    return out


def plain(text: str) -> list[tuple[int, str, int]]:
    """(start, kind, end) of the identifiers that stand in text as they are."""
    found = [(a, "email", b) for a, b in emails(text)]
    if _DIGIT.search(text):
        for m in _IP.finditer(text):
            if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in m[0].split(".")):
                found.append((m.start(), "ip", m.end()))
        for m in _CARD.finditer(text):
            if m.end() - m.start() >= 14:
                d = m[0].replace(" ", "").replace("-", "")
                if 14 <= len(d) <= 19 and luhn(d):
                    found.append((m.start(), "card", m.end()))
        if "+" in text:
            for m in _PHONE.finditer(text):
                if 10 <= sum(c.isdigit() for c in m[0]) <= 15:
                    found.append((m.start(), "phone", m.end()))
    return found


#: Letters that look like ASCII letters, as pairs.
LOOKALIKES = (
    "аa еe оo рp сc уy хx іi јj ѕs һh ԁd ԛq ԝw ӏl АA ВB ЕE КK МM НH ОO РP СC ТT ХX ІI ЈJ ЅS "
    "αa οo ρp νv ιi κk τt υu χx ΑA ΒB ΕE ΖZ ΗH ΙI ΚK ΜM ΝN ΟO ΡP ΤT ΥY ΧX ɡg ıi"
)
#: Names of the digits, in English, German, French and Spanish.
SPELLED = {
    "zero": "0", "oh": "0", "one": "1", "two": "2", "three": "3", "four": "4", "five": "5", "six": "6", "seven": "7", "eight": "8", "nine": "9",
    "null": "0", "eins": "1", "zwei": "2", "drei": "3", "vier": "4", "fünf": "5", "sechs": "6", "sieben": "7", "acht": "8", "neun": "9",
    "zéro": "0", "un": "1", "deux": "2", "trois": "3", "quatre": "4", "cinq": "5", "sept": "7", "huit": "8", "neuf": "9",
    "cero": "0", "uno": "1", "dos": "2", "tres": "3", "cuatro": "4", "cinco": "5", "seis": "6", "siete": "7", "ocho": "8", "nueve": "9",
}
_LOOK = {p[0]: p[1] for p in LOOKALIKES.split()}
_IGNORED = frozenset("​‌‍⁠﻿­")
#: Characters that may need rewriting: anything outside ASCII and the Latin letters of the texts.
_ODD = re.compile(r"[^\x00-\x7fÀ-ÖØ-öø-ÿ]")
_SIGNS = re.compile(  # blanks before a sign are entered at their first only
    r"(?<!\x20)[\x20]*(?:[\[({<][\x20]*(?:(at|@|arroba|ät)|(dot|punkt|point|punto|\.))[\x20]*[\])}>])[\x20]*"
    r"|(?<=[A-Za-z0-9_-])[\x20]+(at|AT)[\x20]+(?=[A-Za-z0-9-]+(?:[\x20]+(?:dot|DOT)[\x20]+|[\x20]*[\[({<][\x20]*dot|\.[A-Za-z]))"
    r"|(?<=[A-Za-z0-9-])[\x20]+(dot|DOT)[\x20]+(?=[A-Za-z0-9])",
    re.I,
)
_RUN = re.compile(r"(?<!\w)(?:(?:plus)[\s,-]+)?(?:(?:" + "|".join(sorted(SPELLED, key=len, reverse=True)) + r"|[0-9]+|dot|point)(?:[\s,./-]+|(?!\w))){4,}", re.I)
_RUN_SIGN = re.compile(r"(?<!\w)(?:" + "|".join(sorted(SPELLED, key=len, reverse=True)) + r")[\s,./-]+(?:(?:dot|point)[\s,./-]+)?(?:" + "|".join(SPELLED) + r"|[0-9])(?!\w)", re.I)


class Traced:
    """A text and, for each of its characters, the source span it stands for."""

    def __init__(self, text: str, starts: list[int] | None = None, ends: list[int] | None = None):
        self.text = text
        self.starts = list(range(len(text))) if starts is None else starts
        self.ends = list(range(1, len(text) + 1)) if ends is None else ends

    def rewritten(self, changes: list[tuple[int, int, str]]) -> Traced:
        """With each (start, end, new) replaced; a new text stands for the whole old span."""
        if not changes:
            return self
        text, starts, ends, at = [], [], [], 0
        for a, b, new in changes:
            text += [self.text[at:a], new]
            starts += self.starts[at:a] + [self.starts[a]] * len(new)
            ends += self.ends[at:a] + [self.ends[b - 1]] * len(new)
            at = b
        return Traced("".join([*text, self.text[at:]]), starts + self.starts[at:], ends + self.ends[at:])

    def source(self, a: int, b: int) -> tuple[int, int]:
        return self.starts[a], self.ends[b - 1]


def fold_characters(t: Traced) -> Traced:
    changes = []
    for m in _ODD.finditer(t.text):
        ch = m[0]
        if ch in _IGNORED:
            changes.append((m.start(), m.end(), ""))
        elif ch in _LOOK:
            changes.append((m.start(), m.end(), _LOOK[ch]))
        elif (d := unicodedata.decimal(ch, None)) is not None:
            changes.append((m.start(), m.end(), str(d)))
        elif len(n := unicodedata.normalize("NFKC", ch)) == 1 and n.isascii():
            changes.append((m.start(), m.end(), n))
    return t.rewritten(changes)


def fold_signs(t: Traced) -> Traced:
    changes = []
    for m in _SIGNS.finditer(t.text):
        before, after = t.text[m.start() - 1 : m.start()], t.text[m.end() : m.end() + 1]
        if before.isalnum() and after.isalnum():
            changes.append((m.start(), m.end(), "@" if m[1] or m[3] else "."))
    return t.rewritten(changes)


_TOKEN = re.compile(r"\w+|[^\w\s]+|\s+")


def fold_digits(t: Traced) -> Traced:
    """Runs of four or more spelled or plain digits, with at least two spelled ones, as digits."""
    changes = []
    for m in _RUN.finditer(t.text):
        new, spelled, last = [], 0, m.start()
        for w in _TOKEN.finditer(m[0]):
            word = w[0].lower()
            if word in SPELLED:
                new.append((m.start() + w.start(), m.start() + w.end(), SPELLED[word]))
                spelled += 1
                last = m.start() + w.end()
            elif word in ("dot", "point"):
                new.append((m.start() + w.start(), m.start() + w.end(), "."))
            elif word == "plus":
                new.append((m.start() + w.start(), m.start() + w.end(), "+"))
            elif word.isdigit():
                last = m.start() + w.end()
            else:
                new.append((m.start() + w.start(), m.start() + w.end(), ""))
        if spelled >= 2:
            changes += [c for c in new if c[1] <= last]
    return t.rewritten(changes)


def disguised(text: str) -> list[tuple[int, str, int]]:
    """Source spans of the identifiers that only the rewritten text shows."""
    odd = _ODD.search(text) is not None
    signs = _SIGNS.search(text) is not None
    digits = _RUN_SIGN.search(text) is not None
    if not (odd or signs or digits):
        return []
    t = Traced(text)
    if odd:
        t = fold_characters(t)
        signs, digits = _SIGNS.search(t.text) is not None, _RUN_SIGN.search(t.text) is not None
    if digits:
        t = fold_digits(t)
    if signs:
        t = fold_signs(t)
    if t.text == text:
        return []
    out = []
    for a, kind, b in plain(t.text):
        s, e = t.source(a, b)
        if text[s:e] != t.text[a:b] and (kind != "email" or re.search(r"\.[A-Za-z]{2,}$", t.text[a:b])):
            out.append((s, kind, e))
    return out


def spans(text: str | None) -> tuple[list[tuple[int, str, int]], list[tuple[int, str, int]]]:
    """(plain spans, all spans), each in order of start and kind."""
    text = text or ""
    order = lambda x: (x[0], KINDS.index(x[1]))
    base = sorted(plain(text), key=order)
    more = apart(disguised(text), base)
    return base, sorted(base + more, key=order)


def apart(found: list[tuple[int, str, int]], base: list[tuple[int, str, int]]) -> list[tuple[int, str, int]]:
    """Those that overlap nothing of base, which is in order of start."""
    starts, reach = [a for a, _, _ in base], list(accumulate((b for _, _, b in base), max))
    return [x for x in found if not (i := bisect_left(starts, x[2])) or reach[i - 1] <= x[0]]


def joined(found: list[tuple[int, str, int]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for a, k, b in found)


def personal_data(docs: DataFrame) -> DataFrame:
    """doc_id, spans (array of start, kind, end, plain) of each row."""

    def start():
        def f(c):
            out = []
            for t in c["text"]:
                base, every = spans(t)
                own = set(base)
                out.append([{"start": a, "kind": k, "end": b, "plain": (a, k, b) in own} for a, k, b in every])
            return {"doc_id": c["doc_id"], "spans": out}

        return f

    kinds = "doc_id long, spans array<struct<start: long, kind: string, end: long, plain: boolean>>"
    return map_slices(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), kinds, start)


def op9_pii(spark, sf_dir: str) -> DataFrame:
    found = personal_data(table(spark, sf_dir, "documents", "doc_id", "text"))
    return digests(found, F.filter("spans", lambda s: s["plain"]), "spans", KINDS)
