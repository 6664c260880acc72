"""Licence scan: winnowed fingerprints pick candidates, banded alignment reports them.

Letters and digits of a template, lower-cased, give hashes of all runs of ``GRAM`` characters;
of every ``SPAN`` neighbours the least is kept. An inverted index leads from fingerprints to
templates and places. A text's own winnowed fingerprints look the index up; any run of
SPAN + GRAM - 1 characters that it shares with a template is found. Hits of a template near one
diagonal make a candidate, and a banded alignment of words decides how much of the template the
region covers and where it begins and ends in the source.

Texts are only mapped; the index is of fixed size (the templates given). Defined cases: null or
empty texts and templates match nothing; a repeated notice is reported at each place; repeated
documents each report; very long texts are scanned whole; overlapping matches are reported
once, by the template with most matching less missing characters; an empty table gives an empty result; other
columns are ignored.
"""

from __future__ import annotations

import re

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bytescan import KEY, KeyScan, windows
from .common import map_slices, table
from .licence_texts import TEMPLATES

GRAM = KEY  # bytes of a fingerprint, read as one integer
SPAN = 6
BAND = 12
COVERAGE = 0.8

_FOLD = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
_DROP = bytes(c for c in range(128) if not chr(c).isalnum())
_WORD = re.compile(r"[A-Za-z0-9]+(?:[.-][A-Za-z0-9]+)*|[^\W\d_]+")


def squeezed(text: str) -> bytes:
    """ASCII letters (lower-cased) and digits, and whatever is not ASCII."""
    return text.encode("utf-8", "surrogatepass").translate(_FOLD, _DROP)


def winnowed(data: bytes) -> np.ndarray:
    """Places of the fingerprints: in each window of SPAN hashes the least, the rightmost of equals."""
    h = windows(data) * np.uint64(0x9E3779B97F4A7C15)
    if len(h) <= SPAN:
        return np.array([len(h) - 1 - int(h[::-1].argmin())]) if len(h) else np.empty(0, dtype=np.int64)
    w = np.lib.stride_tricks.sliding_window_view(h, SPAN)
    return np.unique(np.arange(len(w)) + SPAN - 1 - w[:, ::-1].argmin(axis=1))


def aligned(a: list[str], b: list[str], shift: int, band: int = BAND) -> tuple[int, int, int]:
    """(words of a that match, first and last place in b) of the best alignment with
    b's place minus a's place within band of shift. Matches score 1, gaps and changes cost."""
    best, width = (0.0, 0, 0, 0), 2 * band + 1
    empty = (0.0, 0, -1, -1)
    row = [empty] * (width + 2)
    for i, word in enumerate(a):
        new = [empty] * (width + 2)
        for c in range(width):
            j = i + shift + c - band
            if not 0 <= j < len(b):
                continue
            d, up, left = row[c + 1], row[c + 2], new[c]  # changes, a's word alone, b's word alone
            if b[j] == word:
                x = (d[0] + 1, d[1] + 1, d[2] if d[2] >= 0 else j, j)
            else:
                x = (d[0] - 0.6, *d[1:])
            for y in (up, left):
                if y[0] - 0.6 > x[0]:
                    x = (y[0] - 0.6, *y[1:])
            new[c + 1] = x if x[0] > 0 else empty
            if x[0] > best[0]:
                best = x
        row = new
    return best[1], best[2], best[3]


class Templates:
    def __init__(self, texts: dict[str, str], coverage: float = COVERAGE):
        self.coverage = coverage
        self.names = [n for n, t in texts.items() if t and squeezed(t)]
        self.words = [[w.lower() for w in _WORD.findall(texts[n])] for n in self.names]
        self.chars = [[len(w) for w in ws] for ws in self.words]
        self.index: dict[bytes, list[tuple[int, int]]] = {}
        for k, n in enumerate(self.names):
            data = squeezed(texts[n])
            for p in winnowed(data).tolist():
                self.index.setdefault(data[p : p + GRAM], []).append((k, p))
        self.scan = KeyScan(list(self.index))

    def candidates(self, text: str) -> list[tuple[int, int]]:
        """(template, place of its first character among the squeezed characters)."""
        data = squeezed(text)
        hits = self.scan.find(data)  # winnowing is only done where some key occurs at all
        if not len(hits):
            return []
        hits = np.intersect1d(hits, winnowed(data))
        got: dict[int, list[int]] = {}
        for p in hits.tolist():
            for k, q in self.index[data[p : p + GRAM]]:
                got.setdefault(k, []).append(p - q)
        out = []
        for k, starts in got.items():
            last = None
            for s in sorted(starts):
                if last is None or s - last > BAND * 4:
                    out.append((k, s))
                last = s
        return out

    def matches(self, text: str | None) -> list[tuple[str, float, int, int]]:
        """(template, coverage, start, end) of each licence text found."""
        if not text or not (cands := self.candidates(text)):
            return []
        spans = [m.span() for m in _WORD.finditer(text)]
        words = [text[a:b].lower() for a, b in spans]
        before = np.concatenate(([0], np.cumsum([len(squeezed(w)) for w in words])))
        found = []
        for k, s in cands:
            own = self.words[k]
            first = int(np.searchsorted(before, s, side="left"))
            lo, hi = max(0, first - BAND), min(len(words), first + len(own) + BAND)
            n, a, b = aligned(own, words[lo:hi], first - lo)
            share = n / len(own)
            if n and share >= self.coverage:
                found.append((n, share, k, spans[lo + a][0], spans[lo + b][1]))
        found.sort(key=lambda x: (-sum(self.chars[x[2]]) * (2 * x[1] - 1), x[3], x[2]))  # characters that match, less those that miss
        kept: list[tuple] = []
        for x in found:
            if all(x[4] <= y[3] or y[4] <= x[3] for y in kept):
                kept.append(x)
        return sorted((self.names[k], share, a, b) for _, share, k, a, b in kept)


def licence_matches(docs: DataFrame, templates: dict[str, str] | None = None, coverage: float = COVERAGE) -> DataFrame:
    """doc_id, licence, coverage, start, end of each licence text in each document."""
    texts = TEMPLATES if templates is None else templates

    def start():
        t = Templates(texts, coverage)

        def f(c):
            rows = [(d, *x) for d, text in zip(c["doc_id"], c["text"]) for x in t.matches(text)]
            return dict(zip(("doc_id", "licence", "coverage", "start", "end"), map(list, zip(*rows)) if rows else ([], [], [], [], [])))

        return f

    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return map_slices(slim, "doc_id long, licence string, coverage double, start long, end long", start)


def op10_licences(spark, sf_dir: str) -> DataFrame:
    return licence_matches(table(spark, sf_dir, "documents", "doc_id", "text"))
