"""Benchmark decontamination by pigeonhole edit matching.

A test item that occurs in a text with at most e edits leaves at least one of its e + 1
pieces untouched. The first eight bytes of the pieces of all items are looked for at every
place of each normalised text at once (pieces of fewer bytes one by one), a whole piece decides, and around every hit the item
is verified with the bit-parallel semi-global edit distance. Texts are only mapped, never
shuffled.

Items are taken in blocks of bounded total length; blocks beyond the first cost another
pass over the texts, so the benchmark may grow without a broadcast that grows with it.

Normalised: lower case, runs of white space as one blank. Reported places are offsets in
the original text. Defined cases: null or empty texts and items match nothing; an item
shorter than ``min_item`` characters once normalised must occur exactly, as whole words;
repeated items each report; repeated documents each report; very long texts are matched
whole; an empty table gives no match; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import chain

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bytescan import KEY, KeyScan
from .common import map_slices, small_batches, table

#: One edit is allowed for so many characters of an item; pieces have eight characters and more then.
CHARS_PER_EDIT = 12
MIN_ITEM = 24
#: Characters of items and items that are looked for in one pass.
BLOCK_CHARS = 4_000_000
BLOCK_ITEMS = 20_000


def normal(text: str) -> str:
    return " ".join(text.lower().split())


def places(text: str) -> list[int]:
    """Offset in text of each character of normal(text), and the end."""
    at, out, gap = 0, [], -1
    for i, ch in enumerate(text):
        if ch.isspace():
            gap = i if gap < 0 and out else gap
            continue
        if gap >= 0:
            out.append(gap)
            gap = -1
        out += [i] * len(ch.lower())
        at = i + 1
    return [*out, at]


def best_match(item: str, window: str, budget: int) -> tuple[int, int] | None:
    """(distance, end) of the best occurrence of item in window within budget, by bit vectors.

    The vertical differences of one column of the edit table are held in two integers with
    a bit for each character of the item; the first row is zero, so matches start anywhere.
    """
    m = len(item)
    masks: dict[str, int] = {}
    for i, ch in enumerate(item):
        masks[ch] = masks.get(ch, 0) | 1 << i
    full, top = (1 << m) - 1, 1 << (m - 1)
    plus, minus, score = full, 0, m
    best = None
    for j, ch in enumerate(window):
        eq = masks.get(ch, 0)
        vertical = eq | minus
        diagonal = ((((eq & plus) + plus) ^ plus) | eq) & full
        up = minus | ~(diagonal | plus) & full
        down = plus & diagonal
        score += bool(up & top) - bool(down & top)
        up, down = up << 1 & full, down << 1 & full
        plus = down | ~(vertical | up) & full
        minus = up & vertical
        if score <= budget and (best is None or score < best[0]):
            best = (score, j + 1)
    return best


def every_place(text: str, what: str) -> Iterator[int]:
    at = text.find(what)
    while at >= 0:
        yield at
        at = text.find(what, at + 1)


class Matcher:
    """Items of one block, ready to be found."""

    def __init__(self, items: list[tuple[int, str]], chars_per_edit: int = CHARS_PER_EDIT, min_item: int = MIN_ITEM):
        self.items = [(i, normal(t)) for i, t in items]
        self.items = [(i, t) for i, t in self.items if t]
        self.budget = [0 if len(t) < min_item else len(t) // chars_per_edit for _, t in self.items]
        self.short = {k for k, (_, t) in enumerate(self.items) if len(t.encode()) < KEY or len(t) < min_item}
        self.pieces: dict[bytes, list[tuple[bytes, int, int]]] = {}
        self.tiny: dict[str, list[tuple[int, int]]] = {}  # pieces too short for a key
        for k, ((_, t), e) in enumerate(zip(self.items, self.budget)):
            cuts = [len(t) * p // (e + 1) for p in range(e + 2)]
            for a, b in zip(cuts, cuts[1:]):
                piece = t[a:b].encode("utf-8", "surrogatepass")
                if len(piece) >= KEY:
                    self.pieces.setdefault(piece[:KEY], []).append((piece, k, a))
                elif k not in self.short:
                    self.tiny.setdefault(t[a:b], []).append((k, a))
        self.scan = KeyScan(list(self.pieces))

    def starts(self, t: str) -> dict[int, set[int]]:
        """Where each item would begin, by the pieces of it that t holds."""
        data, spots = t.encode("utf-8", "surrogatepass"), {}
        for k in self.short:
            for at in every_place(t, self.items[k][1]):
                spots.setdefault(k, set()).add(at)
        for piece, owners in self.tiny.items():
            for at in every_place(t, piece):
                for k, a in owners:
                    spots.setdefault(k, set()).add(at - a)
        hits = self.scan.find(data)
        if len(hits):
            chars = np.cumsum((np.frombuffer(data, dtype=np.uint8) & 0xC0) != 0x80)
            for p in hits.tolist():
                for piece, k, a in self.pieces[data[p : p + KEY]]:
                    if data.startswith(piece, p):
                        spots.setdefault(k, set()).add(int(chars[p]) - 1 - a)
        return spots

    def matches(self, text: str | None) -> list[tuple[int, int, int, int]]:
        """(item id, distance, start, end) of each item that occurs in text, its best place."""
        if not text or not self.items:
            return []
        t = normal(text)
        spots = self.starts(t)
        out, offsets = [], None
        for k, starts in spots.items():
            (name, item), e = self.items[k], self.budget[k]
            best, until = None, -1
            for s in sorted(starts):
                if t[max(s, 0) : s + len(item)] == item:
                    got = (0, max(s, 0), s + len(item))
                elif not e or s + len(item) + e <= until:  # another piece of a stretch that was read already
                    continue
                else:
                    lo, until = max(0, s - e), s + len(item) + e
                    hit = best_match(item, t[lo:until], e)
                    if not hit:
                        continue
                    back = best_match(item[::-1], t[max(0, lo + hit[1] - len(item) - e) : lo + hit[1]][::-1], hit[0])
                    end = lo + hit[1]
                    got = (hit[0], end - (back[1] if back else len(item)), end)
                if k in self.short and (got[1] and t[got[1] - 1].isalnum() or got[2] < len(t) and t[got[2]].isalnum()):
                    continue
                if best is None or got[0] < best[0]:
                    best = got
                if best[0] == 0:
                    break
            if best:
                offsets = offsets or places(text)
                start = max(0, best[1])
                out.append((name, best[0], offsets[start], offsets[best[2] - 1] + 1))
        return out


def blocks(items: DataFrame, chars: int, rows: int) -> Iterator[list[tuple[int, str]]]:
    """Items in blocks of bounded size; the driver holds one at a time."""
    now, size = [], 0
    kept = items.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text")).where("item_id IS NOT NULL AND length(text) > 0")
    for r in kept.orderBy("item_id", "text").toLocalIterator():
        if now and (size + len(r["text"]) > chars or len(now) >= rows):
            yield now
            now, size = [], 0
        now.append((r["item_id"], r["text"]))
        size += len(r["text"])
    if now:
        yield now


def benchmark_matches(
    docs: DataFrame, items: DataFrame, chars_per_edit: int = CHARS_PER_EDIT, min_item: int = MIN_ITEM,
    block_chars: int = BLOCK_CHARS, block_rows: int = BLOCK_ITEMS,
) -> DataFrame:
    """doc_id, item_id, distance, start, end of each item in each text."""
    kinds = "doc_id long, item_id long, distance int, start long, end long"
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    out = None
    for block in blocks(items, block_chars, block_rows):

        def start(block=block):  # at most block_chars characters go with the function
            m = Matcher(block, chars_per_edit, min_item)

            def f(c):
                rows = [(d, *x) for d, t in zip(c["doc_id"], c["text"]) for x in m.matches(t)]
                return dict(zip(("doc_id", "item_id", "distance", "start", "end"), map(list, zip(*rows)) if rows else ([], [], [], [], [])))

            return f

        got = map_slices(slim, kinds, start)
        out = got if out is None else out.unionByName(got)
    return docs.sparkSession.createDataFrame([], kinds) if out is None else out


def without_benchmark(docs: DataFrame, items: DataFrame, **options) -> DataFrame:
    """The documents in which no item occurs, with all their columns, whatever their names.

    Null and empty texts stay; repeated rows stay or go alike; an empty table stays empty, and
    an empty benchmark takes nothing away.
    """
    kept = docs
    small_batches(docs.sparkSession)
    for block in blocks(items, options.pop("block_chars", BLOCK_CHARS), options.pop("block_rows", BLOCK_ITEMS)):

        def clean(batches, block=block):
            import pyarrow as pa
            import pyarrow.compute as pc

            m = Matcher(block, **options)
            for b in batches:
                hit = chain.from_iterable([bool(m.matches(t)) for t in b.column("text").slice(at, 256).to_pylist()] for at in range(0, b.num_rows, 256))
                yield b.filter(pc.invert(pa.array(list(hit), type=pa.bool_())))

        kept = kept.mapInArrow(clean, docs.schema)
    return kept


def op3_decontamination(spark, sf_dir: str) -> DataFrame:
    return benchmark_matches(table(spark, sf_dir, "documents", "doc_id", "text"), table(spark, sf_dir, "benchmark", "item_id", "text"))
