"""Candidate lists by grid cell, for blocks whose codebooks are long.

The ball is covered by a Cartesian grid. ``top`` keeps for each cell the codewords closest to its
centre (approximate); ``safe`` keeps every codeword that can be the closest of some point
of the cell (exact, by the triangle inequality). Blocks outside the grid search the whole book.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import lru_cache

import numpy as np

from .codebooks import ball_block, nearest


#: Candidates that are compared at once.
TILE = 1 << 14
#: Distances of cells and codewords that are held at once.
SQUARES = 1 << 20


@dataclass(frozen=True)
class Cells:
    book: np.ndarray
    half: float
    per_axis: int
    #: (cells, longest list): codeword numbers in order, filled up with the first of each list
    lists: np.ndarray
    sizes: np.ndarray
    #: (cells, longest list): those of each list that are the closest of its for some point of the cell, filled up with the first
    short: np.ndarray
    counts: np.ndarray

    def assign(self, z: np.ndarray) -> np.ndarray:
        p = z.shape[1]
        at = np.floor((z + self.half) * (self.per_axis / (2 * self.half))).astype(np.int64)
        inside = ((at >= 0) & (at < self.per_axis)).all(axis=1)
        out = np.empty(len(z), dtype=np.int64)
        cell = at[inside] @ (self.per_axis ** np.arange(p - 1, -1, -1))
        zi, axes = z[inside], np.ascontiguousarray(self.book.T)
        norm, code = (self.book * self.book).sum(axis=1) / 2, self.short[:, 0].take(cell).astype(np.int64)
        count, least = self.counts.take(cell), 1
        while least < self.short.shape[1]:  # lists of like length together
            most = min(2 * least, self.short.shape[1])
            own = np.flatnonzero((count > least) & (count <= most))
            lists, step, least = np.ascontiguousarray(self.short[:, :most]), max(1, TILE // most), most
            for a in range(0, len(own), step):
                at = own[a : a + step]
                cand, x = lists.take(cell[at], axis=0), zi[at]
                cost = x[:, :1] * axes[0].take(cand)
                for i in range(1, p):
                    cost += x[:, i : i + 1] * axes[i].take(cand)
                cost = norm.take(cand) - cost
                code[at] = np.take_along_axis(cand, cost.argmin(axis=1)[:, None], axis=1)[:, 0]  # lists are sorted: the first of equal ones
        out[inside] = code
        if not inside.all():
            out[~inside] = nearest(z[~inside], self.book)
        return out


@lru_cache(maxsize=32)
def cells(d: int, p: int, b: int, per_axis: int = 32, mode: str = "top", n_cand: int = 16) -> Cells:
    book = ball_block(d, p, b)
    half = min(1.0, 4.0 / math.sqrt(d))
    axis = (np.arange(per_axis) + 0.5) * (2 * half / per_axis) - half
    centres = np.stack([a.ravel() for a in np.meshgrid(*[axis] * p, indexing="ij")], axis=1)
    n_cand = min(n_cand, len(book))
    lists, sizes = [], []
    reach = math.sqrt(p) * half / per_axis
    step = max(1, SQUARES // len(book))
    for a in range(0, len(centres), step):
        dist = np.sqrt(np.maximum(0, (centres[a : a + step, None, :] - book[None]) ** 2).sum(axis=2)) if len(book) <= 512 else np.sqrt(
            np.maximum(0, (centres[a : a + step] ** 2).sum(1)[:, None] + (book**2).sum(1) - 2 * centres[a : a + step] @ book.T)
        )
        if mode == "top":
            near = np.argpartition(dist, n_cand - 1, axis=1)[:, :n_cand].copy()  # a view would keep the distances' order alive
            lists.append(near.astype(np.int32))
            sizes += [n_cand] * len(near)
        else:
            ok = dist <= dist.min(axis=1, keepdims=True) + 2 * reach + 1e-9
            for row in ok:
                lists.append(np.flatnonzero(row))
                sizes.append(len(lists[-1]))
    longest = max(sizes)
    table = np.sort(np.concatenate(lists), axis=1) if mode == "top" else np.sort(np.array([np.concatenate([x, np.full(longest - len(x), x[0])]) for x in lists], dtype=np.int32), axis=1)
    return Cells(book, half, per_axis, table, np.array(sizes), *_shortened(table, book, centres, half / per_axis))


def _shortened(table: np.ndarray, book: np.ndarray, centres: np.ndarray, h: float) -> tuple[np.ndarray, np.ndarray]:
    """Lists without the words that another word of the list beats at every point within h of a cell's centre by each axis, and how many are left."""
    short, counts = table.copy(), np.empty(len(table), np.int64)
    step = max(1, SQUARES // (8 * table.shape[1]))
    for a in range(0, len(table), step):
        cand = table[a : a + step]
        away = book[cand] - centres[a : a + step, None, :]
        sq = (away * away).sum(axis=2)
        best = sq.argmin(axis=1)[:, None]
        near = np.take_along_axis(away, best[:, :, None], axis=1)
        keep = sq - np.take_along_axis(sq, best, axis=1) <= 2 * h * np.abs(away - near).sum(axis=2) + 1e-12
        keep[:, 1:] &= cand[:, 1:] != cand[:, :1]  # what the list was filled up with
        first = np.argmax(keep, axis=1)
        order = np.argsort(~keep, axis=1, kind="stable")
        n = keep.sum(axis=1)
        moved = np.take_along_axis(cand, order, axis=1)
        short[a : a + step] = np.where(np.arange(table.shape[1]) < n[:, None], moved, cand[np.arange(len(cand)), first][:, None])
        counts[a : a + step] = n
    return short, counts
