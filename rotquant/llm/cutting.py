"""Cutting stock over a histogram of piece sizes, by column generation.

The restricted master program asks for the least number of bins that hold exactly the
counted pieces, over the patterns found so far; its dual prices go to an unbounded knapsack
that looks for a pattern worth more than one bin. The basis has one row per size, so the
work depends on the number of sizes and never on the number of pieces.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

EPS = 1e-9


def best_pattern(sizes: np.ndarray, prices: np.ndarray, room: int) -> tuple[float, np.ndarray]:
    """The multiset of sizes within room that is worth most, by dynamic programming."""
    use = np.flatnonzero(prices > EPS)
    counts = np.zeros(len(sizes), dtype=np.int64)
    if not len(use):
        return 0.0, counts
    s, v = sizes[use], prices[use]
    order = np.argsort(s, kind="stable")
    use, s, v = use[order], s[order], v[order]
    worth, last = np.zeros(room + 1), np.full(room + 1, -1)
    fits = np.searchsorted(s, np.arange(room + 1), side="right")
    for c in range(1, room + 1):
        worth[c] = worth[c - 1]
        if k := fits[c]:
            got = worth[c - s[:k]] + v[:k]
            j = int(got.argmax())
            if got[j] > worth[c] + EPS:
                worth[c], last[c] = got[j], j
    c = room
    while c > 0:
        if (j := last[c]) < 0:
            c -= 1
        else:
            counts[use[j]] += 1
            c -= s[j]
    return float(worth[room]), counts


def relaxed(sizes: np.ndarray, demand: np.ndarray, room: int, rounds: int = 4000) -> tuple[np.ndarray, np.ndarray, float]:
    """Patterns (columns), how often each is used, and the bins the relaxed program needs."""
    n = len(sizes)
    basis = np.diag((room // sizes).astype(float))
    inverse = np.diag(1.0 / np.diag(basis))
    x = inverse @ demand.astype(float)
    for step in range(rounds):
        worth, column = best_pattern(sizes, inverse.sum(axis=0), room)
        if worth <= 1 + 1e-7:
            break
        u = inverse @ column
        up = np.flatnonzero(u > EPS)
        ratio = x[up] / u[up]
        out = up[int(ratio.argmin())]
        theta = max(0.0, float(ratio.min()))
        x -= theta * u
        x[out] = theta
        basis[:, out] = column
        if step % 64 == 63:  # rounding errors do not pile up
            inverse = np.linalg.inv(basis)
            x = np.maximum(inverse @ demand, 0)
        else:
            row = inverse[out] / u[out]
            inverse -= np.outer(u, row)
            inverse[out] = row
        np.maximum(x, 0, out=x)
    return np.rint(basis).astype(np.int64), x, float(x.sum())


@dataclass
class Plan:
    """Bins by pattern. For each size: where runs of ranks of its pieces go."""

    room: int
    bins: int = 0
    relaxed_bins: float = 0.0
    #: size -> lists: first rank, pieces a bin, first bin, place of the first piece in a bin
    slots: dict[int, list[list[int]]] = field(default_factory=dict)

    def add(self, sizes: np.ndarray, counts: np.ndarray, times: int, taken: np.ndarray) -> None:
        place = 0
        for i in np.argsort(-sizes, kind="stable"):
            if k := int(counts[i]):
                self.slots.setdefault(int(sizes[i]), [[], [], [], []])
                for have, new in zip(self.slots[int(sizes[i])], (int(taken[i]), k, self.bins, place)):
                    have.append(new)
                taken[i] += k * times
                place += k * int(sizes[i])
        self.bins += times

    def locate(self, size: int, rank: np.ndarray, first_bin: int = 0) -> tuple[np.ndarray, np.ndarray]:
        """Bin and place of the pieces of this size with these ranks."""
        start, each, bin0, place = (np.asarray(a, dtype=np.int64) for a in self.slots[size])
        p = np.searchsorted(start, rank, side="right") - 1
        q = rank - start[p]
        return first_bin + bin0[p] + q // each[p], place[p] + q % each[p] * size


def cutting_plan(histogram: dict[int, int], room: int) -> Plan:
    """Bins of the given room for pieces counted by size: whole multiples of the relaxed
    program's patterns, then the largest pieces first for the few that rounding leaves."""
    plan = Plan(room)
    items = sorted((s, c) for s, c in histogram.items() if c > 0)
    if not items:
        return plan
    if items[0][0] < 1 or items[-1][0] > room:
        raise ValueError("a piece must have a size from 1 to the room of a bin")
    sizes, left = np.array([s for s, _ in items]), np.array([c for _, c in items], dtype=np.int64)
    taken = np.zeros_like(left)
    patterns, x, plan.relaxed_bins = relaxed(sizes, left, room)
    for j in range(len(x)):
        a = patterns[:, j]
        if a.any() and (times := int(min(np.floor(x[j] + 1e-6), (left[a > 0] // a[a > 0]).min()))) > 0:
            plan.add(sizes, a, times, taken)
            left -= a * times
    while left.any():
        a, free = np.zeros_like(left), room
        for i in range(len(sizes) - 1, -1, -1):
            a[i] = min(left[i], free // sizes[i])
            free -= a[i] * sizes[i]
        times = int((left[a > 0] // a[a > 0]).min())
        plan.add(sizes, a, times, taken)
        left -= a * times
    return plan
