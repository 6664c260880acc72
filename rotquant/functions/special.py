"""Special functions that the bounds need and numpy lacks."""

from __future__ import annotations

import math


def digamma(x: float) -> float:
    """By recurrence up to 8 and the asymptotic series beyond."""
    if x <= 0:
        raise ValueError("digamma is needed for positive arguments only")
    shift = 0.0
    while x < 8:
        shift -= 1 / x
        x += 1
    r = 1 / (x * x)
    return shift + math.log(x) - 1 / (2 * x) - r * (1 / 12 - r * (1 / 120 - r * (1 / 252 - r * (1 / 240 - r / 132))))


def normal_pdf(x: float) -> float:
    return math.exp(-x * x / 2) / math.sqrt(2 * math.pi)


def golden(f, a: float, b: float, tol: float = 1e-9) -> float:
    """The place of the least value of a unimodal function."""
    g = (math.sqrt(5) - 1) / 2
    c, d = b - g * (b - a), a + g * (b - a)
    fc, fd = f(c), f(d)
    while b - a > tol:
        if fc < fd:
            b, d, fd = d, c, fc
            c = b - g * (b - a)
            fc = f(c)
        else:
            a, c, fc = c, d, fd
            d = a + g * (b - a)
            fd = f(d)
    return (a + b) / 2
