"""Fixed codebooks: scalars, balls, spheres. None of them sees data."""

from __future__ import annotations

import math
from functools import lru_cache

import numpy as np

POINTS = 400_001


def _lloyd_1d(t: np.ndarray, w: np.ndarray, levels: int, rounds: int = 20_000) -> np.ndarray:
    """Levels of least expected squared error for a symmetric density on a grid."""
    mass, moment = np.concatenate(([0], np.cumsum(w))), np.concatenate(([0], np.cumsum(w * t)))
    cut = np.interp((np.arange(levels) + 0.5) / levels, mass[1:] / mass[-1], t)
    for _ in range(rounds):
        edge = np.concatenate(([0], np.searchsorted(t, (cut[1:] + cut[:-1]) / 2), [len(t)]))
        m = np.diff(mass[edge])
        new = np.diff(moment[edge]) / np.maximum(m, 1e-300)
        new = (new - new[::-1]) / 2
        if np.abs(new - cut).max() < 1e-12:
            break
        cut = new
    return new


@lru_cache(maxsize=64)
def gauss_scalar(b: int, d: int) -> np.ndarray:
    """2^b levels fitted to the standard normal, over sqrt(d)."""
    t = np.linspace(-9, 9, POINTS)
    return _lloyd_1d(t, np.exp(-t * t / 2), 2**b) / math.sqrt(d)


@lru_cache(maxsize=64)
def sphere_scalar(b: int, d: int) -> np.ndarray:
    """2^b levels fitted to one coordinate of a uniform unit vector."""
    top = min(1.0, 12 / math.sqrt(d))
    t = np.linspace(-top, top, POINTS)
    return _lloyd_1d(t, np.power(np.maximum(0, 1 - t * t), (d - 3) / 2), 2**b)


def block_density(z: np.ndarray, d: int) -> np.ndarray:
    """Density of a p-coordinate block of a uniform unit vector in d dimensions."""
    p = z.shape[-1]
    c = math.lgamma(d / 2) - p / 2 * math.log(math.pi) - math.lgamma((d - p) / 2)
    r = (z * z).sum(axis=-1)
    return np.where(r < 1, np.exp(c) * np.power(np.maximum(0, 1 - r), (d - p - 2) / 2), 0)


def sample_block(p: int, d: int, n: int, seed: int) -> np.ndarray:
    """Exact draws: a Gaussian block over the length of a Gaussian vector that contains it."""
    g = np.random.default_rng([seed, p, d])
    z = g.standard_normal((n, p))
    rest = g.chisquare(d - p, n) if d > p else 0.0
    return z / np.sqrt((z * z).sum(axis=1) + rest)[:, None]


def nearest(z: np.ndarray, book: np.ndarray, tile: int = 1 << 22, kind=np.float64) -> np.ndarray:
    """Index of the closest point of book to each row of z, in tiles of bounded size."""
    z, book = z.astype(kind, copy=False), book.astype(kind, copy=False)
    half = (book * book).sum(axis=1) / 2
    step = max(1, tile // len(book))
    out = np.empty(len(z), dtype=np.int64)
    for a in range(0, len(z), step):
        out[a : a + step] = (half - z[a : a + step] @ book.T).argmin(axis=1)
    return out


def means(z: np.ndarray, code: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    n = np.bincount(code, minlength=k).astype(float)
    s = np.stack([np.bincount(code, weights=z[:, j], minlength=k) for j in range(z.shape[1])], axis=1)
    return s, n


def _start(d: int, p: int, b: int, z: np.ndarray) -> np.ndarray:
    """A product of scalar levels; it is the best start for one bit and a good one for more."""
    axes = np.meshgrid(*[sphere_scalar(b, d)] * p, indexing="ij")
    grid = np.stack([a.ravel() for a in axes], axis=1)
    # corners that no block reaches take draws instead
    far = np.linalg.norm(grid, axis=1) > np.quantile(np.linalg.norm(z, axis=1), 1 - 0.1 / len(grid) if len(grid) > 64 else 1.0)
    grid[far] = z[: far.sum()]
    return grid


#: Draws, rounds and random starts of the fit, by the number of centroids.
FIT = ((16, 60_000, 40, 3), (64, 60_000, 25, 1), (512, 200_000, 20, 1), (1 << 62, 120_000, 6, 1))


@lru_cache(maxsize=64)
def ball_block(d: int, p: int, b: int, seed: int = 0) -> np.ndarray:
    """2^(bp) centroids of the block law, by Lloyd's rounds over a fixed antipodal sample."""
    if p == 1:
        return sphere_scalar(b, d)[:, None]
    k = 2 ** (b * p)
    n, rounds, tries = next(x[1:] for x in FIT if k <= x[0])
    z = sample_block(p, d, n // 2, seed)
    z = np.concatenate([z, -z])
    starts = [_start(d, p, b, z)] * (k <= 64) + [spread_start(z, k, seed + i) for i in range(tries)]
    book = min((lloyd(z, s, rounds) for s in starts), key=lambda x: x[0])[1]
    return book[np.lexsort(book.T[::-1])]


def spread_start(z: np.ndarray, k: int, seed: int) -> np.ndarray:
    """Draws picked one by one with chances that grow with their distance to those picked before."""
    g = np.random.default_rng([seed, k])
    z = z[:: max(1, len(z) // max(8000, 6 * k))]
    out = [z[g.integers(len(z))]]
    far = ((z - out[0]) ** 2).sum(axis=1)
    for _ in range(k - 1):
        out.append(z[g.choice(len(z), p=far / far.sum())])
        far = np.minimum(far, ((z - out[-1]) ** 2).sum(axis=1))
    return np.array(out)


def lloyd(z: np.ndarray, book: np.ndarray, rounds: int) -> tuple[float, np.ndarray]:
    """(cost, centroids) after rounds of assignment and means, or once the cost stands still."""
    last = math.inf
    for _ in range(rounds):
        code = nearest(z, book, kind=np.float32)
        s, m = means(z, code, len(book))
        away = ((z - book[code]) ** 2).sum(axis=1)
        cost = float(away.mean())
        if empty := int((m == 0).sum()):  # refilled by the worst served draws
            s[m == 0], m[m == 0] = z[np.argsort(-away, kind="stable")[:empty]], 1
        elif last - cost < 1e-7 * cost:
            break
        book, last = s / m[:, None], cost
    return cost, book


@lru_cache(maxsize=16)
def full_sphere(d: int, b: int, seed: int = 0) -> np.ndarray:
    """2^(bd) unit vectors fitted to the uniform law on the sphere; for tiny d only."""
    if b * d > 16:
        raise ValueError("full_sphere has 2^(b d) codewords: b * d may be 16 at most")
    g = np.random.default_rng([seed, d, b])
    unit = lambda x: x / np.linalg.norm(x, axis=1, keepdims=True)
    k = 2 ** (b * d)
    z = unit(g.standard_normal((max(20_000, 16 * k), d)))
    book = z[:k].copy()
    for _ in range(15 if k <= 4096 else 5):
        s, m = means(z, nearest(z, book), k)
        s[m == 0] = z[:k][m == 0]
        book = unit(s)
    return book


def distortion(z: np.ndarray, book: np.ndarray) -> float:
    """Mean squared distance of draws to their codewords."""
    return float(((z - book[nearest(z, book)]) ** 2).sum(axis=1).mean())


def block_quadrature(p: int, d: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """(points, weights) of the block law for p of 1, 2 or 3: midpoints in the radius, spread directions.

    Weights add up to one. With n radii and about n directions, smooth costs are integrated to
    a few parts in n squared.
    """
    top = min(1.0, 9 / math.sqrt(d))
    r = (np.arange(n) + 0.5) * top / n
    w = r ** (p - 1) * np.power(1 - r * r, (d - p - 2) / 2)
    if p == 1:
        at = np.array([[1.0], [-1.0]])
    elif p == 2:
        t = (np.arange(n) + 0.5) * 2 * math.pi / n
        at = np.stack([np.cos(t), np.sin(t)], axis=1)
    elif p == 3:  # equal areas along a spiral
        z = 1 - (2 * np.arange(n) + 1) / n
        t = np.arange(n) * math.pi * (3 - math.sqrt(5))
        s = np.sqrt(1 - z * z)
        at = np.stack([s * np.cos(t), s * np.sin(t), z], axis=1)
    else:
        raise ValueError("quadrature is given for blocks of 1, 2 and 3")
    points = (r[:, None, None] * at[None]).reshape(-1, p)
    weights = np.repeat(w / w.sum(), len(at)) / len(at)
    return points, weights


def spread_sphere(d: int, n: int) -> np.ndarray:
    """n points spread evenly over the unit sphere of 3 or 4 dimensions, by turning irrational angles."""
    i = np.arange(n)
    if d == 3:
        z, t = 1 - (2 * i + 1) / n, i * math.pi * (3 - math.sqrt(5))
        return np.stack([np.sqrt(1 - z * z) * np.cos(t), np.sqrt(1 - z * z) * np.sin(t), z], axis=1)
    if d != 4:
        raise ValueError("spread points are given for 3 and 4 dimensions")
    u, s, t = (i + 0.5) / n, 2 * math.pi * math.sqrt(2) * i, 2 * math.pi * math.sqrt(3) * i
    return np.stack([np.sqrt(u) * np.cos(s), np.sqrt(u) * np.sin(s), np.sqrt(1 - u) * np.cos(t), np.sqrt(1 - u) * np.sin(t)], axis=1)
