"""The quantizers on batches of rows: numpy in, numpy out."""

from __future__ import annotations

import math
from functools import lru_cache

import numpy as np

from ..functions import codebooks as cb
from ..functions.lookup import cells
from ..functions.rotation import gaussian_projection, haar_rotation, hadamard_rotation
from ..model import QuantizerSpec

#: Steps of all rows that the exact sweep sorts at once.
SWEEP = 1 << 16
#: Scales that the ladder search tries, as multiples of 1 / sqrt(d).
LADDER = 48


def ladder(b: int) -> np.ndarray:
    """Steps of the grid, times sqrt(d), spread evenly around the best one for the normal law."""
    best = {1: 1.6, 2: 1.0, 3: 0.59, 4: 0.335}.get(b, 5.4 * 2.0**-b)
    return best * np.linspace(0.5, 1.9, LADDER)


class Codec:
    """Codebooks and rotation of a spec, and what is done with them."""

    def __init__(self, spec: QuantizerSpec):
        self.spec = spec
        w = spec.width
        self.rotation = (hadamard_rotation if spec.rotation == "hadamard" else haar_rotation)(w, spec.seed)
        self.family = spec.codebook
        self.base_bits = spec.b
        if self.family == "sphere_scalar_signbit":
            self.projection = gaussian_projection(w, spec.seed)
            self.base_bits = spec.b - 1
        if self.family in ("gauss_scalar", "sphere_scalar", "sphere_scalar_signbit"):
            make = cb.gauss_scalar if self.family == "gauss_scalar" else cb.sphere_scalar
            self.levels = make(self.base_bits, w) if self.base_bits else np.zeros(1)
            self.cuts = (self.levels[1:] + self.levels[:-1]) / 2
        elif self.family == "full_sphere":
            self.books = {w: cb.full_sphere(w, spec.b)}
        elif self.family == "ball_block":
            self.books = {s: cb.ball_block(w, s, spec.b) for s in {s for _, s in spec.layout}}
            self.tables = {s: cells(w, s, spec.b, spec.cells, spec.assign, spec.n_cand) for s in self.books if s > 1} if spec.assign in ("top", "safe") else {}

    # coding -----------------------------------------------------------------

    def rotate(self, x: np.ndarray) -> np.ndarray:
        if x.shape[1] < self.spec.width:
            x = np.hstack([x, np.zeros((len(x), self.spec.width - x.shape[1]))])
        return x @ self.rotation.T

    def _blocks(self) -> list[tuple[int, int, int]]:
        """(size, first column, number) of runs of equal blocks."""
        out: list[list[int]] = []
        for a, s in self.spec.layout:
            if out and out[-1][0] == s:
                out[-1][2] += 1
            else:
                out.append([s, a, 1])
        return [tuple(x) for x in out]

    def assign(self, z: np.ndarray) -> np.ndarray:
        """Codes of rotated unit vectors."""
        if self.family == "grid_dir":
            return grid_ladder(z, self.spec.b) if self.spec.assign == "ladder" else grid_sweep(z, self.spec.b)
        if self.family in ("ball_block", "full_sphere"):
            parts = []
            for s, a, n in self._blocks():
                block = z[:, a : a + s * n].reshape(-1, s)
                if s == 1:
                    book = self.books[1][:, 0]
                    code = between(block[:, 0], (book[1:] + book[:-1]) / 2)
                else:
                    code = self.tables[s].assign(block) if self.family == "ball_block" and s in self.tables else cb.nearest(block, self.books[s])
                parts.append(code.reshape(len(z), n))
            return np.hstack(parts)
        return between(z, self.cuts)

    def values(self, code: np.ndarray) -> np.ndarray:
        """Raw reconstruction in the rotated domain."""
        if self.family == "grid_dir":
            g = code - (2.0 ** (self.spec.b - 1) - 0.5)
            return g / np.linalg.norm(g, axis=1, keepdims=True)
        if self.family in ("ball_block", "full_sphere"):
            parts, at = [], 0
            for s, _, n in self._blocks():
                parts.append(self.books[s][code[:, at : at + n]].reshape(len(code), -1))
                at += n
            return np.hstack(parts)
        return self.levels.take(code)

    def turned(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Norms and rotated directions of rows, the same for all codecs of one rotation."""
        norm = np.sqrt((x * x).sum(axis=1))
        return norm, self.rotate(x / norm[:, None])

    @property
    def turn(self) -> tuple:
        """What turned() depends on."""
        return self.spec.width, self.spec.rotation, self.spec.seed

    def encode(self, x: np.ndarray, turned: tuple[np.ndarray, np.ndarray] | None = None) -> dict[str, np.ndarray]:
        """Codes and side scalars of rows of any norm; turned: turned(x), if it is there already."""
        norm, z = turned or self.turned(x)
        code = self.assign(z)
        zbar = self.values(code)
        out = {"norm": norm, "code": code, "rho": (z * zbar).sum(axis=1), "zbar_sq": (zbar * zbar).sum(axis=1)}
        if self.family == "sphere_scalar_signbit":
            r = z - zbar
            out["signs"], out["rnorm"] = (r @ self.projection.T > 0).astype(np.int64), np.sqrt((r * r).sum(axis=1))
        return out

    # use --------------------------------------------------------------------

    def scale(self, rho: np.ndarray, zbar_sq: np.ndarray) -> np.ndarray:
        """The factor on the raw reconstruction. An unbiased factor of a code that points away is not a number."""
        if self.spec.rescale == "best":
            return rho / zbar_sq
        if self.spec.rescale == "unbiased":
            return np.where(rho > 0, 1 / np.where(rho > 0, rho, 1), np.nan)
        return np.ones(len(rho))

    def left(self, codes: dict[str, np.ndarray]) -> np.ndarray:
        """Rows whose products with right(queries) are the estimates; rows are never rotated back. A row without an estimate is not a number."""
        zbar = self.values(codes["code"])
        if self.family == "sphere_scalar_signbit":
            zbar = np.hstack([zbar, math.sqrt(math.pi / 2) / self.spec.width * codes["rnorm"][:, None] * (2.0 * codes["signs"] - 1)])
        else:
            zbar = zbar * self.scale(codes["rho"], codes["zbar_sq"])[:, None]
        return zbar * codes["norm"][:, None]

    @property
    def side(self) -> tuple:
        """What right() depends on."""
        return self.spec.d, self.spec.width, self.spec.rotation, self.spec.seed, self.family == "sphere_scalar_signbit"

    def right(self, queries: np.ndarray) -> np.ndarray:
        """Queries rotated once, with their sketch beside them where the family has one."""
        y = self.rotate(queries)
        return np.hstack([y, y @ self.projection.T]) if self.family == "sphere_scalar_signbit" else y

    def estimate(self, codes: dict[str, np.ndarray], queries: np.ndarray) -> np.ndarray:
        """(rows, queries) inner products."""
        return self.left(codes) @ self.right(queries).T

    def decode(self, codes: dict[str, np.ndarray]) -> np.ndarray:
        """Reconstructions in the original domain, with their norms."""
        zbar = self.values(codes["code"])
        if self.family == "sphere_scalar_signbit":
            w = self.spec.width
            zbar = zbar + math.sqrt(math.pi / 2) / w * codes["rnorm"][:, None] * ((2.0 * codes["signs"] - 1) @ self.projection)
        else:
            zbar = zbar * self.scale(codes["rho"], codes["zbar_sq"])[:, None]
        return (zbar @ self.rotation)[:, : self.spec.d] * codes["norm"][:, None]


def between(z: np.ndarray, cuts: np.ndarray) -> np.ndarray:
    """np.searchsorted(cuts, z); few cuts are counted one after the other."""
    if len(cuts) > 32:
        return np.searchsorted(cuts, z)
    code = np.full(z.shape, len(cuts), np.int8)
    for cut in cuts:
        code -= z <= cut
    return code.astype(np.int64)


def grid_sweep(z: np.ndarray, b: int) -> np.ndarray:
    """The grid word with the largest cosine to each row.

    As the scale grows, one coordinate after another steps to its next grid value; the
    inner product and the squared norm change by known amounts at each step, so their running sums over
    the sorted steps give the cosine of every word that some scale rounds to.
    """
    top = 2 ** (b - 1) - 1
    n, d = z.shape
    step = max(1, SWEEP // (d * max(top, 1)))
    if n > step:
        return np.vstack([grid_sweep(z[at : at + step], b) for at in range(0, n, step)])
    a, code = np.abs(z), np.zeros((n, d), dtype=np.int64)
    if top:
        with np.errstate(divide="ignore"):
            t = (np.arange(1, top + 1)[None, None, :] / a[:, :, None]).reshape(n, -1)
        order = np.argsort(t, axis=1)
        dot = np.cumsum(np.take_along_axis(a, order // top, axis=1), axis=1) + a.sum(axis=1, keepdims=True) / 2
        norm = np.cumsum(2.0 * (order % top + 1), axis=1) + d / 4
        cos, rows = dot / np.sqrt(norm), np.arange(n)
        best = cos.argmax(axis=1)
        # steps at one scale are taken together: between them the cosine falls before it rises, so none is best
        last = np.where(cos[rows, best] > a.sum(axis=1) / math.sqrt(d), t[rows, order[rows, best]], -1.0)
        code = (t <= last[:, None]).reshape(n, d, top).sum(axis=2)
    return np.where(z >= 0, code + 2 ** (b - 1), 2 ** (b - 1) - 1 - code)


def grid_ladder(z: np.ndarray, b: int) -> np.ndarray:
    """The best grid word among those that a fixed ladder of scales rounds to."""
    n, d = z.shape
    a, best, code = np.abs(z), np.full(n, -1.0), np.zeros((n, d), dtype=np.int64)
    for step in ladder(b) / math.sqrt(d):
        g = np.minimum(np.floor(a / step), 2 ** (b - 1) - 1)
        cos = ((g + 0.5) * a).sum(axis=1) / np.sqrt(((g + 0.5) ** 2).sum(axis=1))
        better = cos > best
        best, code[better] = np.where(better, cos, best), g[better].astype(np.int64)
    return np.where(z >= 0, code + 2 ** (b - 1), 2 ** (b - 1) - 1 - code)


@lru_cache(maxsize=64)
def codec(spec: QuantizerSpec) -> Codec:
    """One codec a process and spec: the driver's, and one in each Python worker."""
    return Codec(spec)
