"""Random orthogonal matrices."""

from __future__ import annotations

from functools import lru_cache

import numpy as np


@lru_cache(maxsize=32)
def haar_rotation(d: int, seed: int) -> np.ndarray:
    """A draw from the uniform law on orthogonal matrices: Gaussian QR with the signs of R's diagonal put right."""
    q, r = np.linalg.qr(np.random.default_rng(seed).standard_normal((d, d)))
    q = q * np.sign(np.diag(r))
    q.setflags(write=False)
    return q


@lru_cache(maxsize=32)
def gaussian_projection(d: int, seed: int) -> np.ndarray:
    """The matrix of the one-bit residual sketch."""
    s = np.random.default_rng([seed, 1]).standard_normal((d, d))
    s.setflags(write=False)
    return s


@lru_cache(maxsize=32)
def hadamard_rotation(d: int, seed: int, rounds: int = 3) -> np.ndarray:
    """Sign flips and Walsh-Hadamard steps; orthogonal but only close to uniform. d must be a power of two."""
    if d & (d - 1):
        raise ValueError("a Hadamard rotation needs a power of two")
    h = np.ones((1, 1))
    while len(h) < d:
        h = np.block([[h, h], [h, -h]])
    g, m = np.random.default_rng([seed, 2]), np.eye(d)
    for _ in range(rounds):
        m = h @ (g.choice([-1.0, 1.0], d)[:, None] * m) / np.sqrt(d)
    return m
