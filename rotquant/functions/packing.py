"""Codes as bit strings."""

from __future__ import annotations

import numpy as np


def packed_rows(code: np.ndarray, bits: list[int]) -> list[bytes]:
    """Each row's entries one after another, high bits first, filled up with zeros to a byte."""
    parts = [((code[:, i : i + 1] >> np.arange(b - 1, -1, -1)) & 1).astype(np.uint8) for i, b in enumerate(bits) if b]
    if not parts:
        return [b""] * len(code)
    return [r.tobytes() for r in np.packbits(np.hstack(parts), axis=1)]


def unpacked_rows(rows: list[bytes], bits: list[int]) -> np.ndarray:
    out = np.zeros((len(rows), len(bits)), dtype=np.int64)
    if not sum(bits):
        return out
    flat = np.unpackbits(np.frombuffer(b"".join(rows), dtype=np.uint8).reshape(len(rows), -1), axis=1)
    at = 0
    for i, b in enumerate(bits):
        out[:, i] = flat[:, at : at + b] @ (1 << np.arange(b - 1, -1, -1)) if b else 0
        at += b
    return out
