"""All places in a byte string where one of many eight-byte keys begins, in array steps."""

from __future__ import annotations

import numpy as np

from ..functions.passages import KEY, windows

_MULT = np.uint64(0x9E3779B97F4A7C15)  # fixed odd multiplier


class KeyScan:
    def __init__(self, keys: list[bytes]):
        """keys: of exactly eight bytes."""
        self.keys = np.unique(np.frombuffer(b"".join(keys), dtype="<u8")) if keys else np.empty(0, dtype="<u8")
        self.bits = max(16, int(len(self.keys)).bit_length() + 7)
        self.maybe = np.zeros(1 << self.bits, dtype=bool)
        self.maybe[self._slot(self.keys)] = True

    def _slot(self, v: np.ndarray) -> np.ndarray:
        return (v * _MULT) >> np.uint64(64 - self.bits)

    def find(self, data: bytes) -> np.ndarray:
        """Byte offsets where a key begins."""
        v = windows(data)
        if not len(v) or not len(self.keys):
            return np.empty(0, dtype=np.int64)
        at = np.flatnonzero(self.maybe[self._slot(v)])
        if not len(at):
            return at
        got = v[at]
        i = np.minimum(np.searchsorted(self.keys, got), len(self.keys) - 1)
        return at[self.keys[i] == got]
