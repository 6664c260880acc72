"""Where stated passages occur in texts: eight-byte keys found in array steps, then the whole passage compared."""

from __future__ import annotations

import numpy as np

KEY = 8


def windows(data: bytes) -> np.ndarray:
    """Every run of eight bytes as one integer, without a copy."""
    return np.ndarray(max(0, len(data) - KEY + 1), dtype="<u8", buffer=data, strides=(1,)) if len(data) >= KEY else np.empty(0, dtype="<u8")


class Passages:
    """Passages by name, ready to be looked for in any text at once."""

    def __init__(self, items: list[tuple[int, str]]):
        self.items = [(i, t, t.encode("utf-8", "surrogatepass")) for i, t in items if t]
        self.by_key: dict[int, list[int]] = {}
        for k, (_, _, data) in enumerate(self.items):
            if len(data) >= KEY:
                self.by_key.setdefault(int(windows(data[:KEY])[0]), []).append(k)
        self.short = [k for k, (_, _, data) in enumerate(self.items) if len(data) < KEY]
        self.keys = np.array(sorted(self.by_key), dtype="<u8")

    def find(self, text: str | None) -> list[tuple[int, int]]:
        """(number of the passage, place of its first occurrence in characters)."""
        if not text:
            return []
        data, first = text.encode("utf-8", "surrogatepass"), {}
        v = windows(data)
        if len(v) and len(self.keys):
            at = np.minimum(np.searchsorted(self.keys, v), len(self.keys) - 1)
            for p in np.flatnonzero(self.keys[at] == v).tolist():
                for k in self.by_key[int(v[p])]:
                    if k not in first and data.startswith(self.items[k][2], p):
                        first[k] = len(data[:p].decode("utf-8", "surrogatepass"))
        for k in self.short:
            if (p := text.find(self.items[k][1])) >= 0:
                first[k] = p
        return sorted(first.items())
