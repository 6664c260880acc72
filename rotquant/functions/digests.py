"""MD5 of many short messages at once, in array steps."""

from __future__ import annotations

import math

import numpy as np

#: Longest message that fits into one block.
LONGEST = 55
_START = np.array([0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476], np.uint32)
_ADD = [np.uint32(int(abs(math.sin(i + 1)) * 2**32)) for i in range(64)]
_TURN = [x for four in ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)) for x in four * 4]
_WORD = [(a * i + b) % 16 for (a, b), r in zip(((1, 0), (5, 1), (3, 5), (7, 0)), range(4)) for i in range(16 * r, 16 * r + 16)]


def md5_blocks(blocks: np.ndarray) -> np.ndarray:
    """Digests as four little-endian words a row, of rows of 64 bytes that are padded already."""
    m = np.ascontiguousarray(blocks.view("<u4").T)
    n = m.shape[1]
    a, b, c, d = (np.full(n, x) for x in _START)
    f, g = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for i in range(64):
        if i < 16:  # d ^ (b & (c ^ d))
            np.bitwise_xor(c, d, out=f)
            f &= b
            f ^= d
        elif i < 32:  # c ^ (d & (b ^ c))
            np.bitwise_xor(b, c, out=f)
            f &= d
            f ^= c
        elif i < 48:
            np.bitwise_xor(b, c, out=f)
            f ^= d
        else:
            np.invert(d, out=f)
            f |= b
            f ^= c
        f += a
        f += m[_WORD[i]]
        f += _ADD[i]
        np.right_shift(f, 32 - _TURN[i], out=g)
        f <<= _TURN[i]
        f |= g
        f += b
        a, d, c, b, f = d, c, b, f, a
    return np.stack([a, b, c, d], axis=1) + _START


def padded(names: list[bytes], ends: list[bytes]) -> np.ndarray:
    """(names, ends, 64 bytes): the block of each name followed by each end."""
    size, longest = np.array([len(x) for x in names]), max(map(len, ends))
    if size.max(initial=0) + longest > LONGEST:
        raise ValueError("a message is longer than a block")
    out = np.frombuffer(b"".join(x.ljust(64, b"\0") for x in names), np.uint8).reshape(len(names), 1, 64).repeat(len(ends), axis=1)
    rows = np.arange(len(names))
    for k, end in enumerate(ends):
        for j, byte in enumerate(end + b"\x80"):
            out[rows, k, size + j] = byte
    bits = 8 * (size[:, None] + np.array([len(e) for e in ends]))
    out[:, :, 56], out[:, :, 57] = bits & 255, bits >> 8
    return out
