"""``rng.key`` in numpy: the MD5 of many short texts at once, each of one block of 64 bytes."""

from __future__ import annotations

import hashlib
import math

import numpy as np

_SHIFTS = [s for four in ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)) for s in four * 4]
_ADDED = [np.uint32(int(abs(math.sin(i + 1)) * 2**32)) for i in range(64)]
_WORDS = [i if i < 16 else (5 * i + 1) % 16 if i < 32 else (3 * i + 5) % 16 if i < 48 else 7 * i % 16 for i in range(64)]
_START = [np.uint32(x) for x in (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)]
CHUNK = 4096  # texts whose words stay in a core's cache


class Keys:
    """Keys of the same ids under many names: the ids are written out once."""

    def __init__(self, ids: np.ndarray):
        self.text = ids.astype("S20")
        self.width = self.text.dtype.itemsize
        self.sizes = np.char.str_len(self.text)

    def of(self, seed: int, axis: str, stage: str, trial: int) -> np.ndarray:
        """``rng.key(seed, axis, stage, trial, id)`` of each id."""
        prefix = f"{seed}:{trial}:{axis}:{stage}:".encode()
        if len(prefix) + self.width > 55:  # more than one block
            return np.array([int.from_bytes(hashlib.md5(prefix + x).digest()[:6]) for x in self.text.tolist()], np.int64)
        out = np.empty(len(self.text), np.int64)
        for at in range(0, len(out), CHUNK):
            out[at : at + CHUNK] = _first_bits(prefix, self.text[at : at + CHUNK], self.sizes[at : at + CHUNK])
        return out


def _first_bits(prefix: bytes, text: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    n, off = len(text), len(prefix)
    block = np.zeros((n, 64), np.uint8)
    block[:, :off] = np.frombuffer(prefix, np.uint8)
    block[:, off : off + text.dtype.itemsize] = text.view(np.uint8).reshape(n, -1)
    block[np.arange(n), off + sizes] = 0x80
    block[:, 56:58] = ((off + sizes) * 8).astype("<u2").view(np.uint8).reshape(n, 2)
    words = np.ascontiguousarray(block.view("<u4").T)
    a, b, c, d = (np.full(n, x) for x in _START)
    f, t = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for i in range(64):
        if i < 16:
            np.bitwise_xor(c, d, out=f)
            f &= b
            f ^= d
        elif i < 32:
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
        f += words[_WORDS[i]]
        f += _ADDED[i]
        np.right_shift(f, np.uint32(32 - _SHIFTS[i]), out=t)
        f <<= np.uint32(_SHIFTS[i])
        f |= t
        f += b
        a, d, c, b, f = d, c, b, f, a
    a, b = (x.astype("<u4").view(np.uint8).reshape(n, 4).astype(np.int64) for x in (a + _START[0], b + _START[1]))
    return a[:, 0] << 40 | a[:, 1] << 32 | a[:, 2] << 24 | a[:, 3] << 16 | b[:, 0] << 8 | b[:, 1]
