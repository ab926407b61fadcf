"""The numbers of functions.uniform() over NumPy arrays, for tasks that make many of them in memory."""

from __future__ import annotations

import hashlib
import math

import numpy as np

#: Rows that are hashed at a time: enough that a step's call costs little beside its work.
CHUNK = 32_768
_TURNS = [(7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)]
_SINES = [int(abs(math.sin(i + 1)) * 2**32) & 0xFFFFFFFF for i in range(64)]
_START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)


def _digest(words: list) -> tuple[np.ndarray, np.ndarray]:
    """The first two words of the md5 of one block of 16 words, each an array or, where all rows agree, a number."""
    n = next(len(w) for w in words if isinstance(w, np.ndarray))
    a, b, c, d = (np.full(n, v, np.uint32) for v in _START)
    f, low = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for i in range(64):
        kind = i // 16
        if kind == 0:
            np.bitwise_xor(c, d, out=f)
            f &= b
            f ^= d
            g = i
        elif kind == 1:
            np.bitwise_xor(b, c, out=f)
            f &= d
            f ^= c
            g = (5 * i + 1) % 16
        elif kind == 2:
            np.bitwise_xor(b, c, out=f)
            f ^= d
            g = (3 * i + 5) % 16
        else:
            np.invert(d, out=f)
            f |= b
            f ^= c
            g = 7 * i % 16
        f += a
        if isinstance(words[g], np.ndarray):
            f += words[g]
            f += np.uint32(_SINES[i])
        else:
            f += np.uint32((_SINES[i] + words[g]) & 0xFFFFFFFF)
        turn = _TURNS[kind][i % 4]
        np.right_shift(f, np.uint32(32 - turn), out=low)
        f <<= np.uint32(turn)
        f |= low
        f += b
        a, d, c, b, f = d, c, b, f, a
    return a + np.uint32(_START[0]), b + np.uint32(_START[1])


def digits(v: np.ndarray) -> np.ndarray:
    """How many decimal digits each number of at least 0 has."""
    return np.searchsorted(10 ** np.arange(1, 19, dtype=np.int64), v, side="right") + 1


def md5_numbers(fields: list, widths: list[int]) -> np.ndarray:
    """The first 13 hex digits of the md5 of fields joined by "|", as whole numbers. A field is bytes, or an array of numbers
    all of which have as many digits as widths says."""
    size = sum(len(f) if isinstance(f, bytes) else k for f, k in zip(fields, widths, strict=True)) + len(fields) - 1
    n = next(len(f) for f in fields if not isinstance(f, bytes))
    if size > 55:  # more than one block, one by one
        texts = zip(*[[f] * n if isinstance(f, bytes) else [b"%d" % v for v in f.tolist()] for f in fields], strict=True)
        return np.array([int(hashlib.md5(b"|".join(t)).hexdigest()[:13], 16) for t in texts], np.int64)
    fixed, moving, at = bytearray(64), {}, 0
    for j, (f, k) in enumerate(zip(fields, widths, strict=True)):
        if j:
            fixed[at] = ord("|")
            at += 1
        if isinstance(f, bytes):
            fixed[at : at + len(f)] = f
            at += len(f)
        else:
            for i in range(k):
                fixed[at + i] = ord("0")
                moving[at + i] = (j, k - 1 - i)
            at += k
    fixed[at] = 0x80
    fixed[56:60] = (size * 8).to_bytes(4, "little")
    plain = [int.from_bytes(fixed[4 * i : 4 * i + 4], "little") for i in range(16)]
    out = np.empty(n, np.int64)
    for lo in range(0, n, CHUNK):
        words, rest = list(plain), {}
        for p in sorted(moving, key=lambda p: (moving[p][0], moving[p][1])):  # a field's last digit first
            j, place = moving[p]
            if place == 0:
                v = fields[j][lo : lo + CHUNK]
                rest[j] = v.astype(np.uint32) if widths[j] <= 9 else v.astype(np.uint64)
            up = rest[j] // 10
            digit = (rest[j] - up * 10).astype(np.uint32)
            rest[j] = up
            words[p // 4] = words[p // 4] + (digit << np.uint32(8 * (p % 4))) if isinstance(words[p // 4], np.ndarray) else np.uint32(words[p // 4]) + (digit << np.uint32(8 * (p % 4)))
        a, b = _digest(words)
        out[lo : lo + CHUNK] = (a.byteswap().astype(np.int64) << 20) | (b.byteswap() >> np.uint32(12)).astype(np.int64)
    return out


_P1, _P2, _P3, _P4, _P5 = (np.uint64(p) for p in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))


def _turned(v: np.ndarray, by: int) -> np.ndarray:
    return (v << np.uint64(by)) | (v >> np.uint64(64 - by))


def _final(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(33))) * _P2
    h = (h ^ (h >> np.uint64(29))) * _P3
    return h ^ (h >> np.uint64(32))


def xx_int(v: np.ndarray, seed: np.ndarray) -> np.ndarray:
    """xxhash64 of 32-bit numbers (uint64 arrays), as Spark chains it."""
    h = (seed + np.uint64((int(_P5) + 4) % 2**64)) ^ ((v & np.uint64(0xFFFFFFFF)) * _P1)
    return _final(_turned(h, 23) * _P2 + _P3)


def xx_long(v: np.ndarray, seed: np.ndarray) -> np.ndarray:
    h = (seed + np.uint64((int(_P5) + 8) % 2**64)) ^ (_turned(v * _P2, 31) * _P1)
    return _final(_turned(h, 27) * _P1 + _P4)
