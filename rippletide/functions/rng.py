"""Stateless draws: a hash of keys, so a retry or another partitioning never changes a world."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def _col(x: Column | str | int) -> Column:
    return x if isinstance(x, Column) else F.lit(x)


def u01(*keys: Column | str | int, mode: str = "xxhash") -> Column:
    """Uniform in [0, 1). ``mode="md5"`` uses 32 bits of an md5 and agrees with the SQL oracles;
    ``"xxhash"`` is the faster default with 53 bits."""
    if mode == "md5":
        text = F.concat_ws("|", *[_col(k).cast("string") for k in keys])
        return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)
    return F.shiftrightunsigned(F.xxhash64(*[_col(k) for k in keys]), 11).cast("double") * F.lit(2.0**-53)


def normal(tag: str, seed: int, key: Column, mode: str = "xxhash") -> Column:
    """Standard normal by the Box-Muller transform of two draws."""
    a, b = u01(tag + "1", seed, key, mode=mode), u01(tag + "2", seed, key, mode=mode)
    return F.sqrt(-2 * F.log(1 - a)) * F.cos(2 * F.pi() * b)


_SHIFTS = [7, 12, 17, 22] * 4 + [5, 9, 14, 20] * 4 + [4, 11, 16, 23] * 4 + [6, 10, 15, 21] * 4
_SINES = [int(abs(np.sin(i + 1)) * 2**32) for i in range(64)]
_PLACES = [i if i < 16 else (5 * i + 1) % 16 if i < 32 else (3 * i + 5) % 16 if i < 48 else 7 * i % 16 for i in range(64)]
_START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)
#: Messages whose hash is taken at a time: the arrays of a step stay in the CPU's cache.
_BLOCK = 8192


def _md5_head(words: dict[int, np.ndarray], n: int) -> np.ndarray:
    """The first four bytes of the md5 of n one-block messages as a number; words not given are 0."""
    a, b, c, d = (np.full(n, x, np.uint32) for x in _START)
    f, g = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for i in range(61):  # the last three steps leave the first word as it is
        if i < 16 or i >= 48:
            if i < 16:
                np.bitwise_xor(c, d, out=f)
                np.bitwise_and(f, b, out=f)
                np.bitwise_xor(f, d, out=f)
            else:
                np.invert(d, out=f)
                np.bitwise_or(f, b, out=f)
                np.bitwise_xor(f, c, out=f)
        elif i < 32:
            np.bitwise_xor(b, c, out=f)
            np.bitwise_and(f, d, out=f)
            np.bitwise_xor(f, c, out=f)
        else:
            np.bitwise_xor(b, c, out=f)
            np.bitwise_xor(f, d, out=f)
        np.add(f, a, out=f)
        np.add(f, np.uint32(_SINES[i]), out=f)
        if _PLACES[i] in words:
            np.add(f, words[_PLACES[i]], out=f)
        np.left_shift(f, np.uint32(_SHIFTS[i]), out=g)
        np.right_shift(f, np.uint32(32 - _SHIFTS[i]), out=f)
        np.bitwise_or(f, g, out=f)
        np.add(f, b, out=f)
        a, b, c, d, f = d, f, b, c, a
    return (b + np.uint32(_START[0])).byteswap()


def _digits(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    text = x.astype("S20").view(np.uint8).reshape(len(x), 20)
    return text, (text != 0).sum(1)


def pair_draws(keys: str, u: np.ndarray, v: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """``u01(*keys, u[i], v[j], mode="md5")`` of each pair of i and j, keys joined by ``|``."""
    head = np.frombuffer(f"{keys}|".encode(), np.uint8)
    k = len(head)
    if k > 13:
        raise ValueError("the keys and two numbers must fit one block")
    (ours, many), (theirs, more) = _digits(u), _digits(v)
    out = np.empty(len(i))
    for size in np.unique(many):
        at = k + size + 1
        left, right = np.zeros((len(u), 64), np.uint8), np.zeros((len(v), 64), np.uint8)
        left[:, :k], left[:, k : k + 20], left[:, k + size] = head, ours, ord("|")
        right[:, at : at + 20] = theirs
        right[np.arange(len(v)), at + more] = 0x80
        left, right = left.view("<u4").T.copy(), right.view("<u4").T.copy()
        right[14] = 8 * (at + more)
        chosen = np.arange(len(i)) if len(np.unique(many)) == 1 else np.flatnonzero(many[i] == size)
        used = [w for w in range(16) if left[w].any() or right[w].any()]
        for start in range(0, len(chosen), _BLOCK):
            block = chosen[start : start + _BLOCK]
            a, b = i[block], j[block]
            words = {w: (left[w][a] if (w + 1) * 4 <= at else right[w][b] if w * 4 >= at else left[w][a] + right[w][b]) for w in used}
            out[block] = _md5_head(words, len(block))
    return out / 2.0**32
