"""Vectorised word splitting and hashing over the byte buffers of Arrow string columns.

Words are maximal runs of bytes other than 0x20 and 0x09-0x0D; in UTF-8 those bytes never occur
inside a longer character, so this equals splitting the decoded text. All hashes are 64-bit,
fixed by seeds below and equal in every process.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

U = np.uint64
_rng = np.random.default_rng(20240229)
BYTE_CODE = _rng.integers(1, 2**63, 256, dtype=np.uint64) * U(2) + U(1)
_P = U(0x9E3779B97F4A7C15)
_P_INV = U(pow(0x9E3779B97F4A7C15, -1, 2**64))
_Q = [U(pow(0xD1342543DE82EF95, j + 1, 2**64)) for j in range(64)]
IS_SPACE = np.zeros(256, bool)
IS_SPACE[[0x20, *range(0x09, 0x0E)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[0x41:0x5B] += 0x20
CHUNK_BYTES = 1 << 20


def mix(h: np.ndarray) -> np.ndarray:
    """The finaliser of a public 64-bit hash: every input bit reaches every output bit."""
    h = h ^ (h >> U(33))
    h = h * U(0xFF51AFD7ED558CCD)
    h ^= h >> U(33)
    h *= U(0xC4CEB9FE1A85EC53)
    h ^= h >> U(33)
    return h


class _Powers:
    """Powers of the byte multiplier and of its inverse modulo 2**64, grown on demand."""

    def __init__(self) -> None:
        self.up = self.down = np.ones(1, np.uint64)

    def to(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            size = max(n, CHUNK_BYTES + 1)
            for name, base in (("up", _P), ("down", _P_INV)):
                steps = np.full(size, base, np.uint64)
                steps[0] = 1
                setattr(self, name, np.cumprod(steps, dtype=np.uint64))
        return self.up, self.down


_POWERS = _Powers()


def text_buffer(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and row offsets of a string column; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = pc.fill_null(column, "")
    wide = pa.types.is_large_string(column.type)
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    if len(column) == 0:
        at = np.zeros(1, np.int64)
    return (np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)), at


def row_chunks(offsets: np.ndarray, limit: int = CHUNK_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges of about ``limit`` bytes; a longer row makes a range of its own."""
    n, i = len(offsets) - 1, 0
    while i < n:
        j = int(np.searchsorted(offsets, offsets[i] + limit, "right")) - 1
        j = min(max(j, i + 1), n)
        yield i, j
        i = j


class Words:
    """The words of some rows: byte ranges, hashes, and each row's range of words."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, lower: bool = False, separator: np.ndarray = IS_SPACE) -> None:
        lo, hi = int(offsets[0]), int(offsets[-1])
        self.raw = data[lo:hi]
        self.at = at = offsets - lo
        n = hi - lo
        inside = ~separator[self.raw]
        first = np.zeros(n + 1, bool)
        first[at] = True
        before = np.zeros(n, bool)
        before[1:] = inside[:-1]
        starts = np.flatnonzero(inside & (~before | first[:-1]))
        after = np.zeros(n, bool)
        after[:-1] = inside[1:]
        ends = np.flatnonzero(inside & (~after | first[1:])) + 1
        self.starts, self.ends = starts, ends
        self.row_words = np.searchsorted(starts, at)
        folded = LOWER[self.raw] if lower else self.raw
        self.bytes = folded
        up, down = _POWERS.to(n + 1)
        sums = np.zeros(n + 1, np.uint64)
        np.cumsum(BYTE_CODE[folded] * up[:n], out=sums[1:])
        self.sums, self.down = sums, down
        self.hashes = mix((sums[ends] - sums[starts]) * down[starts]) if len(starts) else np.zeros(0, np.uint64)

    def joined(self, keep: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Bytes of each row's words (or of those that ``keep`` marks) with one space between, and where
        each row's begin."""
        starts, ends, cut = self.starts, self.ends, self.row_words
        if keep is not None:
            kept = np.flatnonzero(keep)
            starts, ends, cut = starts[kept], ends[kept], np.searchsorted(kept, cut)
        edge = np.zeros(len(self.raw) + 1, np.int8)
        edge[starts] += 1
        edge[ends] -= 1
        inside = np.cumsum(edge[:-1], dtype=np.int8).view(bool)
        followed = np.ones(len(starts), bool)
        followed[cut[1:][np.diff(cut) > 0] - 1] = False
        gaps = ends[followed]
        inside[gaps] = True
        out = self.raw.copy()
        out[gaps] = 0x20
        return out[inside], np.concatenate([[0], np.cumsum(inside)])[self.at]

    def prefix_hashes(self, n: int) -> np.ndarray:
        """Hash of the first n bytes of each word (all of a shorter one)."""
        if not len(self.starts):
            return np.zeros(0, np.uint64)
        ends = np.minimum(self.ends, self.starts + n)
        return mix((self.sums[ends] - self.sums[self.starts]) * self.down[self.starts] + U(n))

    def grams(self, n: int) -> np.ndarray:
        """Hash of the n words from each word on; entries whose window leaves its row are garbage."""
        m = len(self.hashes) - n + 1
        if m <= 0:
            return np.zeros(0, np.uint64)
        out = self.hashes[:m] * _Q[0]
        for j in range(1, n):
            out += self.hashes[j : j + m] * _Q[j]
        return mix(out)


def sequence_hash(hashes: np.ndarray) -> np.uint64:
    """Hash of a whole (short) word sequence; differs from any window hash of other length."""
    total = (hashes * np.array(_Q[: len(hashes)], np.uint64)).sum(dtype=np.uint64, keepdims=True)
    return mix(total + np.array([len(hashes)], np.uint64) * _Q[40])[0]


def signed(a: np.ndarray) -> np.ndarray:
    return a.view(np.int64)


def list_column(values: np.ndarray, counts: np.ndarray | list[int], kind: pa.DataType | None = None) -> pa.ListArray:
    at = np.zeros(len(counts) + 1, np.int32)
    np.cumsum(counts, out=at[1:])
    return pa.ListArray.from_arrays(pa.array(at, pa.int32()), pa.array(values, kind or pa.int64()))
