"""Vectorised work on UTF-8 buffers of Arrow string columns: words, word hashes, n-gram hashes, XXH64 of slices."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

U = np.uint64
#: Words end at these bytes: space and the five controls from tab to carriage return.
SPACES = (0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D)


def space_table() -> np.ndarray:
    t = np.zeros(256, bool)
    t[list(SPACES)] = True
    return t


def lower_table() -> np.ndarray:
    t = np.arange(256, dtype=np.uint8)
    t[65:91] += 32
    return t


def slices(column, most: int = 1 << 20):
    """Cut an Arrow string column (nulls count as empty) into runs of at most `most` bytes or one text each.

    Yields first row, row after the last, the run's bytes, and its rows' offsets in them.
    """
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = (pc.fill_null(column, "") if column.null_count else column).cast(pa.large_string())
    n = len(column)
    if not n:
        return
    _, offs, data = column.buffers()
    off = np.frombuffer(offs, np.int64)[column.offset : column.offset + n + 1]
    buf = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    i = 0
    while i < n:
        j = max(i + 1, int(np.searchsorted(off, off[i] + most, "right")) - 1)
        yield i, j, buf[off[i] : off[j]], off[i : j + 1] - off[i]
        i = j


def word_bounds(buf: np.ndarray, off: np.ndarray, space: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of words, and for each text the number of words before it (one more at the end)."""
    n = len(buf)
    if not n:
        z = np.zeros(0, np.int64)
        return z, z, np.zeros(len(off), np.int64)
    word = ~space[buf]
    before = np.empty(n, bool)
    before[0] = False
    before[1:] = word[:-1]
    before[off[:-1][off[:-1] < n]] = False
    after = np.empty(n, bool)
    after[-1] = False
    after[:-1] = word[1:]
    ends = off[1:][off[1:] > 0] - 1
    after[ends] = False
    starts = np.flatnonzero(word & ~before)
    stops = np.flatnonzero(word & ~after) + 1
    return starts, stops, np.searchsorted(starts, off)


def mix(h: np.ndarray) -> np.ndarray:
    """A bijective scramble of 64-bit values."""
    h = h ^ (h >> U(33))
    h = h * U(0xFF51AFD7ED558CCD)
    h ^= h >> U(33)
    h = h * U(0xC4CEB9FE1A85EC53)
    return h ^ (h >> U(33))


class Rolling:
    """Hashes of runs of a sequence of 64-bit values, by differences of one running sum of value times power."""

    def __init__(self, base: int):
        self.base, self.back = U(base), U(pow(base, -1, 1 << 64))
        self.up = self.down = np.ones(1, np.uint64)

    def _powers(self, n: int) -> None:
        if len(self.up) < n:
            n = max(n, 1 << 16)
            for name, b in (("up", self.base), ("down", self.back)):
                p = np.full(n, b, np.uint64)
                p[0] = 1
                setattr(self, name, np.multiply.accumulate(p))

    def sums(self, values: np.ndarray) -> np.ndarray:
        self._powers(len(values) + 1)
        s = np.zeros(len(values) + 1, np.uint64)
        np.cumsum(values * self.up[: len(values)], out=s[1:])
        return s

    def runs(self, sums: np.ndarray, start: np.ndarray, stop: np.ndarray) -> np.ndarray:
        return mix((sums[stop] - sums[start]) * self.down[start])


def byte_values() -> np.ndarray:
    """A fixed odd-looking 64-bit value for each byte."""
    return mix(np.arange(1, 257, dtype=np.uint64) * U(0x9E3779B97F4A7C15))


BYTE_BASE, WORD_BASE = 0x5851F42D4C957F2D, 0x2545F4914F6CDD1D


class Hasher:
    """Word hashes of a buffer and hashes of n consecutive words; powers are kept between buffers."""

    def __init__(self):
        self.values, self.bytes, self.words = byte_values(), Rolling(BYTE_BASE), Rolling(WORD_BASE)

    def word(self, buf: np.ndarray, start: np.ndarray, stop: np.ndarray) -> np.ndarray:
        return self.bytes.runs(self.bytes.sums(self.values[buf]), start, stop) if len(start) else np.zeros(0, np.uint64)

    def grams(self, hashes: np.ndarray, n: int) -> np.ndarray:
        """Hash of words i to i + n - 1, for every i that has so many; the caller drops those across two texts."""
        if len(hashes) < n:
            return np.zeros(0, np.uint64)
        i = np.arange(len(hashes) - n + 1)
        return self.words.runs(self.words.sums(hashes), i, i + n)


def spread(first: np.ndarray, count: np.ndarray) -> np.ndarray:
    """first[k], first[k] + 1, ... count[k] values for each k, one after the other."""
    total = int(count.sum())
    if not total:
        return np.zeros(0, np.int64)
    at = np.cumsum(count) - count
    return np.repeat(first - at, count) + np.arange(total)


class HashIndex:
    """Open addressing from 64-bit hashes to consecutive numbers, for whole arrays at a time."""

    def __init__(self, most: int):
        self.bits = max(10, int(2 * most).bit_length())
        self.keys, self.number, self.used = np.zeros(1 << self.bits, np.uint64), np.zeros(1 << self.bits, np.int32), 0

    def find(self, h: np.ndarray) -> np.ndarray:
        """Number of each hash, -1 for those not held. Zero counts as another value."""
        h = np.where(h == 0, U(1), h)
        out = np.full(len(h), -1, np.int64)
        slot = (h >> U(64 - self.bits)).astype(np.int64)
        held = self.keys[slot]
        same = held == h
        out[same] = self.number[slot[same]]
        left = np.flatnonzero(~same & (held != 0))
        while len(left):
            slot[left] = (slot[left] + 1) & ((1 << self.bits) - 1)
            held = self.keys[slot[left]]
            same = held == h[left]
            out[left[same]] = self.number[slot[left[same]]]
            left = left[~same & (held != 0)]
        return out

    def add(self, h: np.ndarray) -> None:
        """Take in distinct hashes that are not held yet; they are numbered on."""
        h = np.where(h == 0, U(1), h)
        slot, left = (h >> U(64 - self.bits)).astype(np.int64), np.arange(len(h))
        while len(left):
            free = left[self.keys[slot[left]] == 0]
            self.keys[slot[free]] = h[free]
            won = free[self.keys[slot[free]] == h[free]]
            self.number[slot[won]] = self.used + won
            done = np.zeros(len(h), bool)
            done[won] = True
            left = left[~done[left]]
            slot[left] = (slot[left] + 1) & ((1 << self.bits) - 1)
        self.used += len(h)


# XXH64: fixed values of the published algorithm.
X1, X2, X3, X4, X5 = 0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5


def _left(x: np.ndarray, r: int) -> np.ndarray:
    return (x << U(r)) | (x >> U(64 - r))


def xxh64(buf: np.ndarray, start: np.ndarray, length: np.ndarray, seed: int = 42) -> np.ndarray:
    """XXH64 of many slices of one buffer at once; the rare long slice goes to the library's own routine."""
    import xxhash

    if not len(start):
        return np.zeros(0, np.uint64)
    buf = np.concatenate([buf, np.zeros(8, np.uint8)])
    u8 = np.ndarray((len(buf) - 7,), "<u8", buf, 0, (1,))
    u4 = np.ndarray((len(buf) - 3,), "<u4", buf, 0, (1,))
    h = np.full(len(start), (seed + X5) & (1 << 64) - 1, np.uint64) + length.astype(np.uint64)
    big = np.flatnonzero(length >= 256)
    mid = np.flatnonzero((length >= 32) & (length < 256))
    if len(mid):
        p, left = start[mid], length[mid] // 32
        lanes = [np.full(len(mid), v & (1 << 64) - 1, np.uint64) for v in (seed + X1 + X2, seed + X2, seed, seed - X1)]
        for s in range(int(left.max())):
            on = np.flatnonzero(left > s)
            for k in range(4):
                lanes[k][on] = _left(lanes[k][on] + u8[p[on] + 32 * s + 8 * k] * U(X2), 31) * U(X1)
        g = _left(lanes[0], 1) + _left(lanes[1], 7) + _left(lanes[2], 12) + _left(lanes[3], 18)
        for v in lanes:
            g = (g ^ (_left(v * U(X2), 31) * U(X1))) * U(X1) + U(X4)
        h[mid] = g + length[mid].astype(np.uint64)
    rest = length % 32
    at = start + length - rest
    for _ in range(3):
        on = np.flatnonzero(rest >= 8)
        if not len(on):
            break
        h[on] = _left(h[on] ^ (_left(u8[at[on]] * U(X2), 31) * U(X1)), 27) * U(X1) + U(X4)
        at[on] += 8
        rest[on] -= 8
    on = np.flatnonzero(rest >= 4)
    h[on] = _left(h[on] ^ (u4[at[on]].astype(np.uint64) * U(X1)), 23) * U(X2) + U(X3)
    at[on] += 4
    rest[on] -= 4
    for _ in range(3):
        on = np.flatnonzero(rest > 0)
        h[on] = _left(h[on] ^ (buf[at[on]].astype(np.uint64) * U(X5)), 11) * U(X1)
        at[on] += 1
        rest[on] -= 1
    h ^= h >> U(33)
    h *= U(X2)
    h ^= h >> U(29)
    h *= U(X3)
    h ^= h >> U(32)
    raw = buf.data
    for k in big:
        h[k] = xxhash.xxh64_intdigest(raw[start[k] : start[k] + length[k]], seed)
    return h
