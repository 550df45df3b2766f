"""Vectorised hashing of words and chunks in UTF-8 buffers."""

from __future__ import annotations

import numpy as np

U64 = np.uint64
_rng = np.random.Generator(np.random.PCG64(20240607))
#: A random number for each byte value, for two independent hashes.
BYTE_KEYS = _rng.integers(1, 1 << 63, (2, 256), dtype=np.uint64) | U64(1)
BASES = (U64(0x9E3779B97F4A7C15), U64(0xD6E8FEB86659FD93))
GRAM_KEYS = _rng.integers(1, 1 << 63, 16, dtype=np.uint64) | U64(1)

SPACE_BYTES = bytes([0x20, *range(0x09, 0x0E)])


def byte_class(chars: bytes, inside: bool = True) -> np.ndarray:
    flags = np.full(256, not inside)
    flags[list(chars)] = inside
    return flags


#: Words are runs of anything but the six ASCII white-space characters.
NOT_SPACE = byte_class(SPACE_BYTES, inside=False)
#: Words are runs of ASCII letters and digits and of all bytes above ASCII.
WORDLIKE = byte_class(bytes([*range(0x30, 0x3A), *range(0x41, 0x5B), *range(0x61, 0x7B), *range(0x80, 0x100)]))
#: A-Z to a-z, all else as it is.
LOWER = np.arange(256, dtype=np.uint8)
LOWER[0x41:0x5B] += 32


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit numbers."""
    x = x ^ (x >> U64(30))
    x = x * U64(0xBF58476D1CE4E5B9)
    x ^= x >> U64(27)
    x *= U64(0x94D049BB133111EB)
    x ^= x >> U64(31)
    return x


def runs(raw: np.ndarray, offs: np.ndarray, inside: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, end (bytes) and row of each run of bytes in the class; runs end with their row."""
    n = len(raw)
    if not n:
        e = np.zeros(0, np.int64)
        return e, e, e
    yes = inside[raw]
    first = np.zeros(n + 1, bool)
    first[offs] = True
    start = yes.copy()
    start[1:] &= ~yes[:-1] | first[1:n]
    end = yes.copy()
    end[:-1] &= ~yes[1:] | first[1:n]
    starts = np.flatnonzero(start)
    ends = np.flatnonzero(end) + 1
    return starts, ends, np.searchsorted(offs, starts, "right") - 1


def powers(n: int, base: np.uint64) -> np.ndarray:
    out = np.full(max(n, 1), base, np.uint64)
    out[0] = 1
    return np.multiply.accumulate(out)


_tables: dict[int, tuple[np.ndarray, np.ndarray]] = {}
#: Buffers of more bytes are hashed without a table of powers as long as they are.
MOST_TABLE = 1 << 22


def _powers_of(which: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of a base and of its inverse, kept from call to call."""
    held = _tables.get(which)
    if held is None or len(held[0]) < n:
        size = 1 << max(18, (n - 1).bit_length())
        held = _tables[which] = powers(size, BASES[which]), powers(size, U64(pow(int(BASES[which]), -1, 1 << 64)))
    return held


def segment_hashes(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray, which: int = 0) -> np.ndarray:
    """A 64-bit hash of the bytes of each segment; segments ascend and don't overlap."""
    if not len(starts):
        return np.zeros(0, np.uint64)
    lens = ends - starts
    if len(raw) <= MOST_TABLE:  # differences of one running sum
        ahead, back = _powers_of(which, len(raw))
        total = np.zeros(len(raw) + 1, np.uint64)
        np.cumsum(BYTE_KEYS[which][raw] * ahead[: len(raw)], out=total[1:])
        values = (total[ends] - total[starts]) * back[starts]
    else:
        heads = np.cumsum(lens) - lens
        pos = np.arange(int(lens.sum())) - np.repeat(heads, lens)
        values = np.add.reduceat(BYTE_KEYS[which][raw[np.repeat(starts, lens) + pos]] * powers(int(lens.max()), BASES[which])[pos], heads)
    return mix64(values ^ (lens.astype(np.uint64) * U64(0xA24BAED4963EE407)))


def grams(h: np.ndarray, rows: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of k successive words of a row, and the index of each gram's first word."""
    n = len(h) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    out = h[:n] * GRAM_KEYS[0]
    for i in range(1, k):
        out = mix64(out) + h[i : n + i] * GRAM_KEYS[i]
    at = np.flatnonzero(rows[:n] == rows[k - 1 :])
    return mix64(out[at]), at
