"""Texts of an Arrow batch as NumPy arrays: bytes with offsets, words with hashes. Used inside tasks."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

#: Texts are worked on in slices of about so many bytes, so that a task's memory does not follow the batch.
SLICE_BYTES = 2 << 20
LONG_WORD = 32
_ODD = 0x9E3779B97F4A7C15
_MASK = (1 << 64) - 1


def byte_arrays(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of all texts one after another, and the offsets of each; a null text is empty."""
    column = column.cast(pa.large_binary())
    if column.null_count:
        column = column.fill_null(b"")
    n = len(column)
    if not n:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int64)[column.offset : column.offset + n + 1]
    held = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return held[at[0] : at[-1]], at - at[0]


def slices(offsets: np.ndarray, size: int = SLICE_BYTES) -> Iterator[tuple[int, int]]:
    """Ranges of rows with about size bytes; a longer text has a range of its own."""
    n, i = len(offsets) - 1, 0
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + size, "right")) - 1)
        yield i, j
        i = j


def mixed(h: np.ndarray) -> np.ndarray:
    """64-bit hashes spread over all bits."""
    h = h ^ (h >> np.uint64(32))
    h = h * np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(32)
    h *= np.uint64(0xD6E8FEB86659FD93)
    return h ^ (h >> np.uint64(32))


class Powers:
    """r**i and r**-i modulo 2**64, as far as asked for."""

    def __init__(self, r: int = _ODD):
        self.r, self.back = r, pow(r, -1, 1 << 64)
        self.up = self.down = np.ones(1, np.uint64)

    def to(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            n = max(n, SLICE_BYTES + 1)
            steps = np.full(n, self.r, np.uint64)
            steps[0] = 1
            self.up = np.multiply.accumulate(steps)
            steps = np.full(n, self.back, np.uint64)
            steps[0] = 1
            self.down = np.multiply.accumulate(steps)
        return self.up, self.down


def symbol_codes(seed: int = 11) -> np.ndarray:
    return np.random.default_rng(seed).integers(1, 1 << 63, 256, dtype=np.uint64) | np.uint64(1)


class Hasher:
    """Hashes of parts of a byte array, by prefix sums of a polynomial."""

    def __init__(self, seed: int = 11):
        self.codes, self.powers = symbol_codes(seed), Powers()

    def prefix(self, data: np.ndarray) -> np.ndarray:
        up, _ = self.powers.to(len(data) + 1)
        out = np.zeros(len(data) + 1, np.uint64)
        np.cumsum(self.codes[data] * up[: len(data)], out=out[1:])
        return out

    def parts(self, prefix: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        _, down = self.powers.to(len(prefix))
        return mixed((prefix[end] - prefix[start]) * down[start])

    def words(self, low: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """Hashes of words. Polynomials modulo 2**64 can be made to agree on long regular strings, so words of over LONG_WORD bytes get a digest."""
        out = self.parts(self.prefix(low), start, end)
        for k in np.flatnonzero(end - start > LONG_WORD).tolist():
            out[k] = int.from_bytes(hashlib.blake2b(low[start[k] : end[k]].tobytes(), digest_size=8).digest(), "little")
        return out


def class_table(word: str) -> np.ndarray:
    """Lower-cased byte, or 0 where it parts words. alnum: letters, digits and all beyond ASCII; visible: all but ASCII white space."""
    table = np.arange(256, dtype=np.uint8)
    table[65:91] += 32
    out = np.zeros(256, bool)
    if word == "alnum":
        out[48:58] = out[97:123] = out[128:] = True
        out = out[table]
    else:
        out[:] = True
        out[[32, 9, 10, 11, 12, 13]] = False
    if word == "visible":  # a zero byte is part of a word there
        return np.where(out, np.where(table == 0, 1, table), 0).astype(np.uint8)
    return np.where(out, table, 0).astype(np.uint8)


def words(low: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of the words in low (0 parts them; no word crosses texts), and offsets of the words of each text."""
    if not len(low):
        z = np.zeros(0, np.int64)
        return z, z, np.zeros(len(offsets), np.int64)
    inside = low != 0
    starts, ends = inside.copy(), inside.copy()
    starts[1:] &= ~inside[:-1]
    ends[:-1] &= ~inside[1:]
    first = offsets[:-1][offsets[:-1] < offsets[1:]]
    starts[first] = inside[first]
    last = offsets[1:][offsets[:-1] < offsets[1:]] - 1
    ends[last] = inside[last]
    s = np.flatnonzero(starts)
    return s, np.flatnonzero(ends) + 1, np.searchsorted(s, offsets)


def ranges(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """start, start+1, ... of each range, one after another."""
    total = int(lengths.sum())
    if not total:
        return np.zeros(0, np.int64)
    out = np.ones(total, np.int64)
    some = lengths > 0
    s, n = starts[some], lengths[some]
    at = np.cumsum(n)[:-1]
    out[0] = s[0]
    out[at] = s[1:] - s[:-1] - n[:-1] + 1
    return np.cumsum(out)
