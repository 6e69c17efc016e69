"""Word arrays over Arrow text columns without a Python object per word.

A text column arrives as one byte buffer plus offsets.  Words are found with byte masks over the
whole buffer, and each word gets a 64-bit polynomial hash from one running sum: with powers of an odd
base B modulo 2^64, ``(S[end] - S[start]) * B^-start`` does not depend on where the word stands.
UTF-8 makes byte masks safe: bytes of 0x80 and above never occur in ASCII characters.

Nulls count as empty texts.  Memory is bounded by ``SLICE`` bytes of text, or by one text if that is longer.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

#: Bytes of text handled at once, and bytes hashed at once.
SLICE = 2 << 20
CHUNK = 1 << 20

_BASE = 0x9E3779B97F4A7C15
_BASE_INV = pow(_BASE, -1, 1 << 64)
_U = np.uint64

_ascii_lower = np.arange(256, dtype=np.uint8)
_ascii_lower[65:91] += 32
_plain = np.arange(256, dtype=np.uint8)

#: Word bytes of the two word rules: anything but white space, and letters, digits or non-ASCII.
_not_space = np.ones(256, dtype=bool)
_not_space[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = False
_alnum = np.zeros(256, dtype=bool)
_alnum[48:58] = _alnum[65:91] = _alnum[97:123] = _alnum[128:] = True
RULES = {"space": _not_space, "alnum": _alnum}

_powers: list[np.ndarray] = [np.ones(1, dtype=_U), np.ones(1, dtype=_U)]


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_powers[0]) < n:
        size = 1 << int(n - 1).bit_length()
        for k, base in enumerate((_BASE, _BASE_INV)):
            steps = np.full(size, base, dtype=_U)
            steps[0] = 1
            _powers[k] = np.multiply.accumulate(steps)
    return _powers[0], _powers[1]


def mix(h: np.ndarray, salt: int = 0) -> np.ndarray:
    """Spread every bit of a 64-bit value over the whole word."""
    h = h ^ _U(salt & 0xFFFFFFFFFFFFFFFF)
    h = (h ^ (h >> _U(30))) * _U(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> _U(27))) * _U(0x94D049BB133111EB)
    return h ^ (h >> _U(31))


def buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and int64 offsets (n+1) of a string or binary column; a null is an empty range."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("" if pa.types.is_string(column.type) or pa.types.is_large_string(column.type) else b"")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offsets, data = column.buffers()
    n = len(column)
    if n == 0 or data is None:
        return np.zeros(0, dtype=np.uint8), np.zeros(n + 1, dtype=np.int64)
    at = np.frombuffer(offsets, dtype=np.int64 if wide else np.int32)[column.offset : column.offset + n + 1].astype(np.int64)
    return np.frombuffer(data, dtype=np.uint8)[at[0] : at[-1]], at - at[0]


def slices(offsets: np.ndarray, most: int = SLICE) -> Iterator[tuple[int, int]]:
    """Ranges of rows whose texts have at most ``most`` bytes together, or one longer row."""
    i, n = 0, len(offsets) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + most, side="right")) - 1)
        yield i, j
        i = j


class Words:
    """Words of a run of texts: hashes, byte ranges and the first word of each text (n+1 entries)."""

    __slots__ = ("data", "ends", "first", "hashes", "starts")

    def __init__(self, data: np.ndarray, offsets: np.ndarray, rule: str = "space", lower: bool = True, salt: int = 0):
        inside = RULES[rule]
        fold = _ascii_lower if lower else _plain
        base = int(offsets[0])
        data = data[base : int(offsets[-1])]
        offsets = offsets - base
        n = len(data)
        edge = np.zeros(n + 1, dtype=bool)
        edge[offsets] = True
        starts, ends, hashes = [], [], []
        a = 0
        while a < n:
            b = min(a + CHUNK, n)
            while b < n and not edge[b] and inside[data[b]] and inside[data[b - 1]]:  # not within a word
                rest = data[b : b + CHUNK]
                stop = np.flatnonzero(~inside[rest] | edge[b : b + len(rest)])
                b += int(stop[0]) if len(stop) else len(rest)
            part = data[a:b]
            word = inside[part]
            cut = edge[a : b + 1]
            before = np.empty(len(part) + 1, dtype=bool)
            before[0] = before[-1] = False
            before[1:-1] = word[:-1]
            after = np.empty(len(part), dtype=bool)
            after[-1] = False
            after[:-1] = word[1:]
            s = np.flatnonzero(word & (~before[:-1] | cut[:-1]))
            e = np.flatnonzero(word & (~after | cut[1:])) + 1
            up, down = _power_tables(len(part) + 1)
            total = np.zeros(len(part) + 1, dtype=_U)
            np.cumsum((fold[part].astype(_U) + _U(1)) * up[: len(part)], out=total[1:])
            hashes.append(mix((total[e] - total[s]) * down[s], salt))
            starts.append(s + a)
            ends.append(e + a)
            a = b
        none = np.zeros(0, dtype=np.int64)
        self.data = data
        self.starts = np.concatenate(starts) if starts else none
        self.ends = np.concatenate(ends) if ends else none
        self.hashes = np.concatenate(hashes) if hashes else none.astype(_U)
        self.first = np.searchsorted(self.starts, offsets)

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    def owners(self) -> np.ndarray:
        """Row of each word."""
        return np.repeat(np.arange(len(self.first) - 1), self.counts)


def word_runs(column: pa.Array, rule: str = "space", lower: bool = True, most: int = SLICE) -> Iterator[tuple[int, int, Words]]:
    """Rows i..j of a text column with their words, slice by slice."""
    data, offsets = buffers(column)
    for i, j in slices(offsets, most):
        yield i, j, Words(data, offsets[i : j + 1], rule, lower)


def grams(hashes: np.ndarray, k: int) -> np.ndarray:
    """Hash of each k consecutive entries (across texts: the caller masks the ends)."""
    n = len(hashes) - k + 1
    if n <= 0:
        return np.zeros(0, dtype=_U)
    out = hashes[:n].copy()
    for i in range(1, k):
        out = out * _U(_BASE) + hashes[i : i + n]
    return mix(out, k)


def gram_starts(first: np.ndarray, k: int) -> np.ndarray:
    """Positions at which k words of one text follow."""
    counts = np.diff(first)
    n = int(first[-1])
    ok = np.ones(n, dtype=bool)
    short = np.minimum(counts, k - 1)
    if k > 1 and n:
        stop = np.zeros(n + 1, dtype=np.int64)
        np.add.at(stop, first[1:] - short, 1)
        np.add.at(stop, first[1:], -1)
        ok = np.cumsum(stop[:-1]) == 0
    return np.flatnonzero(ok)


def pack(values: np.ndarray, bounds: np.ndarray) -> pa.Array:
    """One binary value per row out of a flat array and the row bounds (n+1, in entries)."""
    raw = np.ascontiguousarray(values)
    at = (bounds * raw.itemsize).astype(np.int32)
    return pa.Array.from_buffers(pa.binary(), len(bounds) - 1, [None, pa.py_buffer(at), pa.py_buffer(raw)])


def signed(values: np.ndarray) -> np.ndarray:
    return values.view(np.int64)


def hash_ranges(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Hashes of byte ranges in order, as those of words, some ranges at a time."""
    out = np.empty(len(starts), dtype=_U)
    i = 0
    while i < len(starts):
        j = max(i + 1, int(np.searchsorted(ends, starts[i] + CHUNK, side="right")))
        a, b = int(starts[i]), int(ends[j - 1])
        up, down = _power_tables(b - a + 1)
        total = np.zeros(b - a + 1, dtype=_U)
        np.cumsum((data[a:b].astype(_U) + _U(1)) * up[: b - a], out=total[1:])
        s, e = starts[i:j] - a, ends[i:j] - a
        out[i:j] = mix((total[e] - total[s]) * down[s])
        i = j
    return out


def spread(begins: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Positions of ranges, one range after another: begin, begin + 1, ... for each."""
    total = int(lengths.sum())
    if not total:
        return np.zeros(0, dtype=np.int64)
    used = lengths > 0
    begins, lengths = begins[used], lengths[used]
    step = np.ones(total, dtype=np.int64)
    at = np.cumsum(lengths)[:-1]
    step[0] = begins[0]
    step[at] = begins[1:] - (begins[:-1] + lengths[:-1] - 1)
    return np.cumsum(step)
