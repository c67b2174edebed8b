"""Vectorised words and word windows over Arrow batches of texts.

A word is a maximal run of bytes other than 0x20 and 0x09-0x0D of the UTF-8 text, so
``[^\\x20\\x09-\\x0D]+``.  Every word gets a 64-bit fingerprint and a window of k words gets
one from the fingerprints of its words.  All work is numpy over the concatenated bytes of a
slab of texts; a slab holds about ``SLAB_BYTES`` (more only if one text is longer), which
bounds the memory of a worker whatever the batch size is.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

SLAB_BYTES = 1 << 18
_U = np.uint64
_BASE = _U(0x9E3779B97F4A7C15)
_INVERSE = _U(pow(0x9E3779B97F4A7C15, -1, 1 << 64))


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser on uint64 (xor-shift and multiply, three rounds)."""
    x = x ^ (x >> _U(30))
    x = x * _U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> _U(27))
    x = x * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


def _byte_values(lower: bool) -> np.ndarray:
    codes = np.arange(256, dtype=np.uint64)
    if lower:
        codes[65:91] += _U(32)
    return mix(codes + _U(0x5DEECE66D)) | _U(1)


_VALUES = {flag: _byte_values(flag) for flag in (False, True)}
_IS_SPACE = np.zeros(256, dtype=bool)
_IS_SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
_powers: dict[str, np.ndarray] = {}


def _power(name: str, base: np.uint64, n: int) -> np.ndarray:
    have = _powers.get(name)
    if have is None or len(have) < n:
        size = max(n, SLAB_BYTES + (1 << 16))
        steps = np.full(size, base, dtype=np.uint64)
        steps[0] = 1
        made = np.cumprod(steps)
        if size > 4 * SLAB_BYTES:
            return made
        have = _powers[name] = made
    return have


def strings(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and n + 1 offsets of a string column; a null reads as an empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.fill_null("")
    kind = np.int64 if pa.types.is_large_string(column.type) else np.int32
    _, ends, data = column.buffers()
    ends = np.frombuffer(ends, dtype=kind)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    if data is None:
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    return np.frombuffer(data, dtype=np.uint8)[ends[0] : ends[-1]], ends - ends[0]


def slabs(offsets: np.ndarray, limit: int = SLAB_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges whose texts add up to at most ``limit`` bytes, or hold one row."""
    at, n = 0, len(offsets) - 1
    while at < n:
        to = int(np.searchsorted(offsets, offsets[at] + limit, side="right")) - 1
        to = min(max(to, at + 1), n)
        yield at, to
        at = to


def word_spans(data: np.ndarray, offsets: np.ndarray, between: np.ndarray = _IS_SPACE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start and end byte of each word, and the n + 1 word offsets of the texts; ``between`` marks the bytes of no word."""
    inside = ~between[data]
    first = inside.copy()
    first[1:] &= ~inside[:-1]
    last = inside.copy()
    last[:-1] &= ~inside[1:]
    cuts = offsets[1:-1]
    cuts = cuts[(cuts > 0) & (cuts < len(data))]
    first[cuts] |= inside[cuts]
    last[cuts - 1] |= inside[cuts - 1]
    starts, ends = np.flatnonzero(first), np.flatnonzero(last) + 1
    return starts, ends, np.searchsorted(starts, offsets, side="left")


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, lower: bool = False) -> np.ndarray:
    """A 64-bit fingerprint of each word, from one running sum over the bytes."""
    if not len(starts):
        return np.zeros(0, np.uint64)
    n = len(data)
    total = np.zeros(n + 1, dtype=np.uint64)
    np.cumsum(_VALUES[lower][data] * _power("base", _BASE, n + 1)[:n], out=total[1:])
    body = (total[ends] - total[starts]) * _power("inverse", _INVERSE, n + 1)[starts]
    return mix(body + mix((ends - starts).astype(np.uint64)))


def window_hashes(words: np.ndarray, k: int, seed: int = 0) -> np.ndarray:
    """Fingerprints of all runs of k words (those that cross texts too: mask them by offsets)."""
    n = len(words) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    factor = mix(np.array([2 * seed + 1], dtype=np.uint64))[0] | _U(1)
    out = np.zeros(n, dtype=np.uint64)
    with np.errstate(over="ignore"):
        for j in range(k):
            out *= factor
            out += words[j : j + n]
    return mix(out ^ _U(k))


def each_slab(column: pa.Array, lower: bool = False) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, row after the last, word fingerprints, word offsets of these rows)."""
    data, offsets = strings(column)
    for at, to in slabs(offsets):
        part, own = data[offsets[at] : offsets[to]], offsets[at : to + 1] - offsets[at]
        starts, ends, bounds = word_spans(part, own)
        yield at, to, word_hashes(part, starts, ends, lower), bounds
