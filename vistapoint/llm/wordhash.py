"""Vectorised hashing of the words of whole Arrow string columns (NumPy, no loop over words).

A word is a maximal run of bytes other than space and 0x09-0x0D. Its hash is a polynomial over Z/2^64 of random
per-byte codes, brought to the word's own origin and mixed, so equal words have equal hashes wherever they stand.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

U64 = np.uint64
CHUNK_BYTES = 1_000_000

_rng = np.random.Generator(np.random.PCG64(20_240_117))
BYTE_CODES = _rng.integers(1, 2**63, 256, dtype=U64) * U64(2) + U64(1)
_BASE = 0x9E3779B97F4A7C15
_BASE_INVERSE = pow(_BASE, -1, 2**64)
_SHINGLE_ODD = _rng.integers(1, 2**63, 64, dtype=U64) * U64(2) + U64(1)
SPACE = np.zeros(256, bool)
SPACE[[32, 9, 10, 11, 12, 13]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

_powers = {_BASE: np.ones(1, U64), _BASE_INVERSE: np.ones(1, U64)}


def powers(base: int, n: int) -> np.ndarray:
    """base**0 .. base**(n-1) modulo 2^64; grows by doubling and is kept by the worker."""
    have = _powers.setdefault(base, np.ones(1, U64))
    while len(have) < n:
        have = np.concatenate([have, have * U64(pow(base, len(have), 2**64))])
        _powers[base] = have
    return have[:n]


def mix(h: np.ndarray) -> np.ndarray:
    """A bijective finaliser on 64-bit values."""
    h = h ^ (h >> U64(32))
    h = h * U64(0xD6E8FEB86659FD93)
    h ^= h >> U64(32)
    h = h * U64(0xD6E8FEB86659FD93)
    return h ^ (h >> U64(32))


def byte_rows(column: pa.Array, chunk_bytes: int = CHUNK_BYTES) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(first row, bytes, row offsets in them) for runs of rows of about chunk_bytes; nulls count as empty; rows stay whole."""
    if column.null_count:
        column = pc.fill_null(column, "" if pa.types.is_string(column.type) or pa.types.is_large_string(column.type) else b"")
    width = np.int64 if pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type) else np.int32
    _, offsets, data = column.buffers()
    offsets = np.frombuffer(offsets, width)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    first = 0
    while first < len(column):
        last = int(np.searchsorted(offsets, offsets[first] + chunk_bytes, side="right")) - 1
        last = min(max(last, first + 1), len(column))
        yield first, data[offsets[first] : offsets[last]], offsets[first : last + 1] - offsets[first]
        first = last


def word_hashes(data: np.ndarray, offsets: np.ndarray, lower: bool = True, separators: np.ndarray = SPACE) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all words in order, and for each row where its words begin (length rows + 1).

    separators: which bytes stand between words; white space by default.
    """
    if not len(data):
        return np.zeros(0, U64), np.zeros(len(offsets), np.int64)
    space = separators[data]
    begins = ~space
    inner = offsets[(offsets > 0) & (offsets < len(data))]
    after_word = np.empty(len(data), bool)
    after_word[0] = False
    np.logical_not(space[:-1], out=after_word[1:])
    after_word[inner] = False
    begins &= ~after_word
    starts = np.flatnonzero(begins)
    if not len(starts):
        return np.zeros(0, U64), np.zeros(len(offsets), np.int64)
    codes = BYTE_CODES[LOWER[data] if lower else data]
    codes[space] = 0
    codes *= powers(_BASE, len(data))
    h = np.add.reduceat(codes, starts)
    h *= powers(_BASE_INVERSE, len(data))[starts]
    return mix(h), np.searchsorted(starts, offsets)


def stem_hashes(data: np.ndarray, offsets: np.ndarray, size: int, separators: np.ndarray = SPACE) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the first ``size`` bytes, lower-cased, of the words longer than that, and where each row's begin."""
    if len(data) <= size:
        return np.zeros(0, U64), np.zeros(len(offsets), np.int64)
    inside = ~separators[data]
    full = inside[: len(data) - size].copy()
    full[1:] &= ~inside[: len(data) - size - 1]
    for j in range(1, size + 1):
        full &= inside[j : len(data) - size + j]
    inner = offsets[(offsets > 0) & (offsets < len(data))]
    for cut in inner:  # a word may begin at a row's first byte, and none goes on past its last
        full[max(cut - size, 0) : cut] = False
        if cut < len(full) and inside[cut : cut + size + 1].all():
            full[cut] = True
    starts = np.flatnonzero(full)
    h = np.zeros(len(starts), U64)
    for j in range(size):
        h += BYTE_CODES[LOWER[data[starts + j]]] * U64(pow(_BASE, j + 7, 2**64))
    return mix(h), np.searchsorted(starts, offsets)


def shingle_hashes(words: np.ndarray, bounds: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of every run of ``size`` words in each row, rows in order, and where each row's begin.

    A row with fewer words, but at least one, has a single shingle: all its words.
    """
    counts = np.diff(bounds)
    n = np.where(counts >= size, counts - size + 1, np.minimum(counts, 1))
    out = np.concatenate([[0], np.cumsum(n)])
    at = np.arange(out[-1]) + np.repeat(bounds[:-1] - out[:-1], n)
    short = np.repeat(counts < size, n)
    h = np.zeros(out[-1], U64)
    ends = np.repeat(bounds[1:], n)
    for j in range(size):
        place = at + j
        inside = place < ends
        h += np.where(inside, words[np.minimum(place, max(len(words) - 1, 0))] if len(words) else U64(0), U64(0)) * _SHINGLE_ODD[j]
    h = mix(h)
    if short.any():
        h[short] ^= np.repeat(counts, n)[short].astype(U64) * _SHINGLE_ODD[63]
    return h, out


def distinct_in_rows(h: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The distinct values of each row, sorted, and where each row's begin."""
    h = h.copy()
    for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
        if b - a > 1:
            h[a:b].sort()
    first = np.ones(len(h), bool)
    first[1:] = h[1:] != h[:-1]
    first[bounds[:-1][bounds[:-1] < len(h)]] = True
    kept = np.concatenate([[0], np.cumsum(first)])
    return h[first], kept[bounds]


def row_reduce(ufunc: np.ufunc, values: np.ndarray, bounds: np.ndarray, empty: int) -> np.ndarray:
    """ufunc over each row's values; ``empty`` for rows without values."""
    out = np.full(len(bounds) - 1, empty, values.dtype)
    full = np.diff(bounds) > 0
    if full.any():
        out[full] = ufunc.reduceat(values, bounds[:-1][full])
    return out
