"""Vectorised text work for Arrow batches: bytes, words, shingles and their hashes.

All of it runs on slices of at most about ``SLICE`` characters, so memory stays
bounded by the longest single text, not by the batch.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

#: Bytes or characters worked on at once.
SLICE = 1_000_000
U = np.uint64
_RNG = np.random.default_rng(20240607)
_BYTE = _RNG.integers(0, 2**63, 256, dtype=U) * U(2) + U(1)
_ODD = _RNG.integers(0, 2**63, 16, dtype=U) * U(2) + U(1)
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_P = 0x9E3779B97F4A7C15
_P_INVERSE = pow(_P, -1, 2**64)
_powers: dict[int, np.ndarray] = {}


def powers(base: int, n: int) -> np.ndarray:
    """base**0 .. base**(n-1) modulo 2**64."""
    have = _powers.get(base)
    if have is None or len(have) < n:
        size = max(n, SLICE + 200_000)
        out = np.full(size, base, dtype=U)
        out[0] = 1
        _powers[base] = have = np.multiply.accumulate(out)
    return have[:n]


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijective scramble of 64-bit numbers."""
    x = x ^ (x >> U(32))
    x = x * U(0xD6E8FEB86659FD93)
    x ^= x >> U(32)
    x = x * U(0xD6E8FEB86659FD93)
    return x ^ (x >> U(32))


def slices(lengths: np.ndarray, most: int = SLICE) -> Iterator[tuple[int, int]]:
    """Row ranges whose lengths sum to about ``most``."""
    ends = np.cumsum(lengths)
    begin = 0
    while begin < len(lengths):
        before = ends[begin - 1] if begin else 0
        end = max(begin + 1, int(np.searchsorted(ends, before + most, side="right")))
        yield begin, end
        begin = end


def raw(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of all texts and their offsets; null is empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_string()).fill_null("")
    if not len(column):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, offsets, data = column.buffers()
    offsets = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
    data = np.frombuffer(data, np.uint8) if data else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def runs(inside: np.ndarray, cuts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Begin and end of the runs where ``inside`` holds; no run crosses a cut."""
    if not len(inside):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    first, last = inside.copy(), inside.copy()
    first[1:] &= ~inside[:-1]
    last[:-1] &= ~inside[1:]
    at = cuts[(cuts > 0) & (cuts < len(inside))]
    first[at] = inside[at]
    last[at - 1] = inside[at - 1]
    return np.flatnonzero(first), np.flatnonzero(last) + 1


def span_hashes(codes: np.ndarray, begin: np.ndarray, end: np.ndarray) -> np.ndarray:
    """64-bit hashes of the spans of ``codes`` (uint64, already spread)."""
    total = np.zeros(len(codes) + 1, dtype=U)
    np.cumsum(codes * powers(_P, len(codes)), out=total[1:])
    out = (total[end] - total[begin]) * powers(_P_INVERSE, len(codes) + 1)[begin]
    return mixed(out + (end - begin).astype(U) * _ODD[15])


def word_hashes(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the words (A-Z lowered) of texts and the index of each text's first word."""
    low = _LOWER[data]
    begin, end = runs(~_SPACE[low], offsets)
    return span_hashes(_BYTE[low], begin, end), np.searchsorted(begin, offsets)


def shingle_sets(data: np.ndarray, offsets: np.ndarray, k: int = 5) -> list[np.ndarray]:
    """For each text the sorted distinct hashes of its k-word shingles.

    A text of fewer words has its whole word sequence as the only one; a text
    without words has none.
    """
    words, at = word_hashes(data, offsets)
    n = len(words)
    grams = np.zeros(max(n - k + 1, 0), dtype=U)
    for i in range(k):
        grams += words[i : i + len(grams)] * _ODD[i]
    grams = mixed(grams)
    out = []
    for a, b in zip(at[:-1].tolist(), at[1:].tolist()):
        if b - a >= k:
            own = grams[a : b - k + 1].copy()
            own.sort()
            if len(own) > 1:
                own = own[np.concatenate(([True], own[1:] != own[:-1]))]
        elif b > a:
            own = mixed((words[a:b] * _ODD[: b - a]).sum(keepdims=True, dtype=U) + np.array([b - a], dtype=U) * _ODD[14])
        else:
            own = np.zeros(0, dtype=U)
        out.append(own)
    return out
