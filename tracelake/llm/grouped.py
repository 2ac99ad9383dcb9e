"""Groups of rows from Arrow batches that are sorted by group.

A task reads its sorted partition as a stream; only the rows of one group, or of
several small ones, are held at once.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa


def whole_groups(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[tuple[pa.Table, np.ndarray]]:
    """Tables that hold whole groups only, with the offsets of the groups."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        edge = _bounds([batch], keys)
        joins = bool(held) and all(held[-1].column(k)[-1] == batch.column(k)[0] for k in keys)
        if len(edge) == 2 and (joins or not held):
            held.append(batch)
            continue
        if not joins and held:
            yield _table(held, keys)
            held = []
        cut = int(edge[-2])
        if cut:
            yield _table([*held, batch.slice(0, cut)], keys)
            held = []
        held.append(batch.slice(cut))
    if held:
        yield _table(held, keys)


def starts(batch: pa.RecordBatch, keys: list[str]) -> np.ndarray:
    """Where the runs of equal keys begin in one batch, and its end."""
    return _bounds([batch], keys) if batch.num_rows else np.zeros(1, dtype=np.int64)


def _bounds(batches: list[pa.RecordBatch], keys: list[str]) -> np.ndarray:
    n = sum(b.num_rows for b in batches)
    new = np.zeros(n, dtype=bool)
    new[0] = True
    for k in keys:
        x = np.concatenate([b.column(k).to_numpy(zero_copy_only=False) for b in batches])
        new[1:] |= x[1:] != x[:-1]
    return np.append(np.flatnonzero(new), n)


def _table(batches: list[pa.RecordBatch], keys: list[str]) -> tuple[pa.Table, np.ndarray]:
    return pa.Table.from_batches(batches).combine_chunks(), _bounds(batches, keys)


class Forest:
    """Union-find over the numbers 0..n-1; ``links`` are the unions that joined two trees."""

    def __init__(self, n: int) -> None:
        self.up = list(range(n))
        self.links: list[tuple[int, int]] = []

    def root(self, x: int) -> int:
        up = self.up
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    def join(self, a: int, b: int) -> None:
        ra, rb = self.root(a), self.root(b)
        if ra != rb:
            self.up[max(ra, rb)] = min(ra, rb)
            self.links.append((a, b))
