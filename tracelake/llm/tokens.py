"""Token ids of whole texts with a public byte-level tokenizer, by way of distinct pre-tokens.

The tokenizer splits a text by a fixed pattern and encodes every piece on its
own. A large batch has far fewer distinct pieces than pieces, so the split runs
on code-point arrays, pieces are hashed, and only pieces that a worker has not
met yet go through the tokenizer. Ids are those of the tokenizer: the strings of
the file's added tokens, where a text holds them, are cut out first and get their
own ids, as the tokenizer does unless it is told to take them for ordinary text.
"""

from __future__ import annotations

import json
import re
from functools import lru_cache
from pathlib import Path

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from tracelake.llm import textvec
from tracelake.llm.textvec import U

#: A piece store that has grown beyond this many pieces is begun anew.
MOST_PIECES = 500_000
_OTHER, _LETTER, _DIGIT, _SPACE = 0, 1, 2, 3


@lru_cache(maxsize=1)
def _classes() -> np.ndarray:
    """Class of every code point as the tokenizer's pattern sees it."""
    import regex

    every = "".join(map(chr, [*range(0xD800), *range(0xE000, 0x110000)]))
    out = np.zeros(0x110000, dtype=np.uint8)
    for value, pattern in ((_LETTER, r"\p{L}+"), (_DIGIT, r"\p{N}+"), (_SPACE, r"\s+")):
        for m in regex.finditer(pattern, every):
            begin, end = (ord(every[m.start()]), ord(every[m.end() - 1]) + 1)
            out[begin:end] = value
    out[0xD800:0xE000] = _OTHER
    return out


def piece_bounds(points: np.ndarray, cuts: np.ndarray) -> np.ndarray:
    """Begins of the pieces of concatenated texts; ``cuts`` are the texts' begins.

    The rules: a contraction after an apostrophe that begins a piece; a run of
    letters, of digits or of other signs, with one blank before it; of a run of
    white space before something else, all but the last sign.
    """
    n = len(points)
    kind = _classes()[points]
    first = np.zeros(n, dtype=bool)
    first[cuts] = True
    last = np.zeros(n, dtype=bool)
    last[:-1] = first[1:]
    last[-1] = True
    change = first.copy()
    change[1:] |= kind[1:] != kind[:-1]
    space = kind == _SPACE
    begins = change.copy()
    # The last of a run of white space that something else follows stands alone,
    # or, being a blank, goes with what follows.
    follows = np.zeros(n, dtype=bool)
    follows[:-1] = space[:-1] & ~space[1:]
    follows &= ~last
    begins |= follows
    lead = np.flatnonzero(follows & (points == 32))
    begins[lead + 1] = False
    # Contractions: an apostrophe at the begin of a piece, and one of the endings.
    quote = np.flatnonzero(begins & (points == 39))
    if len(quote):
        padded = np.concatenate([points, np.zeros(3, points.dtype)])
        inside = np.concatenate([~first, np.zeros(3, dtype=bool)])
        one, two = padded[quote + 1], padded[quote + 2]
        here, there = inside[quote + 1], inside[quote + 1] & inside[quote + 2]
        short = here & np.isin(one, [ord(c) for c in "stmd"])
        long = there & (((one == ord("r")) & (two == ord("e"))) | ((one == ord("v")) & (two == ord("e"))) | ((one == ord("l")) & (two == ord("l"))))
        for at, size in ((quote[short], 2), (quote[long], 3)):
            begins[at + 1] = False
            after = at + size
            begins[after[after < n]] = True
            if size == 3:
                begins[at + 2] = False
    return np.flatnonzero(begins)


@lru_cache(maxsize=1)
def _byte_signs() -> dict[str, int]:
    """Byte-level vocabularies write a byte as a printable sign: itself, or the next free one from 256 on."""
    printable = [*range(33, 127), *range(161, 173), *range(174, 256)]
    others = [b for b in range(256) if b not in printable]
    return {chr(b): b for b in printable} | {chr(256 + i): b for i, b in enumerate(others)}


def _token_bytes(token: str) -> bytes:
    return bytes(_byte_signs()[c] for c in token)


class Pieces:
    """Ids of pieces by hash, filled as they are met."""

    def __init__(self, path: str, added: bool = True) -> None:
        """``added``: whether the strings of added tokens in a text are these tokens, or ordinary text."""
        import tiktoken

        # Same vocabulary, same ids: merges rank as their ids do. This encoder
        # takes single pieces, without the bookkeeping of a whole tokenizer.
        held = json.loads(Path(path).read_text())
        own = {t["content"]: t for t in held["added_tokens"]}
        if held["normalizer"] is not None or any(t["single_word"] or t["lstrip"] or t["rstrip"] for t in own.values()):
            raise ValueError(f"{path}: normalising and added tokens that take in their neighbours aren't supported")
        self.added = {content: t["id"] for content, t in own.items()} if added else {}
        # Of added tokens that begin at one place, the longest is meant.
        self._cut = re.compile("|".join(map(re.escape, sorted(self.added, key=len, reverse=True)))) if self.added else None
        ranks = {_token_bytes(token): rank for token, rank in held["model"]["vocab"].items() if token not in own}
        self.encoder = tiktoken.Encoding("pieces", pat_str=r"(?s:.+)", mergeable_ranks=ranks, special_tokens={})
        self._code = np.random.default_rng(5).integers(0, 2**63, 2**16, dtype=U) * U(2) + U(1)
        self._empty()

    def _empty(self) -> None:
        self.keys = np.zeros(0, dtype=U)
        self.slot = np.zeros(0, dtype=np.int64)
        self.begin = np.zeros(1, dtype=np.int64)
        self.ids = np.zeros(0, dtype=np.uint32)

    def _learn(self, keys: np.ndarray, pieces: list[str]) -> None:
        found = list(map(self.encoder.encode_ordinary, pieces))
        sizes = np.fromiter(map(len, found), dtype=np.int64, count=len(found))
        slots = np.arange(len(self.begin) - 1, len(self.begin) - 1 + len(found))
        self.begin = np.concatenate([self.begin, self.begin[-1] + np.cumsum(sizes)])
        self.ids = np.concatenate([self.ids, np.fromiter((i for f in found for i in f), dtype=np.uint32, count=int(sizes.sum()))])
        at = np.searchsorted(self.keys, keys)
        self.keys = np.insert(self.keys, at, keys)
        self.slot = np.insert(self.slot, at, slots)

    def encode(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts in a row, and the offset of each text's first."""
        if not self.added or not any(t in text for t in self.added for text in texts):
            return self._ordinary(texts)
        # Each text as ordinary parts with an added token between two of them.
        parts, marks, begin = [], [], [0]
        for text in texts:
            found = self._cut.findall(text)
            parts += self._cut.split(text)
            marks += [*(self.added[f] for f in found), -1]
            begin.append(len(parts))
        ids, at = self._ordinary(parts)
        mark = np.array(marks)
        has = mark >= 0
        out = np.insert(ids, at[1:][has], mark[has].astype(ids.dtype))
        moved = at + np.concatenate([[0], np.cumsum(has)])
        return out, moved[begin]

    def _ordinary(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        joined = "".join(texts)
        sizes = np.fromiter(map(len, texts), dtype=np.int64, count=len(texts))
        starts = np.concatenate([[0], np.cumsum(sizes)])
        if not len(joined):
            return np.zeros(0, np.uint32), np.zeros(len(texts) + 1, np.int64)
        points = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
        begin = piece_bounds(points, starts[:-1][sizes > 0])
        end = np.append(begin[1:], len(points))
        spread = self._code[points & 0xFFFF] + (points >> 16).astype(U) * U(0x9E3779B97F4A7C15)
        hashes = textvec.span_hashes(spread, begin, end)
        keys, where, back = np.unique(hashes, return_index=True, return_inverse=True)
        if len(self.keys) > MOST_PIECES:
            self._empty()
        at = np.minimum(np.searchsorted(self.keys, keys), max(len(self.keys) - 1, 0))
        new = self.keys[at] != keys if len(self.keys) else np.ones(len(keys), dtype=bool)
        if new.any():
            self._learn(keys[new], [joined[a:b] for a, b in zip(begin[where[new]].tolist(), end[where[new]].tolist())])
        slot = self.slot[np.searchsorted(self.keys, keys)][back]
        size = self.begin[slot + 1] - self.begin[slot]
        stop = np.cumsum(size)
        ids = self.ids[np.repeat(self.begin[slot] - (stop - size), size) + np.arange(stop[-1])]
        piece = np.searchsorted(begin, starts)
        return ids, np.concatenate([[0], stop])[piece]


_made: dict[tuple[str, bool], Pieces] = {}


def token_ids(column: pa.Array, path: str, added: bool = True):
    """Yields (first row, ids, offsets) for slices of a column of texts; null is empty."""
    if (path, added) not in _made:
        _made[path, added] = Pieces(path, added)
    sizes = pc.utf8_length(column).fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)
    for a, b in textvec.slices(sizes):
        yield a, *_made[path, added].encode([t or "" for t in column.slice(a, b - a).to_pylist()])
