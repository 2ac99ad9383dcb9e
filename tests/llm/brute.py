"""Plain, quadratic versions of what the operators compute."""

from __future__ import annotations

import re
from itertools import combinations


def shingles(text: str | None) -> frozenset:
    words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]+", lambda m: m.group().lower(), text or ""))
    if len(words) < 5:
        return frozenset([tuple(words)] if words else [])
    return frozenset(tuple(words[i : i + 5]) for i in range(len(words) - 4))


def roots(nodes, links) -> dict:
    """Smallest node reachable from each."""
    up = {n: n for n in nodes}

    def root(n):
        while up[n] != n:
            n = up[n]
        return n

    for a, b in links:
        a, b = root(a), root(b)
        up[max(a, b)] = min(a, b)
    return {n: root(n) for n in nodes}


def near_duplicates(rows: list[tuple[int, str | None]], percent: int = 85) -> dict[int, tuple[int, int, bool]]:
    sets = {i: shingles(t) for i, t in rows}
    holders: dict = {}
    for i, s in sets.items():
        for x in s:
            holders.setdefault(x, set()).add(i)
    met = {p for h in holders.values() for p in combinations(sorted(h), 2)}
    links = [(a, b) for a, b in met if 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b])]
    top = roots(sets, links)
    return {i: (len(s), top[i], top[i] == i) for i, s in sets.items()}
