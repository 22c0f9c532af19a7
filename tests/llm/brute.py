"""Plain versions of the operators, against which the tests hold them."""

from __future__ import annotations

import re
from collections import defaultdict

WORD = re.compile(r"[^\x20\x09-\x0D]+")
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def shingles(text: str | None, width: int = 5) -> frozenset:
    words = WORD.findall((text or "").translate(LOWER))
    if len(words) < width:
        return frozenset([tuple(words)]) if words else frozenset()
    return frozenset(tuple(words[i : i + width]) for i in range(len(words) - width + 1))


def near_duplicates(rows: list[tuple[int, str | None]], percent: int = 75) -> dict[int, tuple[int, int]]:
    """doc_id -> (set size, smallest reachable doc_id), by counting shared shingles through an inverted index."""
    sets = {i: shingles(t) for i, t in rows}
    groups = defaultdict(list)
    for i, s in sets.items():
        groups[s].append(i)
    reps = {min(ids): s for s, ids in groups.items() if s}
    parent = {i: i for i in sets}

    def find(i: int) -> int:
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    def join(a: int, b: int) -> None:
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)

    for s, ids in groups.items():
        for i in ids if s else ():
            join(min(ids), i)
    index = defaultdict(list)
    for i, s in sorted(reps.items()):
        shared = defaultdict(int)
        for x in s:
            for j in index[x]:
                shared[j] += 1
            index[x].append(i)
        for j, n in shared.items():
            if 100 * n >= percent * (len(s) + len(reps[j]) - n):
                join(i, j)
    return {i: (len(s), find(i)) for i, s in sets.items()}
