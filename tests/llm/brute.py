"""Plain-Python references that the operators are held against."""

from __future__ import annotations

import re

SPACED = re.compile(r"[^\x20\x09-\x0D]+")
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def words(text):
    return SPACED.findall(text or "")


def shingles(text, size=5):
    w = words((text or "").translate(LOWER))
    if not w:
        return set()
    return {tuple(w[i : i + size]) for i in range(len(w) - size + 1)} if len(w) >= size else {tuple(w)}


def near_groups(rows, percent=75):
    """doc_id -> (set size, component) by comparing every pair that shares a shingle."""
    sets = {i: shingles(t) for i, t in rows}
    posts = {}
    for i, s in sets.items():
        for x in s:
            posts.setdefault(x, []).append(i)
    parent = {i: i for i in sets}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    seen = set()
    for ids in posts.values():
        for k, a in enumerate(ids):
            for b in ids[k + 1 :]:
                if (a, b) not in seen:
                    seen.add((a, b))
                    both = len(sets[a] & sets[b])
                    if 100 * both >= percent * (len(sets[a]) + len(sets[b]) - both):
                        ra, rb = sorted((root(a), root(b)))
                        parent[rb] = ra
    return {i: (len(s), root(i)) for i, s in sets.items()}
