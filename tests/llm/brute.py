"""Plain versions of operators, for small tables."""

import re
from collections import defaultdict

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def words(text):
    return WORD.findall(text or "")


def shingles(text, width=5):
    w = words(re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    return {tuple(w[i : i + width]) for i in range(max(1, len(w) - width + 1))} if w else set()


def near_duplicates(rows, percent):
    """(doc_id, n_shingles, component_id, kept) of rows (doc_id, text) with distinct ids."""
    sets = {k: shingles(t) for k, t in rows}
    holders = defaultdict(list)
    for k, s in sets.items():
        for x in s:
            holders[x].append(k)
    parent = {k: k for k in sets}

    def root(k):
        while parent[k] != k:
            k = parent[k]
        return k

    for a, s in sets.items():
        both = defaultdict(int)
        for x in s:
            for b in holders[x]:
                if b > a:
                    both[b] += 1
        for b, n in both.items():
            if 100 * n >= percent * (len(s) + len(sets[b]) - n):
                x, y = sorted((root(a), root(b)))
                parent[y] = x
    return [(k, len(s), root(k), root(k) == k) for k, s in sets.items()]


def removed(rows, size=50):
    """For rows (doc_id, text): (doc_id, words, flags of the words that go)."""
    first = {}
    for k, t in rows:
        if k is None:
            continue
        w = words(t)
        for i in range(len(w) - size + 1):
            g = tuple(w[i : i + size])
            first[g] = min(first.get(g, k), k)
    for k, t in rows:
        w = words(t)
        gone = [False] * len(w)
        for i in range(len(w) - size + 1):
            if k is not None and first[tuple(w[i : i + size])] < k:
                gone[i : i + size] = [True] * size
        yield k, w, gone
