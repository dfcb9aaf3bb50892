"""Plain versions of the operators, for small inputs."""

import re
from collections import Counter, defaultdict

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def lower(text):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")


def shingle_set(text, size):
    words = WORD.findall(lower(text))
    if not words:
        return frozenset()
    return frozenset(tuple(words[i : i + size]) for i in range(max(1, len(words) - size + 1)))


def find(parent, x):
    while parent[x] != x:
        parent[x] = parent[parent[x]]
        x = parent[x]
    return x


def near_components(docs, size=3, percent=85):
    """{doc_id: (set size, component)} by an inverted index over all pairs that share a shingle."""
    sets = {i: shingle_set(t, size) for i, t in docs}
    parent = {i: i for i in sets}
    classes = defaultdict(list)
    for i, s in sets.items():
        if s:
            classes[s].append(i)
    for same in classes.values():
        for i in same:
            a, b = find(parent, same[0]), find(parent, i)
            parent[max(a, b)] = min(a, b)
    index, reps = defaultdict(list), {min(v): k for k, v in classes.items()}
    for i in sorted(reps):
        shared = Counter()
        for s in reps[i]:
            shared.update(index[s])
            index[s].append(i)
        for j, n in shared.items():
            if 100 * n >= percent * (len(reps[i]) + len(reps[j]) - n):
                a, b = find(parent, i), find(parent, j)
                parent[max(a, b)] = min(a, b)
    return {i: (len(sets[i]), find(parent, i)) for i in sets}


def repeat_words(words, window=5):
    seen = defaultdict(list)
    for i in range(len(words) - window + 1):
        seen[tuple(words[i : i + window])].append(i)
    return len({i + k for at in seen.values() if len(at) > 1 for i in at for k in range(window)})


def nearest(vectors, queries, k):
    import numpy as np

    ids = np.array([i for i, _ in vectors])
    m = np.array([v for _, v in vectors], float)
    out = {}
    for i, q in queries:
        d = np.sqrt(((m - np.array(q, float)) ** 2).sum(1))
        order = [j for j in np.lexsort((ids, d)) if ids[j] != i][:k]
        out[i] = [(int(ids[j]), float(d[j])) for j in order]
    return out
