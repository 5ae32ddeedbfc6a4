"""Plain versions of the operators, for small inputs."""

import hashlib
import re

LOW = str.maketrans({chr(i): chr(i + 32) for i in range(65, 91)})
WORD = re.compile(r"[^\x20\x09-\x0D]+")


def shingle_set(text, width):
    words = WORD.findall((text or "").translate(LOW))
    if not words:
        return frozenset()
    if len(words) < width:
        return frozenset([tuple(words)])
    return frozenset(tuple(words[i : i + width]) for i in range(len(words) - width + 1))


def near_components(rows, width, num, den):
    """rows: (id, text) -> {id: (set size, smallest id reachable)}"""
    sets = [(i, shingle_set(t, width)) for i, t in rows]
    root = {i: i for i, _ in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    index = {}
    for k, (_, s) in enumerate(sets):
        for x in s:
            index.setdefault(x, []).append(k)
    seen = {}
    for ks in index.values():
        for a in range(len(ks)):
            for b in range(a + 1, len(ks)):
                seen[ks[a], ks[b]] = seen.get((ks[a], ks[b]), 0) + 1
    for (a, b), common in seen.items():
        (i, s), (j, t) = sets[a], sets[b]
        if den * common >= num * (len(s) + len(t) - common):
            x, y = sorted((find(i), find(j)))
            root[y] = x
    return {i: (len(s), find(i)) for i, s in sets}


def sha(text):
    return hashlib.sha256(text).hexdigest()
