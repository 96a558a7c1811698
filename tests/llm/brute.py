"""Plain single-machine versions of what the operators return."""

import re
from collections import defaultdict

_WORD = re.compile(r"[^\x20\x09-\x0D]+")
_LOWER = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})


def shingle_set(text, width=5):
    w = _WORD.findall((text or "").translate(_LOWER))
    if not w:
        return frozenset()
    k = min(width, len(w))
    return frozenset(tuple(w[i : i + k]) for i in range(len(w) - k + 1))


def jaccard_components(rows, num=75, den=100):
    """rows: (doc_id, text) -> {doc_id: (size, component)}; all pairs that share a shingle are compared."""
    sets = {i: shingle_set(t) for i, t in rows}
    index = defaultdict(list)
    for i, s in sets.items():
        for x in s:
            index[x].append(i)
    parent = {i: i for i in sets}

    def find(x):
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for i, s in sets.items():
        seen = defaultdict(int)
        for x in s:
            for j in index[x]:
                if j > i:
                    seen[j] += 1
        for j, o in seen.items():
            if den * o >= num * (len(s) + len(sets[j]) - o):
                a, b = find(i), find(j)
                parent[max(a, b)] = min(a, b)
    return {i: (len(s), find(i)) for i, s in sets.items()}


def repeated_bytes(rows, length=100):
    """rows: (doc_id, text) -> {doc_id: (n_bytes, n_removed, n_spans, kept bytes)}"""
    seen, out = set(), {}
    for i, t in sorted(rows):
        b = (t or "").encode()
        gone = bytearray(len(b))
        for p in range(len(b) - length + 1):
            w = b[p : p + length]
            if w in seen:
                gone[p : p + length] = b"\x01" * length
            else:
                seen.add(w)
        spans = sum(1 for k in range(len(b)) if gone[k] and (k == 0 or not gone[k - 1]))
        out[i] = (len(b), sum(gone), spans, bytes(x for x, g in zip(b, gone) if not g))
    return out
