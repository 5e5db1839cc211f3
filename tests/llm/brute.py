"""Plain versions of the operators, for small inputs."""

import hashlib
import re

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def words(text):
    return WORD.findall(text or "")


def lower(text):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")


def key(doc_id):
    return (doc_id is not None, doc_id or 0)


def suffix_dedup(rows, span, row=lambda t: 0):
    """row: what tells rows of one id apart and orders equal starts."""
    first, out = {}, []
    for d, t in rows:
        raw = (t or "").encode()
        for i in range(len(raw) - span + 1):
            k, w = (key(d), i, row(t)), raw[i : i + span]
            first[w] = min(first.get(w, k), k)
    for d, t in rows:
        raw = (t or "").encode()
        gone = [False] * len(raw)
        for i in range(len(raw) - span + 1):
            if first[raw[i : i + span]] != (key(d), i, row(t)):
                gone[i : i + span] = [True] * span
        kept = bytes(b for b, g in zip(raw, gone, strict=True) if not g)
        out.append((d, len(raw), sum(gone), sum(g and not (i and gone[i - 1]) for i, g in enumerate(gone)), hashlib.sha256(kept).hexdigest()))
    return out


def substring_dedup(rows, span):
    first, out = {}, []
    for d, t in sorted(rows, key=lambda r: key(r[0])):
        w = words(t)
        for i in range(len(w) - span + 1):
            first.setdefault(tuple(w[i : i + span]), d)
    for d, t in rows:
        w = words(t)
        gone = [False] * len(w)
        for i in range(len(w) - span + 1):
            if first[tuple(w[i : i + span])] != d:
                gone[i : i + span] = [True] * span
        out.append((d, len(w), sum(gone), hashlib.sha256(" ".join(x for x, g in zip(w, gone, strict=True) if not g).encode()).hexdigest()))
    return out


def jaccard_components(rows, size=5, percent=80):
    sets = []
    for d, t in rows:
        w = words(lower(t))
        sets.append((d, {tuple(w[i : i + size]) for i in range(len(w) - size + 1)} if len(w) >= size else ({tuple(w)} if w else set())))
    parent = list(range(len(rows)))

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i, (_, a) in enumerate(sets):
        for j in range(i):
            b = sets[j][1]
            if a and b and 100 * len(a & b) >= percent * len(a | b):
                parent[find(i)] = find(j)
    least = {}
    for i, (d, _) in enumerate(sets):
        least[find(i)] = min(least.get(find(i), d), d, key=key)
    return [(d, len(s), least[find(i)]) for i, (d, s) in enumerate(sets)]
