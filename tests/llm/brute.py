"""Plain versions of the operators that SQL cannot express, for small inputs."""

from __future__ import annotations

import hashlib


def words(text):
    return (text or "").encode().split()


def later_windows(docs, size=20):
    """{doc_id: (n_words, n_removed, digest)}"""
    first, out = {}, {}
    rows = sorted(((d, words(t)) for d, t in docs), key=lambda r: r[0])
    for d, w in rows:
        for s in range(len(w) - size + 1):
            first.setdefault(tuple(w[s : s + size]), (d, s))
    for d, w in rows:
        gone = [False] * len(w)
        for s in range(len(w) - size + 1):
            if first[tuple(w[s : s + size])] != (d, s):
                gone[s : s + size] = [True] * size
        left = [x for x, g in zip(w, gone) if not g]
        out[d] = (len(w), sum(gone), hashlib.sha256(b" ".join(left)).hexdigest())
    return out


def repeated_bytes(docs, size=400):
    """{doc_id: (n_bytes, n_removed, n_spans, digest)}"""
    seen, out = {}, {}
    raw = [(d, (t or "").encode()) for d, t in docs]
    for d, b in raw:
        for s in range(len(b) - size + 1):
            k = hash(b[s : s + size])
            seen[k] = seen.get(k, 0) + 1
    for d, b in raw:
        gone = bytearray(len(b) + 1)
        end = 0
        for s in range(len(b) - size + 1):
            if seen[hash(b[s : s + size])] > 1:
                for i in range(max(s, end), s + size):
                    gone[i] = 1
                end = max(end, s + size)
        left = bytes(x for x, g in zip(b, gone) if not g)
        spans = sum(gone[i] and not (i and gone[i - 1]) for i in range(len(b)))
        out[d] = (len(b), sum(gone), spans, hashlib.sha256(left).hexdigest())
    return out
