"""Slow, plain versions of the operators, written without their kernels."""

from __future__ import annotations

import hashlib
import re
from collections import defaultdict


def shingle_set(text, width=5):
    low = re.sub("[A-Z]", lambda m: m.group(0).lower(), text or "")
    words = re.findall(r"[^\x20\x09-\x0D]+", low)
    if not words:
        return frozenset()
    if len(words) < width:
        return frozenset([tuple(words)])
    return frozenset(tuple(words[i : i + width]) for i in range(len(words) - width + 1))


def components(docs, share=85, share_of=100):
    """docs: (id, text). -> {id: (set size, smallest reachable id)}"""
    sets = {i: shingle_set(t) for i, t in docs}
    holders = defaultdict(list)
    for i, s in sets.items():
        for x in s:
            holders[x].append(i)
    root = {i: i for i in sets}

    def find(i):
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    seen = set()
    for s in holders.values():
        for n, a in enumerate(s):
            for b in s[n + 1 :]:
                if (a, b) in seen:
                    continue
                seen.add((a, b))
                both = len(sets[a] & sets[b])
                if share_of * both >= share * (len(sets[a]) + len(sets[b]) - both):
                    x, y = sorted((find(a), find(b)))
                    root[y] = x
    return {i: (len(sets[i]), find(i)) for i in sets}


def repeats(docs, size=100):
    """docs: (id, text) -> {id: (bytes, removed, spans, digest of the rest)}"""
    first: dict = {}
    out = {}
    for i, text in sorted(docs):
        raw = (text or "").encode()
        gone = bytearray(len(raw))
        for p in range(len(raw) - size + 1):
            if first.setdefault(raw[p : p + size], (i, p)) != (i, p):
                gone[p : p + size] = b"\1" * size
        spans = len(re.findall(b"\1+", bytes(gone)))
        rest = bytes(b for b, g in zip(raw, gone) if not g)
        out[i] = (len(raw), sum(gone), spans, hashlib.sha256(rest).hexdigest())
    return out
