"""Plain versions of the contracts, for small tables."""

import hashlib
import re
import zlib
from collections import defaultdict

import numpy as np
import xxhash


def sha(b):
    return hashlib.sha256(b.encode() if isinstance(b, str) else b).hexdigest()


def op1(docs, length=100):
    first, out = {}, {}
    for d, t in sorted(docs):
        for i in range(len(t) - length + 1):
            first.setdefault(t[i : i + length], (d, i))
    for d, t in docs:
        gone = np.zeros(len(t) + 1, int)
        for i in range(len(t) - length + 1):
            if first[t[i : i + length]] < (d, i):
                gone[i] += 1
                gone[i + length] -= 1
        gone = np.cumsum(gone)[:-1] > 0
        kept = bytes(b for b, g in zip(t, gone, strict=True) if not g)
        out[d] = (len(t), int(gone.sum()), int((gone & ~np.r_[False, gone[:-1]]).sum()) if len(t) else 0, sha(kept))
    return out


ASSIGN = re.compile(r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.A)


def op3(text):
    text = text or ""
    spans = [(m.start(), 0, "assign", m.end()) for m in ASSIGN.finditer(text) if len(m[1]) >= 6]
    spans += [(m.start(), 1, "access", m.end()) for m in re.finditer(r"AKIA[A-Z0-9]+", text) if len(m[0]) >= 20]
    spans += [(m.start(), 2, "hex", m.end()) for m in re.finditer(r"[0-9a-f]+", text) if len(m[0]) >= 24]
    spans.sort()
    n = [sum(s[1] == k for s in spans) for k in range(3)]
    return *n, sha(",".join(f"{k}:{s}:{e}" for s, _, k, e in spans))


def op5_print(text):
    words = (text or "").encode().lower().split()
    if not words:
        return 0
    h = [xxhash.xxh64_intdigest(b" ".join(words[i : i + 3]), 42) for i in range(max(1, len(words) - 2))]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def op5(rows):
    """(doc_id, text) to {doc_id: (print, component)}."""
    fp = [op5_print(t) for _, t in rows]
    parent = list(range(len(rows)))

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    f = np.array(fp, np.uint64)
    for i in range(len(rows)):
        for j in np.nonzero(np.bitwise_count(f ^ f[i]) <= 2)[0]:
            a, b = root(i), root(int(j))
            if a != b:
                parent[max(a, b)] = min(a, b)
    low = defaultdict(lambda: 1 << 62)
    for i, (d, _) in enumerate(rows):
        low[root(i)] = min(low[root(i)], d)
    return {d: (f"{fp[i]:016x}", low[root(i)]) for i, (d, _) in enumerate(rows)}


WORD = re.compile(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def op6(docs, items):
    windows = defaultdict(set)
    for item, t in items:
        w = WORD.findall((t or "").encode().lower())
        for i in range(max(1, len(w) - 9) if w else 0):
            windows[tuple(w[i : i + 10])].add(str(item))
    sizes = sorted({len(k) for k in windows})
    out = {}
    for d, t in docs:
        w, hit, names = WORD.findall((t or "").encode().lower()), set(), set()
        for n in sizes:
            for i in range(len(w) - n + 1):
                if (k := tuple(w[i : i + n])) in windows:
                    names |= windows[k]
                    hit |= set(range(i, i + n))
        out[d] = (len(w), len(hit), len(names), sha(",".join(sorted(names))), bool(hit))
    return out


def op8(rows, k=20):
    m = {i: [int(np.floor(64 * float(x))) for x in v] for i, v in rows if v is not None and all(x is not None and np.isfinite(x) for x in v)}
    out = []
    for q in sorted(m):
        if q % 20 == 0:
            s = sorted((-sum(a * b for a, b in zip(m[q], m[i], strict=False)), i) for i in m if i != q)[:k]
            out += [(q, r + 1, i, -x) for r, (x, i) in enumerate(s)]
    return out


def op9(rows):
    """(doc_id, text) to {doc_id: (held_out, n_tokens, n_known, N, base)}."""
    held = {d: zlib.crc32(str(d).encode()) % 10 == 0 for d, _ in rows}
    words = {d: [*(t or "").encode().lower().split(), None] for d, t in rows}
    c = defaultdict(int)
    for d in words:
        if not held[d]:
            for w in words[d]:
                c[w] += 1
    n, v = sum(c.values()), len(c)
    return {d: (held[d], len(w), sum(c.get(x, 0) > 0 for x in w), n, sum(np.log10((c.get(x, 0) + 0.1) / (n + 0.1 * (v + 1))) for x in w)) for d, w in words.items()}
