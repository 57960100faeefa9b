"""Plain versions of the operators, for small inputs."""

import hashlib
import re
import zlib

import numpy as np

_WORDS = re.compile(r"[^\x20\x09-\x0D]+")
_LOW = {c: c + 32 for c in range(65, 91)}


def find(parent, x):
    while parent[x] != x:
        x = parent[x]
    return x


def shingle_set(text, k=5):
    w = _WORDS.findall((text or "").translate(_LOW))
    return {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set())


def near_duplicates(rows, percent=85):
    """{doc_id: (n_shingles, component)}"""
    sets = {i: shingle_set(t) for i, t in rows}
    ids = sorted(sets)
    parent = {i: i for i in ids}
    for x, i in enumerate(ids):
        for j in ids[x + 1 :]:
            s, t = sets[i], sets[j]
            if s and t and 100 * len(s & t) >= percent * len(s | t):
                a, b = find(parent, i), find(parent, j)
                parent[max(a, b)] = min(a, b)
    return {i: (len(sets[i]), find(parent, i)) for i in ids}


def repeated(rows, width=100):
    """{doc_id: (n_bytes, n_removed, n_spans, sha, kept)}; rows with unique doc_ids."""
    seen, out = set(), {}
    for i, t in sorted(rows):
        raw = (t or "").encode()
        gone = bytearray(len(raw))
        for s in range(len(raw) - width + 1):
            w = raw[s : s + width]
            if w in seen:
                gone[s : s + width] = b"\1" * width
            seen.add(w)
        kept = bytes(c for c, g in zip(raw, gone) if not g)
        spans = sum(1 for k in range(len(raw)) if gone[k] and (k == 0 or not gone[k - 1]))
        out[i] = (len(raw), sum(gone), spans, hashlib.sha256(kept).hexdigest(), kept)
    return out


def links(rows, cosine=0.95):
    """{vec_id: (n_links, component)}"""
    good = {i: np.array(v, float) for i, v in rows if v is not None and None not in v and np.isfinite(np.array(v, float)).all() and np.any(v)}
    parent = {i: i for i, _ in rows}
    n = dict.fromkeys(parent, 0)
    for i in good:
        for j in good:
            if i != j and good[i] @ good[j] / np.sqrt(good[i] @ good[i]) / np.sqrt(good[j] @ good[j]) >= cosine:
                n[i] += 1
                a, b = find(parent, i), find(parent, j)
                parent[max(a, b)] = min(a, b)
    return {i: (n[i], find(parent, i)) for i in parent}


def top_k(rows, every=20, k=20):
    v = {i: np.floor(64 * np.array(x, float)).astype(int) for i, x in rows}
    return {q: [(i, s) for s, i in sorted((-int(v[q] @ v[i]), i) for i in v if i != q)[:k]] for q in v if q % every == 0}


ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)


def base_secrets(text):
    t = text or ""
    out = [(m.start(), 0, "assign", m.end()) for m in ASSIGN.finditer(t) if len(m[2]) >= 12]
    out += [(m.start(), 1, "access", m.end()) for m in re.finditer(r"AKIA[A-Z0-9]+", t) if len(m[0]) >= 18]
    out += [(m.start(), 2, "hex", m.end()) for m in re.finditer(r"[0-9a-f]+", t) if len(m[0]) >= 16]
    return [(k, s, e) for s, _, k, e in sorted(out)]


def crc(ids):
    return zlib.crc32(np.array(ids, "<u4").tobytes())
