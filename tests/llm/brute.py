"""Plain versions of the contracts, for tests."""

import hashlib
import math
import re
import struct
import zlib
from collections import Counter, defaultdict

WORD = re.compile(rb"[^\x20\x09-\x0D]+")
KINDS = ("email", "ip", "card", "phone")
PATTERN = {
    "email": re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"),
    "ip": re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"),
    "card": re.compile(r"[0-9]([\x20-]?[0-9])+"),
    "phone": re.compile(r"\+[0-9][\x20().0-9-]+[0-9]"),
}


def sha(b):
    return hashlib.sha256(b).hexdigest()


def quality(text):
    text = text or ""
    words = WORD.findall(text.encode())
    lines, dup = set(), 0
    for line in text.encode().split(b"\n"):
        if WORD.search(line):
            dup += line in lines
            lines.add(line)
    grams = Counter(tuple(words[i : i + 8]) for i in range(len(words) - 7))
    inside = {i + k for i in range(len(words) - 7) if grams[tuple(words[i : i + 8])] > 1 for k in range(8)}
    n = len(words)
    return n, sum(len(w.decode()) for w in words), sum(c in "#*$%&|<>" for c in text), dup, len(inside), n < 20 or 100 * len(inside) > 30 * n


def luhn(digits):
    return sum(sum(divmod(int(c) * (1 + i % 2), 10)) for i, c in enumerate(reversed(digits))) % 10 == 0


def pii(text):
    out = []
    for k, kind in enumerate(KINDS):
        for m in PATTERN[kind].finditer(text or ""):
            d = re.sub("[^0-9]", "", m[0])
            if {"email": True, "ip": kind == "ip" and all(int(x) <= 255 for x in m[0].split(".")), "card": 14 <= len(d) <= 19 and luhn(d), "phone": 10 <= len(d) <= 15}[kind]:
                out.append((m.start(), k, m.end()))
    out.sort()
    return [sum(x[1] == k for x in out) for k in range(4)], sha(",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in out).encode()), out


def terms(texts, window, threshold):
    """{place: words that reveal a value the text holds}, by document shares of value, word and both."""
    word = re.compile(r"[^\W\d_]{4,}")
    held = {i: [(t[s:e], s, e) for s, _, e in pii(t)[2]] for i, t in enumerate(texts) if t}
    near = {i: {(v, w) for v, s, e in x for w in word.findall(texts[i][:s].lower())[-window:] + word.findall(texts[i][e:].lower())[:window]} for i, x in held.items()}
    both, value = Counter(p for x in near.values() for p in x), Counter(v for x in held.values() for v in {y[0] for y in x})
    seen = Counter(w for t in texts if t for w in set(word.findall(t.lower())))
    n = len(texts)
    told = {(v, w) for (v, w), c in both.items() if seen[w] and math.log2(c * n / (value[v] * seen[w])) >= threshold * max(math.log2(n / value[v]), 1e-9)}
    return {i: [m[0] for m in word.finditer(t or "") if any((v, m[0].lower()) in told for v, _, _ in held.get(i, []))] for i, t in enumerate(texts)}


def shingles(text, width):
    w = WORD.findall(re.sub(rb"[A-Z]", lambda m: m[0].lower(), (text or "").encode()))
    return {tuple(w[i : i + width]) for i in range(len(w) - width + 1)} or ({tuple(w)} if w else set())


def near(rows, width, percent=80):
    """{doc_id: (n, component, kept)} with unique ids."""
    sets = {d: shingles(t, width) for d, t in rows}
    up = {d: d for d in sets}

    def top(d):
        while up[d] != d:
            d = up[d]
        return d

    by = defaultdict(list)
    for d, s in sets.items():
        for g in s:
            by[g].append(d)
    seen = Counter()
    for ds in by.values():
        if len(ds) < 3000:
            for i, a in enumerate(ds):
                for b in ds[:i]:
                    seen[a, b] += 1
    for (a, b), n in seen.items():
        if 100 * n >= percent * (len(sets[a]) + len(sets[b]) - n):
            x, y = sorted((top(a), top(b)))
            up[y] = x
    return {d: (len(s), top(d), top(d) == d) for d, s in sets.items()}


def repeats(rows, threshold):
    """[(doc_id, n_bytes, n_removed, n_spans, kept_sha256)]."""
    raws = [(d, (t or "").encode()) for d, t in rows]
    seen = Counter()
    for _, b in raws:
        for i in range(len(b) - threshold + 1):
            seen[b[i : i + threshold]] += 1
    out = []
    for d, b in raws:
        gone = bytearray(len(b))
        for i in range(len(b) - threshold + 1):
            if seen[b[i : i + threshold]] > 1:
                gone[i : i + threshold] = b"\1" * threshold
        spans = len(re.findall(b"\x01+", bytes(gone)))
        out.append((d, len(b), sum(gone), spans, sha(bytes(x for x, g in zip(b, gone) if not g))))
    return out


def repeats_fast(rows, threshold):
    """The same by hashes of all windows, for whole tables."""
    import numpy as np

    raws = [(d, (t or "").encode()) for d, t in rows]
    p, q = 1_000_003, (1 << 61) - 1
    keys = []
    top = pow(p, threshold - 1, q)
    for _, b in raws:
        h, out = 0, []
        for i, c in enumerate(b):
            if i >= threshold:
                h = (h - b[i - threshold] * top) % q
            h = (h * p + c) % q
            if i >= threshold - 1:
                out.append(h)
        keys.append(np.array(out, dtype=np.int64))
    flat = np.concatenate(keys)
    _, back, count = np.unique(flat, return_inverse=True, return_counts=True)
    hit = count[back] > 1
    out, at = [], 0
    for (d, b), k in zip(raws, keys):
        gone = np.zeros(len(b) + 1, dtype=np.int64)
        where = np.flatnonzero(hit[at : at + len(k)])
        at += len(k)
        np.add.at(gone, where, 1)
        np.add.at(gone, where + threshold, -1)
        g = np.cumsum(gone[:-1]) > 0
        spans = int((g & ~np.concatenate(([False], g[:-1]))).sum())
        out.append((d, len(b), int(g.sum()), spans, sha(np.frombuffer(b, np.uint8)[~g].tobytes())))
    return out


def payload(text):
    b = (text or "").encode()
    p = b + bytes(-len(b) % 64 or (64 if not b else 0))
    return len(b), len(p), sha(p), zlib.crc32(p[-64:])


def crc_ids(ids):
    return zlib.crc32(struct.pack(f"<{len(ids)}I", *ids))
