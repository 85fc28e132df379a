"""The contracts in plain Python, for small inputs."""

import hashlib
import re
import zlib
from collections import Counter, defaultdict

SPLIT = re.compile(r"[^\x20\x09-\x0D]+")


def sha(x: bytes) -> str:
    return hashlib.sha256(x).hexdigest()


def suffix(rows, size=400):
    seen = Counter()
    for _, t in rows:
        b = (t or "").encode()
        seen.update(b[i : i + size] for i in range(len(b) - size + 1))
    out = []
    for d, t in rows:
        b = (t or "").encode()
        gone = bytearray(len(b))
        for i in range(len(b) - size + 1):
            if seen[b[i : i + size]] > 1:
                gone[i : i + size] = b"\1" * size
        spans = len(re.findall(b"\1+", bytes(gone)))
        out.append((d, len(b), sum(gone), spans, sha(bytes(x for x, g in zip(b, gone) if not g))))
    return sorted(out)


def substring(rows, size=13):
    first = {}
    texts = [(d, SPLIT.findall(t or "")) for d, t in rows]
    for d, w in texts:
        for i in range(len(w) - size + 1):
            k = tuple(w[i : i + size])
            first[k] = min(first.get(k, d), d)
    out = []
    for d, w in texts:
        gone = [False] * len(w)
        for i in range(len(w) - size + 1):
            if first[tuple(w[i : i + size])] < d:
                gone[i : i + size] = [True] * size
        out.append((d, len(w), sum(gone), sha(" ".join(x for x, g in zip(w, gone) if not g).encode())))
    return sorted(out)


def lower(t):
    return re.sub("[A-Z]+", lambda m: m[0].lower(), t)


def neardup(rows, size=3, similar=85):
    sets = []
    for d, t in rows:
        w = SPLIT.findall(lower(t or ""))
        k = min(size, len(w))
        sets.append((d, {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if w else set()))
    up = {d: d for d, _ in sets}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    by = defaultdict(list)
    for i, (_, s) in enumerate(sets):
        for x in s:
            by[x].append(i)
    common = Counter()
    for group in by.values():
        if len(group) < 400:
            common.update((a, b) for j, a in enumerate(group) for b in group[j + 1 :])
    for (a, b), n in common.items():
        (da, sa), (db, sb) = sets[a], sets[b]
        n = len(sa & sb)
        if 100 * n >= similar * (len(sa) + len(sb) - n):
            x, y = root(da), root(db)
            up[max(x, y)] = min(x, y)
    return sorted((d, len(s), root(d), root(d) == d) for d, s in sets)


def decontamination(rows, items, size=13):
    word = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    windows = defaultdict(set)
    for i, t in items:
        w = word.findall(lower(t or ""))
        for j in range(max(1, len(w) - size + 1) if w else 0):
            windows[tuple(w[j : j + size])].add(str(i))
    lengths = {len(k) for k in windows}
    out = []
    for d, t in rows:
        w = word.findall(lower(t or ""))
        hit, found = [False] * len(w), set()
        for n in lengths:
            for i in range(len(w) - n + 1):
                k = tuple(w[i : i + n])
                if k in windows:
                    hit[i : i + n] = [True] * n
                    found |= windows[k]
        h = sum(hit)
        out.append((d, len(w), h, len(found), sha(",".join(sorted(found)).encode()), h > 0 and 20 * h >= len(w)))
    return sorted(out)


def quality(rows):
    out = []
    for d, t in rows:
        t = t or ""
        w = SPLIT.findall(t)
        at = defaultdict(list)
        for i in range(len(w) - 7):
            at[tuple(w[i : i + 8])].append(i)
        hit = set()
        for places in at.values():
            if len(places) > 1:
                for p in places:
                    hit.update(range(p, p + 8))
        lines = [x for x in t.split("\n") if SPLIT.search(x)]
        out.append((d, len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t), len(lines) - len(set(lines)), len(hit), len(w) < 20 or 100 * len(hit) > 30 * len(w)))
    return sorted(out)


def warc(rows):
    out, last = [], {}
    for p, h in rows:
        b = (h or "").encode()
        if len(b) >= 1000:
            k = hashlib.sha1(b).hexdigest()
            last[k] = max(last.get(k, p), p)
    for p, h in rows:
        b = (h or "").encode()
        k = hashlib.sha1(b).hexdigest()
        to = last.get(k, p) if len(b) >= 1000 else p
        out.append((p, len(b), k, "response" if to == p else "revisit", None if to == p else to))
    return sorted(out)


def crc(ids) -> int:
    import numpy as np

    return zlib.crc32(np.array(ids, "<u4").tobytes())
