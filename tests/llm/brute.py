"""Plain versions of the operators, for small inputs."""

import hashlib
import re
import zlib
from collections import Counter, defaultdict

LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def words(text):
    return re.findall(r"[^\x20\x09-\x0D]+", text or "")


def gram_set(text, n):
    w = words((text or "").translate(LOWER))
    if not w:
        return set()
    return {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if len(w) >= n else {tuple(w)}


def components(docs, n, num):
    """[(doc_id, text)] -> [(doc_id, set size, component)] in order."""
    sets = [gram_set(t, n) for _, t in docs]
    up = list(range(len(docs)))

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    for i in range(len(docs)):
        for j in range(i):
            if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= num * len(sets[i] | sets[j]):
                up[root(i)] = root(j)
    least = defaultdict(list)
    for i, (d, _) in enumerate(docs):
        least[root(i)].append(d)
    return [(d, len(s), min((x for x in least[root(i)] if x is not None), default=None)) for i, ((d, _), s) in enumerate(zip(docs, sets))]


def dedup(docs, window):
    """[(doc_id, text)] -> [(doc_id, words, removed, digest)] in order."""
    each = [words(t) for _, t in docs]
    seen = Counter(tuple(w[i : i + window]) for w in each for i in range(len(w) - window + 1))
    out = []
    for (d, _), w in zip(docs, each):
        gone = [False] * len(w)
        for i in range(len(w) - window + 1):
            if seen[tuple(w[i : i + window])] > 1:
                gone[i : i + window] = [True] * window
        kept = [x for x, g in zip(w, gone) if not g]
        out.append((d, len(w), sum(gone), hashlib.sha256(" ".join(kept).encode()).hexdigest()))
    return out


def contamination(docs, items, n=13):
    find = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").translate(LOWER))
    windows = defaultdict(set)
    for i, t in items:
        w = find(t)
        k = min(n, len(w))
        for a in range(len(w) - k + 1):
            if w:
                windows[tuple(w[a : a + k])].add(i)
    out = []
    for d, t in docs:
        w, hit, ids = find(t), set(), set()
        for k in {len(x) for x in windows}:
            for a in range(len(w) - k + 1):
                if found := windows.get(tuple(w[a : a + k])):
                    ids |= found - {None}
                    hit |= set(range(a, a + k))
        digest = hashlib.sha256(",".join(sorted(map(str, ids))).encode()).hexdigest()
        out.append((d, len(w), len(hit), len(ids), digest, len(hit) > 0 and 20 * len(hit) >= len(w)))
    return out


def held_out(doc_id):
    return zlib.crc32(str(doc_id).encode()) % 4 == 2
