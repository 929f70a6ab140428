"""Plain Python versions of the corpus operators' contracts, for comparison in tests."""

import hashlib
import itertools
import re

import numpy as np
import xxhash

WORDS = re.compile(r"[^\x20\x09-\x0D]+")


def counts(text):
    text = text or ""
    words = WORDS.findall(text)
    grams = [tuple(words[i:i + 3]) for i in range(len(words) - 2)]
    hit = {j for i, g in enumerate(grams) if grams.count(g) > 1 for j in range(i, i + 3)} if len(grams) < 3000 else None
    lines = [x for x in text.split("\n") if WORDS.search(x)]
    return len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in text), sum(x in lines[:i] for i, x in enumerate(lines)), None if hit is None else len(hit)


def fingerprint(text):
    words = WORDS.findall(re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    if not words:
        return 0
    grams = [" ".join(words[i:i + 3]) for i in range(len(words) - 2)] if len(words) >= 3 else [" ".join(words)]
    hashes = [xxhash.xxh64_intdigest(g.encode(), 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def components(n, pairs):
    root = list(range(n))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x
    for a, b in pairs:
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    return [find(i) for i in range(n)]


def near_pairs(fps, radius=2):
    v = np.array(fps, np.uint64)
    i, j = np.nonzero(np.bitwise_count(v[:, None] ^ v) <= radius)
    return [(a, b) for a, b in zip(i.tolist(), j.tolist()) if a < b]


def digest(marks):
    return ",".join(f"{k}:{s}:{e}" for s, _, e, k in sorted(marks))


def sha(text):
    return hashlib.sha256(text.encode()).hexdigest()


def luhn(text):
    d = [int(c) for c in re.sub("[^0-9]", "", text)][::-1]
    return sum(x if i % 2 == 0 else x * 2 - 9 * (x > 4) for i, x in enumerate(d)) % 10 == 0


def personal(text):
    text, out = text or "", []
    n = lambda t: len(re.sub("[^0-9]", "", t))
    for k, (kind, pattern, good) in enumerate((
            ("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", lambda t: True),
            ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", lambda t: all(int(p) <= 255 for p in t.split("."))),
            ("card", r"[0-9]([\x20-]?[0-9])+", lambda t: 14 <= n(t) <= 19 and luhn(t)),
            ("phone", r"\+[0-9][\x20().0-9-]+[0-9]", lambda t: 10 <= n(t) <= 15))):
        out += [(m.start(), k, m.end(), kind) for m in re.finditer(pattern, text) if good(m[0])]
    return out


def secret(text):
    text, out = text or "", []
    assign = r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
    for k, (kind, pattern, good) in enumerate((
            ("assign", assign, lambda m: len(m[2]) >= 12), ("access", r"AKIA[A-Z0-9]+", lambda m: len(m[0]) >= 18), ("hex", r"[0-9a-f]+", lambda m: len(m[0]) >= 16))):
        out += [(m.start(), k, m.end(), kind) for m in re.finditer(pattern, text) if good(m)]
    return out


def embedding_links(rows, cosine=0.98):
    """{position: (links, smallest position linked)} of (vec, label) rows."""
    good = [v is not None and lab is not None and len(v) and all(x is not None and np.isfinite(x) for x in v) and any(v) for v, lab in rows]
    x = [np.array(v, float) / np.linalg.norm(np.array(v, float)) if g else None for (v, _), g in zip(rows, good)]
    pairs = [(i, j) for i in range(len(rows)) for j in range(i) if good[i] and good[j] and rows[i][1] == rows[j][1] and len(x[i]) == len(x[j]) and x[i] @ x[j] >= cosine]
    n = [0] * len(rows)
    for i, j in pairs:
        n[i] += 1
        n[j] += 1
    return n, components(len(rows), pairs)


def line_repeats(texts, window=3, long_words=50):
    """Texts without later repeats: each window of lines against all earlier places, then line by line to both sides."""
    worded = [[(p, " ".join(WORDS.findall(line))) for p, line in enumerate(t.split("\n")) if WORDS.search(line)] if t is not None else [] for t in texts]
    source, out = {}, []
    for t, lines in zip(texts, worded):
        said, gone = [x for _, x in lines], set()
        for i in range(len(said)):
            n = next((n for n in range(1, window + 1) if i + n <= len(said) and (n == window or sum(len(x.split(" ")) for x in said[i:i + n]) >= long_words)), None)
            if n is None:
                continue
            short = lambda x: len(x.split(" ")) < long_words
            before, after = (list(itertools.takewhile(short, x)) for x in (said[max(0, i - window + 1):i][::-1], said[i + n:i + n + window - 1]))
            if (key := tuple(said[i:i + n])) not in source:
                source[key] = before, after
                continue
            same = [next((k for k, (a, b) in enumerate(zip(x, y)) if a != b), min(len(x), len(y))) for x, y in zip(source[key], (before, after))]
            gone.update(p for p, _ in lines[i - same[0]:i + n + same[1]])
        out.append(None if t is None else "\n".join(x for p, x in enumerate(t.split("\n")) if p not in gone))
    return out


def pour(budget, caps, weights):
    """Whole-number shares of a budget by weight, none beyond its cap; what a full child leaves goes to the rest."""
    full = set()
    while True:
        room = max(0, budget - sum(caps[c] for c in full))
        left = sum(weights[c] for c in caps if c not in full)
        more = {c for c in caps if c not in full and weights[c] > 0 and caps[c] * left <= weights[c] * room}
        if not more:
            return {c: caps[c] if c in full else weights[c] * room // left if left else 0 for c in caps}
        full |= more


def mixture(rows, share, weights, epochs, key):
    """{doc_id: copies} of rows (doc_id, tokens, path); ``key``: (epoch, doc_id) -> order within a leaf."""
    leaves = {}
    for i, n, path in rows:
        if n:
            leaves.setdefault(path, []).append((i, n))
    total = sum(n for _, n, _ in rows)

    def cap(prefix):
        return epochs * sum(n for p, docs in leaves.items() if p[:len(prefix)] == prefix for _, n in docs)

    given = {(): min(int(total * share), cap(()))}
    for depth in range(len(next(iter(leaves), ()))):
        below = {}
        for prefix, budget in given.items():
            kids = sorted({p[:depth + 1] for p in leaves if p[:depth] == prefix})
            below |= pour(budget, {k: cap(k) for k in kids}, {k: round(1e6 * weights[depth].get(k[-1], 1)) for k in kids})
        given = below
    copies = {}
    for path, docs in leaves.items():
        tokens = sum(n for _, n in docs)
        full, used = given[path] // tokens, 0
        room = given[path] - full * tokens
        for at, (i, n) in enumerate(sorted(docs, key=lambda d: key(full, d[0]))):
            used += n
            copies[i] = full + (used <= room)
    return {i: c for i, c in copies.items() if c}
