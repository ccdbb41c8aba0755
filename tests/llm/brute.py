"""Plain single-machine versions that the operators are held against."""

from __future__ import annotations

import hashlib
import random
import re
from collections import Counter, defaultdict

import numpy as np

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def roots(nodes, links):
    up = {n: n for n in nodes}

    def find(x):
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    for a, b in links:
        a, b = find(a), find(b)
        if a != b:
            up[max(a, b)] = min(a, b)
    return {n: find(n) for n in nodes}


def vectors(rows, threshold=0.98):
    """rows: (id, vector, label) -> {id: (n_links, component)}."""
    ok = []
    for i, v, label in rows:
        if v is None or label is None or any(x is None for x in v):
            continue
        x = np.array(v, float)
        if len(x) and np.isfinite(x).all() and (x * x).sum() > 0:
            ok.append((i, x / np.sqrt((x * x).sum()), (label, len(x))))
    n, links = Counter(), []
    groups = defaultdict(list)
    for i, x, k in ok:
        groups[k].append((i, x))
    for g in groups.values():
        x = np.array([v for _, v in g])
        hit = x @ x.T >= threshold
        np.fill_diagonal(hit, False)
        for k, (i, _) in enumerate(g):
            n[i] += int(hit[k].sum())
            links += [(i, g[j][0]) for j in np.flatnonzero(hit[k])]
    comp = roots([r[0] for r in rows], links)
    return {r[0]: (n[r[0]], comp[r[0]]) for r in rows}


def quality_base(text):
    text = text or ""
    words = WORD.findall(text)
    lines = [x for x in text.split("\n") if WORD.search(x)]
    three = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
    often = {k for k, c in Counter(three).items() if c > 1}
    covered = {i + k for i, x in enumerate(three) if x in often for k in range(3)}
    n = len(words)
    return (n, sum(map(len, words)), sum(text.count(c) for c in "#*$%&|<>"), len(lines) - len(set(lines)), len(covered), n < 50 or 100 * len(covered) > 50 * n)


ASSIGN = re.compile(r"((?:[Pp][Aa][Ss][Ss][Ww][Oo][Rr][Dd]|[Pp][Aa][Ss][Ss][Ww][Dd]|[Ss][Ee][Cc][Rr][Ee][Tt]|[Tt][Oo][Kk][Ee][Nn]|[Aa][Pp][Ii]_?[Kk][Ee][Yy]))[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)")


def secrets_base(text):
    text = text or ""
    out = [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= 6]
    out += [(m.start(), 1, m.end()) for m in re.finditer(r"AKIA[A-Z0-9]+", text) if len(m[0]) >= 20]
    out += [(m.start(), 2, m.end()) for m in re.finditer(r"[0-9a-f]+", text) if len(m[0]) >= 24]
    name = ("assign", "access", "hex")
    digest = ",".join(f"{name[k]}:{a}:{b}" for a, k, b in sorted(out))
    n = Counter(k for _, k, _ in out)
    return n[0], n[1], n[2], hashlib.sha256(digest.encode()).hexdigest()


def shingles(text):
    w = WORD.findall("".join(c.lower() if c.isascii() else c for c in text or ""))
    if not w:
        return frozenset()
    return frozenset(tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4)))


def near(rows):
    """rows: (id, text) -> {id: (n_shingles, component)}; all pairs that share a shingle."""
    sets = {i: shingles(t) for i, t in rows}
    holders = defaultdict(list)
    for i, s in sets.items():
        for x in s:
            holders[x].append(i)
    both = Counter()
    for h in holders.values():
        for k, a in enumerate(h):
            for b in h[k + 1 :]:
                both[a, b] += 1
    links = [(a, b) for (a, b), n in both.items() if 100 * n >= 85 * (len(sets[a]) + len(sets[b]) - n)]
    comp = roots(sets, links)
    return {i: (len(sets[i]), comp[i]) for i in sets}


def words(n, seed=0, vocabulary=4000):
    r = random.Random(seed)
    return [f"w{r.randrange(vocabulary)}" for _ in range(n)]
