"""Brute-force versions of corpus operators."""

import hashlib
import math
import zlib
from collections import Counter

from memojoin.llm import kn_quality, mixing


def shingles(text, n):
    w = (text or "").encode().lower().split()
    if not w:
        return frozenset()
    return frozenset(tuple(w[k : k + n]) for k in range(len(w) - n + 1)) if len(w) >= n else frozenset([tuple(w)])


def brute(rows, n, percent):
    sets = [shingles(t, n) for _, t in rows]
    comp = [i for i, _ in rows]
    top = list(range(len(rows)))

    def root(i):
        while top[i] != i:
            i = top[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            a, b = sets[i], sets[j]
            if a and b and 100 * len(a & b) >= percent * len(a | b):
                top[root(i)] = root(j)
    low = {}
    for i, d in enumerate(comp):
        r = root(i)
        low[r] = min(low.get(r, d), d)
    return {d: (len(sets[i]), low[root(i)]) for i, d in enumerate(comp)}


class PlainKneserNey:
    """The model by dictionaries over all texts."""

    def __init__(self, texts):
        self.tri, self.two, self.one = Counter(), Counter(), Counter()
        for t in texts:
            w = ["", "", *(t or "").encode().split()]
            self.tri.update(zip(w, w[1:], w[2:]))
        self.two.update((b, c) for _, b, c in self.tri)
        self.one.update(c for _, c in self.two)
        self.d = [kn_quality.discounts(*[sum(n == k for n in x.values()) for k in (1, 2, 3, 4)]) for x in (self.one, self.two, self.tri)]
        self.contexts = [{}, {}]
        for level, x in enumerate((self.two, self.tri)):
            for g, n in x.items():
                at = self.contexts[level].setdefault(g[:-1] if level else g[0], [0, 0.0])
                at[0] += n
                at[1] += self.d[level + 1][min(n, 3)]
        self.unknown = sum(self.d[0][min(n, 3)] for n in self.one.values()) / sum(self.one.values()) / (len(self.one) + kn_quality.UNKNOWN_WORDS)

    def p(self, a, b, c):
        n = self.one[c]
        p = (n - self.d[0][min(n, 3)]) / sum(self.one.values()) + self.unknown
        for level, (context, g, x) in enumerate(((b, (b, c), self.two), ((a, b), (a, b, c), self.tri))):
            if context in self.contexts[level]:
                total, mass = self.contexts[level][context]
                n = x[g]
                p = (n - self.d[level + 1][min(n, 3)]) / total + mass / total * p
        return p

    def log10(self, text):
        w = ["", "", *(text or "").encode().split()]
        return sum(math.log10(self.p(*w[k - 2 : k + 1])) for k in range(2, len(w)))


def quality(rows, good):
    """ids that stay, of rows (doc_id, lang, text) with distinct ids and of ids labelled good."""
    held = lambda d: zlib.crc32(str(d).encode()) % kn_quality.FOLDS == kn_quality.HELD_OUT
    model = PlainKneserNey([t for d, _, t in rows if d in good and not held(d)])
    known = {d: (lang, len((t or "").encode().split()), model.log10(t)) for d, lang, t in rows}
    tested = [known[d] for d in known if d in good and held(d) and known[d][1]]

    def mean(part):
        return sum(x[2] for x in part) / sum(x[1] for x in part)

    parts = {lang: [x for x in tested if x[0] == lang] for lang in {x[0] for x in tested}}
    parts = {lang: p for lang, p in parts.items() if lang is not None and len(p) >= kn_quality.LEAST_TRUSTED}
    prior = {lang: mean(p) for lang, p in parts.items()}
    shrunk = lambda x: -(x[2] + kn_quality.PRIOR_WORDS * prior.get(x[0], mean(tested))) / (x[1] + kn_quality.PRIOR_WORDS)
    cut = lambda p: sorted(map(shrunk, p))[math.ceil(kn_quality.QUANTILE * len(p)) - 1] + kn_quality.MARGIN
    cuts = {lang: cut(p) for lang, p in parts.items()}
    return {d for d, x in known.items() if x[1] and shrunk(x) <= cuts.get(x[0], cut(tested))}


def mixed(rows):
    """How often each id is emitted, of rows (doc_id, source, text) with distinct ids."""
    size = Counter()
    for _, source, t in rows:
        size[source] += len((t or "").encode().split())
    names = sorted({r[1] for r in rows}, key=lambda s: (s is None, s or ""))
    target = dict(zip(names, mixing.share_out([size[s] for s in names], [1 + k % 3 for k in range(len(names))], sum(size.values()))))
    out = {}
    for d, source, _ in rows:
        rate = target[source] / size[source] if size[source] else 0.0
        draw = int(hashlib.md5(f"{mixing.SEED}|{d}".encode()).hexdigest()[:13], 16) / (1 << 52)
        out[d] = math.floor(rate) + (draw < rate - math.floor(rate))
    return {d: n for d, n in out.items() if n}
