"""The predicates in plain Python, for tables of a few tuples."""

from collections import Counter
from math import exp, log, sqrt


def grams(s, q=2, pad="$"):
    s = " ".join((s or "").split())
    if not s:
        return []
    p = pad * (q - 1) + s.replace(" ", pad * (q - 1)) + pad * (q - 1)
    return [p[i : i + q] for i in range(len(p) - q + 1)]


class Reference:
    def __init__(self, rows, tokens=grams):
        self.tokens = tokens
        self.bags = {t: Counter(tokens(s)) for t, s in rows}
        self.n = len(rows)
        self.dl = {t: sum(b.values()) for t, b in self.bags.items()}
        self.cs = sum(self.dl.values())
        self.df = Counter(x for b in self.bags.values() for x in b)
        self.cf = Counter()
        self.pml = Counter()
        for t, b in self.bags.items():
            for x, tf in b.items():
                self.cf[x] += tf
                self.pml[x] += tf / self.dl[t]

    def idf(self, x):
        return log(self.n) - log(self.df[x])

    def rs(self, x):
        return log((self.n - self.df[x] + 0.5) / (self.df[x] + 0.5))

    def p(self, x, t):
        tf, dl = self.bags[t][x], self.dl[t]
        avg = self.pml[x] / self.df[x]
        f = avg * dl
        r = (1 / (1 + f)) * (f / (1 + f)) ** tf
        return min(max((tf / dl) ** (1 - r) * avg**r, 1e-12), 1 - 1e-12)

    def scores(self, query, name):
        q = Counter(self.tokens(query))
        out = {}
        for t, b in self.bags.items():
            both = [x for x in q if x in b]
            if both:
                out[t] = getattr(self, name)(q, t, both)
        return out

    def xect(self, q, t, both):
        return float(len(both))

    def jaccard(self, q, t, both):
        return len(both) / len(set(q) | set(self.bags[t]))

    def wm(self, q, t, both):
        return sum(map(self.rs, both))

    def bm25(self, q, t, both, k1=1.5, k3=8, b=0.675):
        k = k1 * ((1 - b) + b * self.dl[t] / (self.cs / self.n))
        return sum(self.rs(x) * (k1 + 1) * self.bags[t][x] / (k + self.bags[t][x]) * (k3 + 1) * q[x] / (k3 + q[x]) for x in both)

    def cosine(self, q, t, both):
        a = {x: n * self.idf(x) for x, n in q.items() if x in self.df}
        b = {x: n * self.idf(x) for x, n in self.bags[t].items()}
        norm = sqrt(sum(v * v for v in a.values())) * sqrt(sum(v * v for v in b.values()))
        return sum(a[x] * b[x] for x in both) / norm if norm else 0.0

    def lm(self, q, t, both):
        g = lambda x: self.cf[x] / self.cs
        return sum(log(self.p(x, t)) - log(1 - self.p(x, t)) - log(g(x)) for x in both) + sum(log(1 - self.p(x, t)) for x in self.bags[t])

    def lm_full(self, q, t, both=None):
        """The product over the whole vocabulary, term by term."""
        total = 0.0
        for x in self.df:
            p = self.p(x, t) if x in self.bags[t] else min(self.cf[x] / self.cs, 1 - 1e-12)
            total += log(p) if x in q else log(1 - p)
        return total

    def hmm(self, q, t, both, a0=0.2):
        return exp(sum(log(1 + (1 - a0) * (self.bags[t][x] / self.dl[t]) / (a0 * self.cf[x] / self.cs)) for x in both))
