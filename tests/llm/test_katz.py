import math
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

from winjoin.llm import katz
from winjoin.llm.katz import discounts, katz_scores

TOKEN = re.compile(r"[^\x20\x09-\x0D]+")


def toks(t):
    return TOKEN.findall("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")) + ["</s>"]


class Reference:
    """The same model from plain dictionaries, evaluated by recursion."""

    def __init__(self, texts, order, gt_max=5, absolute=0.75):
        self.order = order
        self.c = Counter(w for t in texts for w in toks(t))
        self.n, self.v = sum(self.c.values()), len(self.c)
        d = lambda t, r: 1.0 if r > gt_max else t[r]
        d1 = discounts(Counter(self.c.values()), gt_max, absolute)
        self.p = {w: d(d1, r) * r / self.n for w, r in self.c.items()}
        self.unknown = 1 - sum(self.p.values())
        if self.unknown <= 1e-12:
            u = 1 / (self.n + 1)
            self.p = {w: x * (1 - u) / (1 - self.unknown) for w, x in self.p.items()}
            self.unknown = u
        self.star, self.alpha = {}, {}
        for k in range(2, order + 1):
            grams = Counter(tuple((["<s>"] * (k - 1) + toks(t))[i : i + k]) for t in texts for i in range(len(toks(t))))
            ctx = Counter()
            for g, n in grams.items():
                ctx[g[:-1]] += n
            ratio = discounts(Counter(grams.values()), gt_max, absolute)
            raw = {g: d(ratio, n) * n / ctx[g[:-1]] for g, n in grams.items()}
            s, q = defaultdict(float), defaultdict(float)
            for g, x in raw.items():
                s[g[:-1]] += x
                q[g[:-1]] += self.prob(g[1:-1], g[-1])
            f = {h: ctx[h] / (ctx[h] + 1) / s[h] if s[h] > 1 - 1e-9 else 1.0 for h in s}
            self.star |= {g: x * f[g[:-1]] for g, x in raw.items()}
            self.alpha |= {h: (1 - s[h] * f[h]) / (1 - q[h]) for h in s}

    def prob(self, h, w):
        if not h:
            return self.p.get(w, self.unknown)
        if (*h, w) in self.star:
            return self.star[(*h, w)]
        return self.alpha.get(h, 1.0) * self.prob(h[1:], w)

    def row(self, t):
        ts = toks(t)
        base = sum(math.log10((self.c[w] + 1) / (self.n + self.v + 1)) for w in ts)
        padded = ["<s>"] * (self.order - 1) + ts
        return len(ts), sum(self.c[w] > 0 for w in ts), self.n, base, sum(math.log10(self.prob(tuple(padded[i : i + self.order - 1]), w)) for i, w in enumerate(ts))


def corpus():
    rnd = random.Random(6)
    vocabulary = ["w%d" % int(rnd.paretovariate(0.7)) for _ in range(3000)] + ["É", "the"] * 300
    rows = [(i, " \t\n"[i % 3].join(rnd.choice(vocabulary) for _ in range(rnd.randint(0, 80))).upper()) for i in range(400)]
    return rows + [(500, None), (501, ""), (None, "the w1"), (3, "dup id"), (502, "the " * 700), (503, "onlyonce followed " * 9), (504, "onlyonce followed " * 9), (505, "solo pair")]


def held(i):
    return i is not None and zlib.crc32(str(i).encode()) % 7 == 2


@pytest.mark.parametrize("order,flush,parts,block", [(1, 6_000_000, 3, 1000), (2, 6_000_000, None, 1_000_000), (2, 700, 5, 300), (3, 6_000_000, 4, 1_000_000), (3, 700, 5, 300), (4, 900, 3, 200)])
def test_against_plain_dictionaries(spark, monkeypatch, order, flush, parts, block):
    monkeypatch.setattr(katz, "BLOCK", block)
    rows = corpus()
    docs = spark.createDataFrame([(i, t, 0.0) for i, t in rows], "doc_id long, text string, score double").repartition(3, "doc_id")
    ref = Reference([t for i, t in rows if not held(i)], order)
    key = lambda r: (str(r[0]), r[2], r[5])
    got = sorted(([r.doc_id, r.held_out, r.n_tokens, r.n_known, r.train_tokens, r.base_score, r.score] for r in katz_scores(docs, order=order, flush=flush, parts=parts).collect()), key=key)
    want = sorted(([i, held(i), *ref.row(t)] for i, t in rows), key=key)
    assert len(got) == len(want)
    for g, w in zip(got, want):
        assert g[:5] == w[:5] and g[5] == pytest.approx(w[5]) and g[6] == pytest.approx(w[6]), (g, w)


def test_probabilities_of_a_context_sum_to_one():
    ref = Reference([t for _, t in corpus()], 3)
    words = list(ref.p) + ["<unknown>"]
    for h in [("<s>",), ("the",), ("w1",), ("w99999",), ("</s>",), ("<s>", "<s>"), ("the", "the"), ("w1", "the"), ("É", "w1"), ("x", "w1"), ("x", "y")]:
        assert sum(ref.prob(h, w) for w in words) == pytest.approx(1.0)
    assert all(0 < a for a in ref.alpha.values())
    assert ref.prob(("solo",), "pair") > 2 * ref.alpha[("solo",)] * ref.p["pair"]


def test_discounts_free_the_mass_of_the_counts_of_one():
    for counts in ({1: 1000, 2: 300, 3: 150, 4: 90, 5: 60, 6: 42}, {1: 5, 2: 9, 3: 2}, {1: 10, 2: 5, 4: 3}, {1: 1000, 2: 10, 3: 10, 4: 10, 5: 10, 6: 500}):
        d = discounts(counts, 5, 0.75)
        freed = sum(n * r * (1 - d[r]) for r, n in counts.items() if r <= 5)
        assert all(0 < x <= 1 for x in d[1:])
        most = sum(n * r * 0.95 for r, n in counts.items() if r <= 5)
        assert freed == pytest.approx(min(counts[1], most))
    assert discounts({}, 5, 0.75)[1] > 0


def test_spread_contexts_have_places_in_proportion_to_their_counts():
    s = katz.Spread.of(np.array([9, 5, 7], np.uint64), np.array([1000, 100, 333]), 1000, 10)
    assert s.ctx.tolist() == [5, 7, 9] and s.places.tolist() == [4, 14, 40]
    parts = katz._part_of_pair(np.full(4000, 9, np.uint64), katz.B.mix(np.arange(4000, dtype=np.uint64)), s, 10)
    assert np.bincount(parts, minlength=10).max() < 1000


def test_empty_tables(spark):
    docs = spark.createDataFrame(corpus(), "doc_id long, text string")
    assert katz_scores(docs.limit(0)).collect() == []
    only_held = docs.where("doc_id IS NOT NULL").where("crc32(cast(doc_id as string)) % 7 = 2")
    got = katz_scores(only_held).collect()
    assert got and all(r.n_known == 0 and r.train_tokens == 0 and r.score == r.base_score == 0 for r in got)
