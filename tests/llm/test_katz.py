"""The block-wise model against a dictionary model, and its distributions against 1."""

import math
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

from patchspace.llm import katz

WORD = re.compile(r"[^\x20\x09-\x0D]+")
LOW = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})
SCHEMA = "doc_id long, text string, lang string"


def tokens(text):
    return [*WORD.findall((text or "").translate(LOW)), None]  # None ends a text


class Brute:
    """Dictionaries of n-grams; a history is a tuple that begins with the start mark at the earliest."""

    def __init__(self, docs, order):
        self.order = order
        self.counts = [Counter() for _ in range(order + 1)]  # by length of the n-gram
        for i, t in docs:
            if i is not None and zlib.crc32(str(i).encode()) % 7 == 2:
                continue
            w = ["<s>", *tokens(t)]
            for k in range(1, order + 1):
                for at in range(max(1, k - 1), len(w)):
                    self.counts[k][tuple(w[at - k + 1 : at + 1])] += 1
        self.uni = self.counts[1]
        self.n, self.v = sum(self.uni.values()), len(self.uni)
        cofc = lambda c: np.array([0] + [sum(x == r for x in c.values()) for r in range(1, katz.K + 2)])
        self.d = [katz.good_turing(cofc(c)) if c else None for c in self.counts]
        self.after = defaultdict(dict)
        for k in range(2, order + 1):
            for g, c in self.counts[k].items():
                self.after[g[:-1]][g[-1]] = c
        self.unknown = 1 - sum(self.discount(1, c) * c for c in self.uni.values()) / self.n if self.n else 1.0
        self.scale = 1.0
        if self.n and self.unknown <= 1e-12:
            self.unknown, self.scale = 1 / (self.n + 1), self.n / (self.n + 1)

    def discount(self, k, c):
        return self.d[k][c] if c <= katz.K else 1.0

    def p(self, h, w):
        h = tuple(h)
        if not h:
            c = self.uni[w,]
            return self.discount(1, c) * c * self.scale / self.n if c else self.unknown
        seen = self.after.get(h)
        if not seen:
            return self.p(h[1:], w)
        k, n = len(h) + 1, sum(seen.values())
        if all(c > katz.K for c in seen.values()):
            n += 1
        if w in seen:
            return self.discount(k, seen[w]) * seen[w] / n
        left = 1 - sum(self.discount(k, c) * c for c in seen.values()) / n
        return left / (1 - sum(self.p(h[1:], x) for x in seen)) * self.p(h[1:], w)

    def score(self, text):
        w = ["<s>", *tokens(text)]
        return sum(math.log10(self.p(w[max(0, at - self.order + 1) : at], w[at])) for at in range(1, len(w)))


def corpus():
    rng = np.random.default_rng(5)
    words = np.array([f"W{i}" for i in range(60)])
    docs = [(i, " ".join(rng.choice(words, rng.integers(1, 60), p=np.arange(60, 0, -1) / 1830))) for i in range(120)]
    return docs + [(200, ""), (201, None), (202, "  "), (None, "W1 w2"), (3, "W1\tW2\n W3 new"), (204, "unheard ünheard W1"), (9, docs[9][1])]


@pytest.mark.parametrize("order,block,bucket", [(1, 300, 200), (2, 10_000_000, 10_000_000), (2, 300, 200), (3, 10_000_000, 10_000_000), (3, 300, 200), (3, 40, 60), (4, 200, 150)])
def test_scores_equal_the_dictionary_model(spark, order, block, bucket):
    docs = corpus()
    df = spark.createDataFrame([(i, t, "x") for i, t in docs], SCHEMA).repartition(3)
    got, _ = katz.score(df, order=order, block_tokens=block, bucket_keys=bucket)
    rows = sorted(got.collect(), key=lambda r: (r.doc_id is None, r.doc_id or 0, r.score))
    b = Brute(docs, order)
    want = sorted(((i is None, i or 0, b.score(t)) for i, t in docs))
    assert [r.doc_id or 0 for r in rows] == [w[1] for w in want]
    assert [r.score for r in rows] == pytest.approx([w[2] for w in want], abs=1e-8)
    assert {r.train_tokens for r in rows} == {b.n}
    base = {i: sum(math.log10((b.uni[w,] + 1) / (b.n + b.v + 1)) for w in tokens(t)) for i, t in docs if i == 204}
    own = next(r for r in rows if r.doc_id == 204)
    assert own.base_score == pytest.approx(base[204], abs=1e-8)
    assert (own.n_tokens, own.n_known) == (4, sum(b.uni[w,] > 0 for w in tokens("unheard ünheard W1")))


@pytest.mark.parametrize("order", [2, 3])
def test_every_distribution_sums_to_one(order):
    b = Brute(corpus(), order)
    for h in [("<s>",), ("w0",), ("w1",), ("w59",), ("never",), ("<s>", "w1"), ("w0", "w1"), ("w2", "never")]:
        h = h[-order + 1 :]
        assert sum(b.p(h, *w) for w in b.uni) + b.p(h, "never seen") == pytest.approx(1, abs=1e-9)


@pytest.mark.parametrize("n", [(1000, 400, 210, 120, 80, 55), (3000, 580, 3, 1, 0, 0), (3000, 0, 580, 0, 0, 1), (10, 900, 30, 2, 1, 1), (7, 0, 0, 0, 0, 0), (0, 0, 0, 0, 0, 0), (5, 5, 5, 5, 5, 5)])
def test_discounts_rise_with_the_count(n):
    d = katz.good_turing(np.array([0, *n]))
    assert d[0] == 1 and (d[1:] > 0).all() and (d[1:] < 1).all() and (np.diff(d[1:]) >= 0).all()


def test_repeated_texts_score_apart(spark):
    """A text that occurs twice has likelier trigrams than one of the same words that occurs once."""
    rng = np.random.default_rng(7)
    vocab = [f"v{i}" for i in range(80)]
    once = [(i, " ".join(rng.choice(vocab, 60))) for i in range(60)]
    docs = once + [(1000 + i, once[i][1]) for i in range(10)]
    docs = [(i, t) for i, t in docs if zlib.crc32(str(i).encode()) % 7 != 2]
    twice = {t for _, t in docs if sum(t == u for _, u in docs) == 2}
    got = katz.score(spark.createDataFrame([(i, t, "x") for i, t in docs], SCHEMA))[0].collect()
    by = {r.doc_id: r.score for r in got}
    assert twice and min(by[i] for i, t in docs if t in twice) > max(by[i] for i, t in docs if t not in twice)


def test_empty_table_and_no_training_rows(spark):
    assert katz.score(spark.createDataFrame([], SCHEMA))[0].count() == 0
    out = [i for i in range(60) if zlib.crc32(str(i).encode()) % 7 == 2][:2]
    rows = katz.score(spark.createDataFrame([(i, "a b", "x") for i in out], SCHEMA))[0].collect()
    assert [(r.held_out, r.n_known, r.train_tokens, r.score) for r in rows] == [(True, 0, 0, 0.0)] * 2
