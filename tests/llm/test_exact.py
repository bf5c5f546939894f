"""Alignments and chain marginals against plain dynamic programs and enumeration."""

import itertools
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from densecount.llm import decontaminate, toxicity


def smith_waterman(x, y, spec):
    h = np.zeros((len(x) + 1, len(y) + 1), int)
    for i in range(1, len(x) + 1):
        for j in range(1, len(y) + 1):
            h[i, j] = max(0, h[i - 1, j - 1] + (spec.match if x[i - 1] == y[j - 1] else -spec.mismatch), h[i - 1, j] - spec.gap, h[i, j - 1] - spec.gap)
    return int(h.max())


@pytest.mark.parametrize("seed", range(5))
def test_alignment_scores(seed):
    rng, spec = np.random.default_rng(seed), decontaminate.LeakSpec()
    pairs = [(rng.integers(2, 7, rng.integers(1, 30)).astype(np.uint64), rng.integers(2, 7, rng.integers(1, 20)).astype(np.uint64)) for _ in range(20)]
    best, _ = decontaminate.align([a for a, _ in pairs], [b for _, b in pairs], spec)
    assert best.tolist() == [smith_waterman(a.tolist(), b.tolist(), spec) for a, b in pairs]


def test_found_leaks_are_those_of_every_alignment(spark):
    """Recall against aligning every document with every item: all pairs from the threshold on
    that share a seed twice are found, with the same score, and no other pair is."""
    r, spec = random.Random(8), decontaminate.LeakSpec()
    words = [f"w{k}" for k in range(500)]
    items = [[r.choice(words) for _ in range(r.choice([12, 30]))] for _ in range(8)]
    docs = []
    for i in range(40):
        w = [r.choice(words) for _ in range(50)]
        if i % 2:
            copy = list(r.choice(items))
            for _ in range(r.choice([0, 1, 2, 4, 8])):
                at = r.randrange(len(copy))
                copy[at : at + 1] = r.choice([[], ["new"], [copy[at], "more"]])
            at = r.randrange(50)
            w[at:at] = copy
        docs.append((i, w))
    want = {}
    for i, w in docs:
        for k, item in enumerate(items):
            share = smith_waterman(w, item, spec) / (spec.match * len(item))
            if share >= spec.threshold:
                want[i, k] = share
    rows = spark.createDataFrame([(i, " ".join(w)) for i, w in docs], "doc_id long, text string")
    bench = spark.createDataFrame([(k, " ".join(x)) for k, x in enumerate(items)], "item_id long, text string")
    got = {(x["doc_id"], x["item_id"]): x["score"] for x in decontaminate.leaks(rows, bench).collect()}
    seeds = lambda w: {tuple(w[k : k + spec.n]) for k in range(len(w) - spec.n + 1)}
    reachable = {p for p in want if len(seeds(docs[p[0]][1]) & seeds(items[p[1]])) >= spec.min_hits}
    assert set(got) == reachable and len(reachable) >= 0.9 * len(want)
    assert all(got[p] == pytest.approx(want[p]) for p in got)


def test_marginals_by_enumeration():
    rng = np.random.default_rng(3)
    size = [1, 5, 0, 8, 3]
    ptr = np.concatenate([[0], np.cumsum(size)])
    s, chain = rng.normal(0, 2, ptr[-1]), rng.normal(0, 1, (2, 2))
    got = toxicity.marginals(s, ptr, chain)
    for a, n in zip(ptr, size, strict=False):
        total, one = 0.0, np.zeros(n)
        for y in itertools.product((0, 1), repeat=n):
            w = np.exp(sum(s[a + t] * y[t] for t in range(n)) + sum(chain[y[t - 1], y[t]] for t in range(1, n)))
            total += w
            one += w * np.array(y)
        assert np.allclose(got[a : a + n], one / total)


def test_empty_tables(spark):
    docs = spark.createDataFrame([(1, "x")], "doc_id long, text string").withColumn("score", F.lit("clash"))
    none = docs.where("doc_id > 1")
    labels = spark.createDataFrame([(1, 1)], "doc_id long, toxic int")
    bench = spark.createDataFrame([(1, "a b c")], "item_id long, text string")
    assert decontaminate.leaks(none, bench).count() == 0 and decontaminate.leaks(docs, bench.where("item_id > 1")).count() == 0
    assert toxicity.score(none, labels).count() == 0 and toxicity.score(docs, labels.where("doc_id > 1")).count() == 1
