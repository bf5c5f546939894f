"""Retained contexts of the suffix tree against counting every context in plain Python."""

import math
import random
from collections import Counter, defaultdict

import numpy as np
import pytest

from densecount.llm import suffix_lm


@pytest.mark.parametrize("seed", range(3))
def test_retained_contexts(seed):
    r, spec = random.Random(seed), suffix_lm.TreeSpec(depth=4, least=5, gain=6.0)
    text = "".join(r.choice(["aba ", "abb ", "cab ", "b"]) for _ in range(400)).encode()
    symbols = np.frombuffer(text, np.uint8)
    keys, counts = np.unique(suffix_lm.grams(symbols, np.array([0, len(text)]), spec.depth), return_counts=True)
    got = defaultdict(dict)
    for level, context, symbol, n in zip(*(suffix_lm.states(keys, counts.astype(np.int64), spec)[c].to_pylist() for c in ("level", "context", "symbol", "n")), strict=True):
        got[level, bytes((context >> 8 * (level - 1 - i)) & 255 for i in range(level))][symbol] = n  # nearest byte first
    follow = defaultdict(Counter)
    padded = b"\0" * spec.depth + text
    for i in range(len(text)):
        for n in range(1, spec.depth + 1):
            follow[padded[spec.depth + i - n : spec.depth + i][::-1]][text[i]] += 1

    def diverges(c):
        own, up = follow[c], follow[c[:-1]]
        total, above = sum(own.values()), sum(up.values())
        return sum(k * math.log(k / total / (up[s] / above)) for s, k in own.items()) >= spec.gain

    kept = {c for c in follow if len(c) >= 2 and sum(follow[c].values()) >= spec.least and (len(c) == 2 or diverges(c))}
    kept |= {c[:n] for c in kept for n in range(2, len(c))}
    assert {c for _, c in got} == kept
    assert all(got[len(c), c] == dict(follow[c]) for c in kept)


def test_every_distribution_sums_to_one():
    symbols = np.frombuffer(b"the cat sat on the mat and the cat ran " * 30, np.uint8)
    spec = suffix_lm.TreeSpec(least=2, gain=1.0)
    keys, counts = np.unique(suffix_lm.grams(symbols, np.array([0, len(symbols)]), spec.depth), return_counts=True)
    import pyarrow as pa

    short = pa.table({"level": pa.array([0, 0], pa.int32()), "context": [0, 0], "symbol": pa.array([97, 116], pa.int32()), "n": [60, 150]})
    tree = suffix_lm.Tree(pa.concat_tables([short.cast(suffix_lm.SHORT), suffix_lm.states(keys, counts.astype(np.int64), spec).cast(suffix_lm.SHORT)]), spec)
    for key in keys[:: max(1, len(keys) // 7)].tolist():
        every = np.array([key >> 8 << 8 | s for s in range(256)], np.uint64)
        assert tree.probability(every).sum() == pytest.approx(1)
