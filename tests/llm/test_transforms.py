"""Merged shard orders and the FM-index against plain sorting and plain search."""

import numpy as np
import pytest

from densecount.llm import bwt_dedup, fm_index


@pytest.mark.parametrize("seed", range(6))
def test_merge_is_the_order_of_the_union(seed):
    rng = np.random.default_rng(seed)
    side, width = 10, 34
    rows = rng.integers(97, 99, (300, width)).astype(np.uint8)
    rows[::3] = rows[:1]  # copies within and across shards
    rows[5:9, -3:] = 0
    cuts = [0, 1, 40, 41, 200, 300]
    parts, left, at = [], [], 0
    for a, b in zip(cuts, cuts[1:], strict=False):
        right_order, left_order = bwt_dedup.sorted_shard(rows[a:b], side)
        back = np.empty(b - a, np.int64)
        back[right_order] = np.arange(b - a)
        parts.append(rows[a:b][right_order])
        left.append(back[left_order] + at)
        at += b - a
    matrix = np.concatenate(parts)
    after, before = bwt_dedup.sides(matrix, side)
    for words, order, text in ((after, np.arange(300), [bytes(r[side:]) for r in matrix]), (before, np.concatenate(left), [bytes(r[:side][::-1]) for r in matrix])):
        got, lcp = bwt_dedup.interleave(words, order)
        sorted_text = [text[i] for i in got]
        assert sorted_text == sorted(text)
        for i in range(1, 300):
            x, y = sorted_text[i - 1], sorted_text[i]
            want = next((k for k in range(len(x)) if x[k] != y[k]), len(x))
            assert min(lcp[i], len(x)) == want


def test_merge_of_nothing():
    order, lcp = bwt_dedup.interleave(np.zeros((0, 3), np.uint64), np.zeros(0, np.int64))
    assert len(order) == len(lcp) == 0


@pytest.mark.parametrize("seed", range(4))
def test_matching_statistics_of_streamed_patterns(seed):
    rng = np.random.default_rng(seed)
    depth, rows = 5, rng.integers(1, 4, (40, 9))
    text = np.concatenate([rows, np.zeros((40, 1), np.int64)], 1).ravel()
    index = fm_index.FMIndex(text, 4, depth)
    plain = text.tolist()
    queries = np.concatenate([rows[:10], rng.integers(0, 4, (10, 9))])
    for c, size, lo, hi in index.matching(queries, 2):
        for q in range(len(queries)):
            want, count = 0, 0
            for k in range(1, depth + 1):
                pattern = queries[q, c : c + k].tolist()
                if len(pattern) < k or 0 in pattern:
                    break
                n = sum(plain[i : i + k] == pattern for i in range(len(plain)))
                if n < 2:
                    break
                want, count = k, n
            assert size[q] == want
            if want:
                assert hi[q] - lo[q] == count
