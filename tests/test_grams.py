"""Bitmaps of substrings in NumPy against hashlib and the relational build."""

import hashlib

import numpy as np
from pyspark.sql import functions as F

from densecount import workloads
from densecount.operators import build, grams


def test_md5_keys_of_any_length():
    data = np.random.default_rng(1).integers(256, size=400, dtype=np.uint8)
    padded = np.append(data, np.zeros(4, np.uint8)).astype(np.uint32)
    four = padded[:-3] | padded[1:-2] << 8 | padded[2:-1] << 16 | padded[3:] << 24
    at = np.array([0, 1, 2, 3, 77, 250])
    for size in (0, 1, 4, 5, 31, 55, 56, 63, 64, 65, 119, 120, 124):
        want = [int(hashlib.md5(data[p : p + size].tobytes()).hexdigest()[:15], 16) for p in at]
        assert grams._md5_key(four, at, size).tolist() == want


def test_substrings_make_the_bitmaps_of_their_rows(spark):
    texts = ["", None, "abc", "naïve café – 漢字かな交じり文 😀😀 x", "the same line\nthe same line", "ab" * 40, "ab" * 40, "abab"]
    df = spark.createDataFrame([("de" if i % 2 else None, t) for i, t in enumerate(texts)], "lang string, text string")
    rows = [(g, k, t[i : i + k]) for g, t in df.collect() if t is not None for k in (1, 3, 8) for i in range(len(t) - k + 1)]
    sized = spark.createDataFrame(rows, "lang string, n int, t string").select(F.struct("lang", "n").alias("g"), "t")
    want = sorted(map(repr, build.register_bitmaps(sized, "t", ["g"], 88).collect()))
    assert sorted(map(repr, grams.substring_bitmaps(df, "lang", "text", (1, 3, 8), 88).collect())) == want


def test_long_texts_lose_nothing_where_they_are_cut(monkeypatch):
    text = "".join(chr(c) for c in np.random.default_rng(2).choice([97, 98, 233, 0x6F22, 0x1F600], 700))
    data, ends = np.frombuffer(text.encode(), np.uint8), np.array([len(text.encode())])
    whole = {k: np.zeros(88 * grams.LEVELS, bool) for k in (2, 9)}
    grams.mark_all(whole, {k: grams.slots() for k in whole}, data, ends, 88)
    cut = {k: np.zeros(88 * grams.LEVELS, bool) for k in (2, 9)}
    last = {k: grams.slots() for k in cut}
    monkeypatch.setattr(grams, "PIECE", 101)
    parts = list(grams._pieces(data, np.array([0, len(data)]), np.array([0]), 9))
    assert len(parts) > 10
    for part in parts:
        grams.mark_all(cut, last, *part, 88)
    assert all((whole[k] == cut[k]).all() for k in whole)


def test_substrings_do_not_become_rows(spark):
    plan = workloads.wl_kmer_distinct(spark, "/root/testdata/sf0.001")._jdf.queryExecution().optimizedPlan().toString()
    assert "array_join" not in plan and "md5" not in plan
