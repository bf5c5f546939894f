"""Every stage of the pipeline against brute force, each on an input of its own."""

import random
import re

import pytest
from pyspark.sql import functions as F

from densecount.llm import quality_rules, stages

WORD = re.compile(r"[^\x20\x09-\x0D]+")
ITEM = "which river crosses the seven northern valleys before it turns west and meets the cold inland sea near the harbour town of old lanterns".split()


def pool(r, n):
    return ["".join(r.choice("bdfklmnprst") + r.choice("aeiou") for _ in range(r.choice([2, 3]))) for _ in range(n)]


@pytest.fixture(scope="module")
def rows():
    r = random.Random(4)
    words = pool(r, 900)
    docs = [(i, " ".join(r.choice(words) for _ in range(r.choice([70, 120])))) for i in range(24)]
    near = docs[3][1].split()
    near[5] = "changed"
    docs += [(30, " ".join(near)), (31, docs[3][1]), (32, " ".join(near[:40] + ["other"] * 3 + near[43:]))]
    docs += [(40, "# $ % & " * 80), (41, "short text"), (42, None), (43, ""), (44, "same words " * 60)]
    docs += [(50, docs[7][1] + "\n" + "\n".join(f"line {k} of a notice" for k in range(5))), (51, docs[8][1] + "\n" + "\n".join(f"line {k} of a notice" for k in range(5)))]
    docs += [(60, docs[9][1] + " " + " ".join(ITEM)), (61, " ".join(ITEM[:9] + ["x"] + ITEM[10:]) + " " + docs[10][1]), (62, " ".join(words * 3))]
    return docs


@pytest.fixture(scope="module")
def sf_dir(spark, tmp_path_factory):
    where = str(tmp_path_factory.mktemp("sf"))
    spark.createDataFrame([(1, " ".join(ITEM)), (2, None)], "item_id long, text string").write.parquet(f"{where}/benchmark.parquet")
    return where


def frame(spark, rows):
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    return df.select("doc_id", "text", F.lit("en").alias("lang"), F.lit("s").alias("source"), F.length("text").cast("long").alias("n_chars"), F.lit(1).alias("kept"), F.lit("x").alias("bucket"))


def shingles(text, n):
    w = WORD.findall(re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    return frozenset(zip(*[w[k:] for k in range(n)], strict=False)) if len(w) >= n else frozenset({tuple(w)} if w else ())


def test_quality(spark, rows, sf_dir):
    out = stages.quality(spark, frame(spark, rows), sf_dir)
    assert out.columns == stages.COLUMNS
    got = {r["doc_id"] for r in out.collect()}
    verdict = {r["doc_id"] for r in quality_rules.judge(frame(spark, rows)).where("kept").collect()}
    assert got == verdict and not got & {40, 41, 42, 43, 44} and set(range(24)) <= got


def test_lines(spark, rows, sf_dir):
    got = {r["doc_id"]: r for r in stages.lines(spark, frame(spark, rows), sf_dir).collect()}
    assert set(got) == {i for i, _ in rows}
    for i, t in rows:
        want = t.rsplit("\n", 5)[0] if i == 51 else t
        assert got[i]["text"] == want and got[i]["n_chars"] == (None if want is None else len(want))


def test_near_copies(spark, rows, sf_dir):
    sets = {i: shingles(t, 5) for i, t in rows}
    group = {i: i for i in sets}
    for _ in sets:
        for a in sets:
            for b in sets:
                if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                    group[a] = min(group[a], group[b])
    got = {r["doc_id"] for r in stages.near_copies(spark, frame(spark, rows), sf_dir).collect()}
    assert got == {i for i in sets if group[i] == i} and not got & {30, 31}


def test_leaks(spark, rows, sf_dir):
    got = {r["doc_id"] for r in stages.leaks(spark, frame(spark, rows), sf_dir).collect()}
    assert got == {i for i, _ in rows} - {60, 61}


def test_pack(spark, rows, sf_dir):
    out = stages.pack(spark, frame(spark, rows), sf_dir).collect()
    total, ends = {}, {}
    for r in out:
        total[r["doc_id"]] = total.get(r["doc_id"], 0) + r["length"]
        ends.setdefault(r["sequence_id"], []).append((r["offset"], r["offset"] + r["length"]))
    assert set(total) == {i for i, _ in rows} and total[42] == total[43] == 1
    for spans in ends.values():
        spans.sort()
        assert spans[0][0] == 0 and spans[-1][1] <= 1024 and all(a[1] == b[0] for a, b in zip(spans, spans[1:], strict=False))
    assert len(ends) <= -(-sum(total.values()) // 1024) + 1


def test_stages_of_nothing(spark, rows, sf_dir):
    none = frame(spark, rows).where("doc_id < 0")
    for _, stage in stages.STAGES:
        assert stage(spark, none, sf_dir).count() == 0
