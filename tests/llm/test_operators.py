"""Each operator against brute force on small texts with nulls, empties, ties and repeats."""

import hashlib
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from densecount.llm import bwt_dedup, decontaminate, fm_dedup, license_scan, line_dedup, ngram_join, packing, quality_rules, suffix_lm, toxicity

WORD = re.compile(r"[^\x20\x09-\x0D]+")
ALNUM = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def lower(t):
    return re.sub("[A-Z]", lambda m: m[0].lower(), t or "")


def table(spark, rows):
    """Documents with extra columns whose names clash with the operators' own."""
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    return df.withColumns({"n_words": F.lit("x"), "bucket": F.lit(1), "spans": F.lit(None).cast("string"), "gone": F.lit(2)})


@pytest.fixture(scope="module")
def texts():
    r = random.Random(11)
    words = [a + b for a in "ka lo mi né tu ".split() for b in "ra so ti vu xe".split()]
    base = [[r.choice(words) for _ in range(120)] for _ in range(4)]
    docs = []
    for i in range(50):
        w = list(r.choice(base))
        for _ in range(r.choice([0, 0, 1, 2, 6])):
            w[r.randrange(len(w))] = r.choice(words)
        w = w[r.choice([0, 0, 20]) :] + r.choice([[], base[0][:25], ["same"] * 30])
        docs.append((i, " ".join(w)))
    docs += [(60, None), (61, ""), (62, " \n\t"), (63, "one"), (64, "two words"), (65, docs[0][1]), (66, docs[0][1]), (67, "x " * 3000)]
    return docs


def test_license_scan(spark):
    rows = [(1, "Foo. Licensed under the Apache License, Version 2.0."), (2, "gnu general public license mit license mit license"), (3, None), (4, "cc\nby mit. license"), (5, "nothing of the kind")]
    got = {r["doc_id"]: r for r in license_scan.scan(table(spark, rows)).collect()}
    assert got[1]["base_labels"] == "apache" and got[1]["labels"] == "apache,apache-2.0" and got[1]["first_word"] == 4
    assert (got[2]["n_base"], got[2]["first_word"], got[2]["last_word"], got[2]["base_labels"]) == (3, 0, 6, "gpl,mit")
    assert got[3]["n_words"] == 0 and got[3]["score"] == 0 and got[3]["first_word"] is None
    assert got[4]["n_base"] == 2 and got[5]["n_base"] == 0 and got[5]["labels"] == ""


def test_license_long_template(spark):
    mit = next(t for k, t in license_scan.TEMPLATES if k == "mit")
    rows = [(1, "before " + mit.replace("merge", "fuse") + " after"), (2, " ".join(mit.split()[:5]))]
    got = {r["doc_id"]: r for r in license_scan.scan(table(spark, rows)).collect()}
    assert got[1]["labels"] == "mit" and got[1]["n_base"] == 0 and got[1]["spans"][0]["first_word"] == 1 and got[1]["score"] > 0.9
    assert got[2]["labels"] == ""


def test_decontamination(spark, texts):
    item = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon".split()
    edited = item[:7] + ["new"] + item[8:13] + item[14:]
    rows = [*texts, (100, " ".join(["pad"] * 30 + item)), (101, " ".join(edited + ["pad"] * 10)), (102, " ".join(item[:4])), (103, "ALPHA, Beta; " + " ".join(item[2:]))]
    bench = spark.createDataFrame([(7, " ".join(item)), (8, None), (9, "two words"), (10, "")], "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]): r for r in decontaminate.leaks(table(spark, rows), bench).collect()}
    assert {k[0] for k in got if k[1] == 7} == {100, 101, 103}
    assert got[100, 7]["score"] == 1 and got[100, 7]["first_word"] == 30 and (64, 9) in got
    blocks = decontaminate.leaks(table(spark, rows), bench, decontaminate.LeakSpec(block_chars=40))
    assert {(r["doc_id"], r["item_id"]) for r in blocks.collect()} == set(got)


@pytest.mark.parametrize("n,percent,options", [(3, 90, {}), (5, 80, {"all_pairs": 2, "combined": 12, "meet": 2}), (2, 70, {"all_pairs": 1})])
def test_ngram_join(spark, texts, n, percent, options):
    sets = {}
    for i, t in texts:
        w = WORD.findall(lower(t))
        sets[i] = set(zip(*[w[k:] for k in range(n)])) if len(w) >= n else ({tuple(w)} if w else set())
    root = {i: i for i in sets}

    def find(x):
        return x if root[x] == x else find(root[x])

    for a in sets:
        for b in sets:
            both = len(sets[a] & sets[b])
            if b < a and sets[a] and 100 * both >= percent * (len(sets[a]) + len(sets[b]) - both):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    rows = table(spark, texts).unionByName(table(spark, [(None, "no id")]))
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in ngram_join.join(rows, ngram_join.JoinSpec(n=n, percent=percent, **options)).collect()}
    assert got.pop(None)[1] is None
    assert got == {i: (len(s), find(i)) for i, s in sets.items()}


@pytest.mark.parametrize("options", [{}, {"all_pairs": 2, "meet": 7, "slice": 16}, {"all_pairs": 12, "meet": 20}, {"all_pairs": 2, "meet": 5, "combined": 6}])
def test_ngram_join_counts_every_link(spark, options):
    r = random.Random(3)
    docs = []
    for g in range(3):  # groups whose members are similar or just not
        base = [f"w{g}x{k}" for k in range(90)]
        for k in range(40):
            w = list(base)
            for at in r.sample(range(len(w)), r.choice([0, 1, 2, 4, 6])):
                w[at] = f"edit{r.randrange(4)}"
            docs.append((100 * g + k, " ".join(w)))
    docs += [(900, None), (901, ""), (902, docs[5][1])]
    sets = {i: frozenset(zip(*[WORD.findall(t or "")[k:] for k in range(3)])) for i, t in docs}
    kinds = set(sets.values()) - {frozenset()}
    want = {i: sum(a != b and 100 * len(a & b) >= 80 * len(a | b) for b in kinds) if a else 0 for i, a in sets.items()}
    got = {x["doc_id"]: x["n_links"] for x in ngram_join.join(table(spark, docs).unionByName(table(spark, [(None, docs[5][1])])), ngram_join.JoinSpec(n=3, percent=80, **options)).collect()}
    assert got.pop(None) == 0
    assert got == want and 0 < sum(want.values()) < len(kinds) ** 2 / 3


def test_line_dedup(spark):
    rows = [(1, "a\nb\nc\nd"), (2, "x\na\n\nb\nc\ny"), (3, "a\nb"), (4, None), (5, "z\nz\nz\nz"), (6, "a\nb\nc\nd")]
    got = {r["doc_id"]: r["text"] for r in line_dedup.dedup(table(spark, rows)).collect()}
    assert got == {1: "a\nb\nc\nd", 2: "x\n\ny", 3: "a\nb", 4: None, 5: "z", 6: ""}


def test_toxicity_generalises(spark):
    r = random.Random(5)
    words = ["".join(r.choice("bdfgklmnprst") + r.choice("aeiou") for _ in range(3)) for _ in range(400)]
    docs, labels = [], []
    for i in range(600):
        w = [r.choice(words) for _ in range(60)]
        toxic = i % 3 == 0
        if toxic:
            for _ in range(3):
                w[r.randrange(60)] = "zzgrub" + r.choice(words)[:3]
        docs.append((i, " ".join(w)))
        labels.append((i, int(toxic)))
    rows = table(spark, [*docs, (900, None), (901, "")])
    got = {x["doc_id"]: x for x in toxicity.score(rows, spark.createDataFrame(labels, "doc_id long, toxic int")).collect()}
    held = [i for i, _ in docs if zlib.crc32(str(i).encode()) % 5 == 0]
    assert all(got[i]["held_out"] == (zlib.crc32(str(i).encode()) % 5 == 0) for i in got)
    right = sum(got[i]["predicted"] == (i % 3 == 0) for i in held)
    assert right >= 0.95 * len(held) and got[900]["predicted"] == got[901]["predicted"] == 0
    assert any(got[i]["spans"] for i in held if i % 3 == 0)


def test_toxicity_without_labels(spark):
    got = toxicity.score(table(spark, [(1, "a b"), (2, None)]), spark.createDataFrame([], "doc_id long, toxic int")).collect()
    assert all(r["score"] < 0.5 for r in got) and len(got) == 2


def test_suffix_lm(spark, texts):
    rows = [*texts, (None, "ka ra")]
    tokens = {i: [*WORD.findall(lower(t)), "<end>"] for i, t in rows}
    held = {i: zlib.crc32(("" if i is None else str(i)).encode()) % 5 == 1 for i in tokens}
    count = Counter(w for i, t in tokens.items() if not held[i] for w in t)
    total, kinds = sum(count.values()), len(count)
    got = {r["doc_id"]: r for r in suffix_lm.score(table(spark, rows)).collect()}
    assert set(got) == set(tokens)
    for i, t in tokens.items():
        base = sum(np.log10((count[w] + 0.5) / (total + 0.5 * (kinds + 1))) for w in t)
        r = got[i]
        assert (r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"]) == (held[i], len(t), sum(count[w] > 0 for w in t), total)
        assert r["base_score"] == pytest.approx(base) and r["score"] < 0
    assert sum(got[i]["score"] for i in got if held[i]) > sum(got[i]["base_score"] for i in got if held[i])


def test_suffix_states_do_not_depend_on_the_corpus_size():
    """A context that diverges is retained however much else there is."""
    r = np.random.default_rng(4)
    one = np.frombuffer(b"aqux bquy " * 60, np.uint8)
    other = r.integers(97, 123, 400_000).astype(np.uint8)
    spec = suffix_lm.TreeSpec(least=8)

    def kept(symbols):
        key, count = np.unique(suffix_lm.grams(symbols, np.array([0, len(symbols)]), spec.depth), return_counts=True)
        rows = suffix_lm.states(key, count.astype(np.int64), spec).to_pylist()
        return {(x["level"], x["context"]) for x in rows}

    near = int.from_bytes(b"uqa", "big")  # "aqu", nearest byte on top
    assert (3, near) in kept(one) and (3, near) in kept(np.concatenate([one, np.tile(np.where(other == 113, 97, other), 60)]))


def test_quality_features(spark, texts):
    rows = [*texts, (70, "a#b $$ c\nc\nc\n \n"), (71, "r s t r s t u")]
    got = {r["doc_id"]: r for r in quality_rules.judge(table(spark, rows)).collect()}
    for i, t in rows:
        w, lines = WORD.findall(t or ""), [x for x in (t or "").split("\n") if WORD.search(x)]
        c, cover = Counter(zip(w, w[1:], w[2:])), set()
        for k in range(len(w) - 2):
            if c[tuple(w[k : k + 3])] > 1:
                cover |= {k, k + 1, k + 2}
        want = (len(w), sum(map(len, w)), sum(x in "#*$%&|<>" for x in t or ""), len(lines) - len(set(lines)), len(cover))
        r = got[i]
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == want
        assert r["base_failed"] == (len(w) < 50 or 100 * len(cover) > 50 * len(w))
        assert not (r["kept"] and r["base_failed"])


def test_packing(spark, texts):
    from tokenizers import Tokenizer

    rows = [*texts, (80, "it's  odd\n\n\ttext 中文 <|endoftext|> é's"), (81, "word " * 5000)]
    spec = packing.PackSpec(capacity=256)
    tokenizer = Tokenizer.from_file(packing.default_tokenizer())
    by = defaultdict(list)
    places = defaultdict(list)
    for r in packing.pack(table(spark, rows), spec).collect():
        by[r["doc_id"]].append(r)
        places[r["sequence_id"]].append((r["offset"], r["length"]))
    for i, t in rows:
        ids = [*tokenizer.encode(t or "", add_special_tokens=False).ids, 2]
        parts = sorted(by[i], key=lambda r: r["piece"])
        assert [p["piece"] for p in parts] == list(range(-(-len(ids) // 256))) and all(p["length"] == 256 for p in parts[1:])
        for p in parts:
            assert zlib.crc32(np.array(ids[p["start"] : p["start"] + p["length"]], "<u4").tobytes()) == p["ids_crc32"]
    for x in places.values():
        at = 0
        for offset, length in sorted(x):
            assert offset == at
            at += length
        assert at <= 256


def brute_words(docs, window=20):
    words, first = {i: WORD.findall(t or "") for i, t in docs}, {}
    for i in sorted(words):
        for k in range(len(words[i]) - window + 1):
            first.setdefault(tuple(words[i][k : k + window]), (i, k))
    out = {}
    for i, w in words.items():
        gone = [False] * len(w)
        for k in range(len(w) - window + 1):
            if first[tuple(w[k : k + window])] < (i, k):
                gone[k : k + window] = [True] * window
        out[i] = (len(w), sum(gone), hashlib.sha256(" ".join(x for x, g in zip(w, gone, strict=True) if not g).encode()).hexdigest())
    return out


def test_fm_dedup(spark, texts):
    got = {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept_sha256"]) for r in fm_dedup.dedup(table(spark, texts).unionByName(table(spark, [(None, texts[0][1])]))).collect()}
    assert got.pop(None)[1] == 0
    assert got == brute_words(texts)


def test_fm_dedup_repeated_rows(spark):
    text = lambda k, n: " ".join(f"w{k}x{i}" for i in range(n))
    docs = [(1, text(1, 60)), (2, text(2, 40) + " " + text(1, 30)), (3, text(3, 25) + " stop " + text(3, 25)), (4, text(4, 10))]
    rows = spark.createDataFrame([*docs, docs[0], docs[1], docs[2], docs[2]], "doc_id long, text string").coalesce(1)  # in one block
    got = [(r["doc_id"], (r["n_words"], r["n_removed"], r["kept_sha256"])) for r in fm_dedup.dedup(rows).collect()]
    want = brute_words(docs)
    assert sorted(got) == sorted((i, want[i]) for i in [1, 2, 3, 4, 1, 2, 3, 3])


def test_bwt_dedup(spark, texts):
    first = {}
    for i, t in sorted(texts, key=lambda x: x[0]):
        b = (t or "").encode()
        for k in range(len(b) - 49):
            first.setdefault(b[k : k + 50], i)
    want = {}
    for i, t in texts:
        b = (t or "").encode()
        gone = bytearray(len(b))
        for k in range(len(b) - 49):
            if first[b[k : k + 50]] < i:
                gone[k : k + 50] = b"\1" * 50
        kept = bytes(x for x, g in zip(b, gone, strict=True) if not g)
        want[i] = (len(b), sum(gone), len(re.findall(b"\1+", bytes(gone))), hashlib.sha256(kept).hexdigest())
    got = {r["doc_id"]: (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in bwt_dedup.dedup(table(spark, texts)).collect()}
    assert got == want


@pytest.mark.parametrize("f", [license_scan.scan, line_dedup.dedup, ngram_join.join, quality_rules.judge, packing.pack, fm_dedup.dedup, bwt_dedup.dedup, suffix_lm.score], ids=lambda f: f.__module__.split(".")[-1])
def test_empty_table(spark, f):
    assert f(table(spark, [(1, "x")]).where("doc_id > 1")).count() == 0
