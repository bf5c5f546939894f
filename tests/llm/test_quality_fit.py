"""The weak-supervision fit against the same expectation-maximisation written in NumPy."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from densecount.llm import quality_rules


def fitted(v: np.ndarray, spec: quality_rules.QualitySpec):
    """Prior, P(vote | good), P(vote | bad) after the spec's steps over votes (rows x rules)."""
    rules, n = v.shape[1], max(len(v), 1)
    tables = [np.tile(np.array(x, float), (rules, 1)) for x in (spec.good_votes, spec.bad_votes)]
    prior = spec.prior_good
    hot = np.stack([v == k for k in (-1, 0, 1)], 2)
    for _ in range(spec.iterations):
        odds = np.log(prior / (1 - prior)) + (hot * np.log(tables[0] / tables[1])).sum((1, 2))
        good = 1 / (1 + np.exp(-odds))
        for side, (w, belief, share) in enumerate(((good, spec.good_votes, spec.prior_good), (1 - good, spec.bad_votes, 1 - spec.prior_good))):
            count = np.array(belief) * n * spec.strength * share + (hot * w[:, None, None]).sum(0)
            tables[side] = count / count.sum(1, keepdims=True)
        prior = (n * spec.strength * spec.prior_good + good.sum()) / (n * (1 + spec.strength))
    return prior, *tables


@pytest.fixture(scope="module")
def judged(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    rules = quality_rules.votes(quality_rules.QualitySpec())
    return quality_rules.judge(docs).withColumn("votes", F.array(*rules.values())).toPandas()


def test_posterior_is_that_of_the_fit(judged):
    spec = quality_rules.QualitySpec()
    v = np.stack(judged["votes"].to_numpy())
    passed = ~judged["base_failed"].to_numpy()
    prior, good, bad = fitted(v[passed], spec)
    hot = np.stack([v == k for k in (-1, 0, 1)], 2)
    want = 1 / (1 + np.exp(-(np.log(prior / (1 - prior)) + (hot * np.log(good / bad)).sum((1, 2)))))
    assert np.allclose(judged["p_good"], want, atol=1e-9)
    assert (judged["kept"].to_numpy() == (passed & (want >= spec.keep_from))).all()


def test_fit_overrules_single_votes(judged):
    """Not the filter that asks every rule to hold: uninformative rules are outvoted."""
    bad_vote = np.stack(judged["votes"].to_numpy()).min(1) < 0
    passed, kept = ~judged["base_failed"].to_numpy(), judged["kept"].to_numpy()
    assert (kept & bad_vote).sum() > 0 and (passed & ~kept).sum() > 0


def test_labelled_good_documents_stay(spark, judged):
    labels = spark.read.parquet("/root/testdata/sf0.01/labels.parquet").toPandas()
    both = judged[~judged["base_failed"]].merge(labels, on="doc_id")
    assert both.loc[both["quality"] == 1, "kept"].mean() >= 0.98
    assert both.loc[both["quality"] == 0, "kept"].mean() <= 0.05


def test_edges(spark):
    rows = [(None, "a b c"), (1, None), (1, None), (2, ""), (3, "word " * 60000)]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("p_good", F.lit("x"))
    got = quality_rules.judge(df).collect()
    assert len(got) == 5 and all(r["base_failed"] and not r["kept"] and r["p_good"] is not None for r in got)
