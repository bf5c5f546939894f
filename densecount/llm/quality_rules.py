"""Quality by weak supervision, in DataFrame expressions only.

Each rule votes good, bad or abstains. The share of documents for every combination of
votes is counted (at most 3**rules rows), expectation-maximisation estimates how likely a
good and a bad document make each vote, and a document's posterior probability of being
good decides, instead of requiring every rule to hold.

The EM loop is one SQL fold over the counted combinations, held in one row whose size is
bounded by the number of rules. Documents meet the estimates as literals.

Edge cases: a null text counts as empty, has no words and fails the base rule; a null doc_id
is judged like any other; repeated rows are judged alike, each counting as one document in
the fit; ties (a posterior of exactly ``keep_from``) are kept; an empty table gives an empty
result; a very long text is one row of arrays of its words, so an executor must hold it a
few times over; extra columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from math import log

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import store

SPACES = " \t\n\x0b\x0c\r"
SYMBOLS = "#*$%&|<>"


def _without(c: Column, characters: str) -> Column:
    for x in characters:
        c = F.replace(c, F.lit(x), F.lit(""))
    return c


def _repeated_words(words: Column) -> Column:
    """Words inside three-word windows that occur twice or more in the array.

    Windows are hashed and sorted with their places; equal neighbours mark repeats, and
    the repeats' places, in order, cover three words each, less what overlaps."""
    places = F.sequence(F.lit(0), F.size(words) - 3)
    hashes = F.transform(places, lambda i: F.xxhash64(F.get(words, i), F.get(words, i + 1), F.get(words, i + 2)))
    pairs = F.array_sort(F.arrays_zip(hashes.alias("h"), places.alias("p")))

    def repeated(pairs_: Column) -> Column:
        last = F.size(pairs_) - 1
        return F.filter(
            pairs_,
            lambda x, i: ((i > 0) & (F.get(pairs_, F.greatest(i - 1, F.lit(0)))["h"] == x["h"])) | ((i < last) & (F.get(pairs_, F.least(i + 1, last))["h"] == x["h"])),
        )

    def covered(at: Column) -> Column:
        return F.aggregate(
            at,
            F.struct(F.lit(0).alias("n"), F.lit(-3).alias("last")),
            lambda s, p: F.struct((s["n"] + F.least(F.lit(3), p - s["last"])).alias("n"), p.alias("last")),
            lambda s: s["n"],
        )

    found = F.transform(F.array(pairs), lambda p: covered(F.array_sort(F.transform(repeated(p), lambda x: x["p"]))))
    distinct = F.size(F.array_distinct(hashes))
    return F.when(F.size(words) < 4, F.lit(0)).when(distinct == F.size(words) - 2, F.lit(0)).otherwise(F.get(found, F.lit(0))).cast("long")


def features(docs: DataFrame) -> DataFrame:
    """doc_id and the counts the rules read; one narrow pass, no shuffle."""
    text = F.coalesce(F.col("text"), F.lit(""))
    base = store.documents(docs, "doc_id", "text").select("doc_id", text.alias("text"))
    split = base.select(
        "doc_id",
        "text",
        F.filter(F.split("text", r"[ \t-\r]+"), lambda w: w != "").alias("w"),
        F.filter(F.split("text", "\n"), lambda x: F.length(_without(x, SPACES)) > 0).alias("l"),
        (F.octet_length("text") - F.octet_length(_without(F.col("text"), SPACES))).alias("spaces"),
    )
    return split.select(
        "doc_id",
        F.size("w").cast("long").alias("n_words"),
        (F.char_length("text") - F.col("spaces")).cast("long").alias("word_chars"),
        (F.octet_length("text") - F.octet_length(_without(F.col("text"), SYMBOLS))).cast("long").alias("n_symbols"),
        (F.size("l") - F.size(F.array_distinct("l"))).cast("long").alias("n_dup_lines"),
        _repeated_words(F.col("w")).alias("n_repeat_words"),
        F.size("l").cast("long").alias("n_lines"),
        F.size(F.array_distinct("w")).cast("long").alias("n_distinct"),
        F.char_length(F.regexp_replace("text", "[^!?]+", "")).cast("long").alias("n_shouts"),
    )


def _vote(good: Column, bad: Column) -> Column:
    return F.when(bad, -1).when(good, 1).otherwise(0)


@dataclass(frozen=True)
class QualitySpec:
    min_words: int = 50
    max_repeat_percent: int = 50
    iterations: int = 25
    prior_good: float = 0.9
    keep_from: float = 0.5
    #: shares up to which a rule votes good and above which it votes bad
    limits: dict = field(default_factory=lambda: {"symbols": (0.01, 0.1), "dup_lines": (0.0, 0.15), "repeats": (0.0, 0.1), "shouts": (-1.0, 0.25)})
    min_lines: int = 4
    #: weight of the prior beliefs below, as a share of all documents
    strength: float = 0.02
    #: P(bad vote), P(abstain), P(good vote) believed of good and of bad documents
    good_votes: tuple = (0.05, 0.25, 0.7)
    bad_votes: tuple = (0.35, 0.35, 0.3)


def votes(spec: QualitySpec) -> dict[str, Column]:
    """The labelling rules: 1 good, -1 bad, 0 abstain. Never null.

    They are weak on purpose and may contradict each other: none decides alone, and how
    much each one's votes tell is left to the fit."""
    words, lines = F.col("n_words"), F.col("n_lines")
    n = F.greatest(words, F.lit(1))

    def share(name: str, x: Column) -> Column:
        low, high = spec.limits[name]
        return F.when(words == 0, 0).otherwise(_vote(x <= low, x > high))

    length = F.col("word_chars") / n
    distinct = F.col("n_distinct") / n
    long = words > 2000
    return {
        "length": F.when(words >= 2 * spec.min_words, 1).otherwise(0),
        "word_size": _vote((length >= 4.4) & (length <= 6), (length < 3.5) | (length > 7)),
        "symbols": share("symbols", F.col("n_symbols") / n),
        "dup_lines": F.when(lines < spec.min_lines, 0).otherwise(share("dup_lines", F.col("n_dup_lines") / F.greatest(lines, F.lit(1)))),
        "repeats": share("repeats", F.col("n_repeat_words") / n),
        "shouts": share("shouts", F.col("n_shouts") / n),
        "variety": F.when(words < spec.min_words, 0).otherwise(_vote(distinct > F.when(long, 0.15).otherwise(0.6), distinct < F.when(long, 0.05).otherwise(0.4))),
    }


def _em(patterns: DataFrame, rules: int, spec: QualitySpec) -> DataFrame:
    """One row: prior and, per rule, P(vote | good) and P(vote | bad) for votes -1, 0, 1.

    Each step spreads every counted vote combination over the classes by its posterior and
    counts again, on top of the prior beliefs, which weigh ``strength`` of all documents."""
    each = F.sequence(F.lit(0), F.lit(rules - 1))
    kinds = F.array(F.lit(-1), F.lit(0), F.lit(1))
    rows = patterns.agg(F.array_sort(F.collect_list(F.struct("v", "n"))).alias("rows"))

    def log_odds(v: Column, s: Column, j: Column) -> Column:
        k = F.get(v, j) + 1
        return F.log(F.get(F.get(s["good"], j), k) / F.get(F.get(s["bad"], j), k))

    def posterior(v: Column, s: Column) -> Column:
        odds = F.aggregate(each, F.log(s["prior"] / (1 - s["prior"])), lambda t, j: t + log_odds(v, s, j))
        return 1 / (1 + F.exp(-odds))

    total = F.greatest(F.lit(1.0), F.aggregate("rows", F.lit(0.0), lambda t, r: t + r["n"]))

    def tally(weighted: Column, side: str) -> Column:
        belief = spec.good_votes if side == "g" else spec.bad_votes
        base = spec.strength * (spec.prior_good if side == "g" else 1 - spec.prior_good)

        def one(j: Column, k: Column) -> Column:
            start = total * base * F.get(F.array(*map(F.lit, belief)), k + 1)
            return F.aggregate(weighted, start, lambda t, r: t + F.when(F.get(r["v"], j) == k, r[side]).otherwise(0.0))

        def row(j: Column) -> Column:
            counts = F.transform(kinds, lambda k: one(j, k))
            return F.transform(F.array(counts), lambda c: F.transform(c, lambda x: x / (F.get(c, F.lit(0)) + F.get(c, F.lit(1)) + F.get(c, F.lit(2)))))

        return F.transform(each, lambda j: F.get(row(j), F.lit(0)))

    def step(s: Column, _: Column) -> Column:
        weighted = F.transform("rows", lambda r: F.struct(r["v"].alias("v"), (r["n"] * posterior(r["v"], s)).alias("g"), (r["n"] * (1 - posterior(r["v"], s))).alias("b")))
        inner = F.transform(
            F.array(weighted),
            lambda w: F.struct(
                (F.aggregate(w, total * spec.strength * spec.prior_good, lambda t, r: t + r["g"]) / (total * (1 + spec.strength))).alias("prior"),
                tally(w, "g").alias("good"),
                tally(w, "b").alias("bad"),
            ),
        )
        return F.get(inner, F.lit(0))

    def table(votes_: tuple) -> Column:
        return F.array_repeat(F.array(*map(F.lit, votes_)), rules)

    start = F.struct(F.lit(spec.prior_good).alias("prior"), table(spec.good_votes).alias("good"), table(spec.bad_votes).alias("bad"))
    return rows.select(F.aggregate(F.sequence(F.lit(1), F.lit(spec.iterations)), start, step).alias("fit"))


def judge(docs: DataFrame, spec: QualitySpec = QualitySpec()) -> DataFrame:
    """Features, base verdict, posterior probability of good and the final ``kept``."""
    counted = store.settle(features(docs), "quality")
    rules = votes(spec)
    vote = F.array(*rules.values())
    failed = (F.col("n_words") < spec.min_words) | (100 * F.col("n_repeat_words") > spec.max_repeat_percent * F.col("n_words"))
    # documents that the base rule rejects would make up a class of their own
    patterns = counted.where(~failed).groupBy(vote.alias("v")).agg(F.count(F.lit(1)).alias("n"))
    fit = _em(patterns, len(rules), spec).first()["fit"]  # one row of 1 + 6 * rules numbers
    odds = F.lit(log(fit["prior"] / (1 - fit["prior"])))
    for j, rule in enumerate(rules.values()):
        weights = [log(g / b) for g, b in zip(fit["good"][j], fit["bad"][j], strict=True)]
        odds = odds + F.when(rule < 0, weights[0]).when(rule > 0, weights[2]).otherwise(weights[1])
    return counted.withColumns({"base_failed": failed, "p_good": 1 / (1 + F.exp(-odds))}).withColumn("kept", ~F.col("base_failed") & (F.col("p_good") >= spec.keep_from))
