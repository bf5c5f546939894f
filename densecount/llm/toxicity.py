"""Toxic spans by a linear-chain conditional random field.

A bounded sample of labelled documents gives token labels: features (a word, or the bytes it
starts or ends with) that stand in many toxic documents and hardly any others mark a token
of a toxic document as toxic. A two-label chain over the tokens is fitted to those by
stochastic gradient on its likelihood; features are hashed, so words never seen are judged by
their stems and neighbours. Every text is then tagged whole: forward-backward marginals give
each token's probability, runs of probable tokens are the offending spans, and a logistic
model of the marginals, fitted on the same sample, gives the document's score.

Only texts are inputs of a score. The sample holds at most ``sample`` documents of either
label; copies and near copies in it count once.

Edge cases: null and empty texts have no tokens and get the score of no evidence; without
labelled documents of both kinds every score is 0; a null doc_id is in no sample; repeated
rows get a row each; extra columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import store, textops

_U = np.uint64


@dataclass(frozen=True)
class ToxicSpec:
    sample: int = 1000  # labelled training documents of either label
    bits: int = 18  # of the feature table
    evidence: float = 14.0  # nats by which a marking feature must favour toxic documents
    most_clean: float = 0.02  # its share of clean documents to that of toxic ones
    side: int = 6  # tokens around a marked one that are trained on
    epochs: int = 6
    rate: float = 0.3
    decay: float = 1e-4
    span_from: float = 0.5
    folds: int = 5


KINDS = 8  # word, four beginnings, an ending, the word before and the word after
BEGINNINGS, ENDING = (3, 4, 5, 6), 3


def word_features(data, starts, ends) -> np.ndarray:
    """Hashes (kinds of a word's own features x words); 0 where a word is too short."""
    running = textops.prefix_hash(data)
    size = ends - starts
    out = np.zeros((6, len(starts)), np.uint64)
    out[0] = textops.span_hash(running, starts, ends)
    for k, n in enumerate(BEGINNINGS, 1):
        out[k] = np.where(size > n, textops.span_hash(running, starts, np.minimum(starts + n, ends)), 0)
    out[5] = np.where(size > ENDING, textops.span_hash(running, np.maximum(ends - ENDING, starts), ends), 0)
    return out


class Tokens:
    """Tokens of a block with the features of its distinct words."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray) -> None:
        data = textops.lower(data)
        starts, ends, self.ptr = textops.words(data, offsets, textops.ALNUM)
        words = textops.word_hashes(data, starts, ends)
        self.words = words
        _, first, self.each = np.unique(words, return_index=True, return_inverse=True)
        self.features = word_features(data, starts[first], ends[first])

    def columns(self, bits: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Table columns of the distinct words: own features, as word before, as word after."""
        kind = np.arange(1, 7, dtype=np.uint64)[:, None]
        own = textops.mix(self.features + kind * _U(0x9E3779B97F4A7C15)) >> _U(64 - bits)
        own[self.features == 0] = 0
        before = textops.mix(self.features[0] ^ _U(0xABCDEF12345)) >> _U(64 - bits)
        after = textops.mix(self.features[0] ^ _U(0x54321FEDCBA)) >> _U(64 - bits)
        return own.astype(np.int64), before.astype(np.int64), after.astype(np.int64)

    def evidence(self, table: np.ndarray, bits: int) -> np.ndarray:
        """Log-odds for the toxic label of every token, without the chain."""
        own, before, after = self.columns(bits)
        n = len(self.each)
        s = table[own].sum(0)[self.each]
        inner = np.ones(n, bool)
        inner[self.ptr[:-1][self.ptr[:-1] < n]] = False
        at = np.flatnonzero(inner)
        s[at] += table[before][self.each[at - 1]]
        s[at - 1] += table[after][self.each[at]]
        return s


def marginals(s: np.ndarray, ptr: np.ndarray, chain: np.ndarray) -> np.ndarray:
    """P(token toxic) by forward-backward, all documents in step."""
    size = np.diff(ptr)
    order = np.argsort(-size, kind="stable")
    start, size = ptr[:-1][order], size[order]
    out = np.zeros(len(s))
    if not len(s):
        return out
    e = np.exp(np.clip(s, -30, 30))
    a = np.exp(chain)
    steps = int(size[0])
    active = np.searchsorted(-size, -np.arange(steps), "left")  # documents longer than t
    q = None
    for t in range(steps):
        k = active[t]
        x = e[start[:k] + t]
        if t == 0:
            f1, f0 = x, np.ones(k)
        else:
            p = q[:k]
            f0 = (1 - p) * a[0, 0] + p * a[1, 0]
            f1 = ((1 - p) * a[0, 1] + p * a[1, 1]) * x
        q = f1 / (f0 + f1)
        out[start[:k] + t] = q
    b = np.zeros(0)  # P-like weight of label 1 from what follows; 0.5: nothing follows
    for t in range(steps - 1, -1, -1):
        k = active[t]
        b = np.concatenate([b, np.full(k - len(b), 0.5)])
        m = active[t + 1] if t + 1 < steps else 0
        if m:
            x = e[start[:m] + t + 1]
            g0 = a[0, 0] * (1 - b[:m]) + a[0, 1] * x * b[:m]
            g1 = a[1, 0] * (1 - b[:m]) + a[1, 1] * x * b[:m]
            b[:m] = g1 / (g0 + g1)
        at = start[:k] + t
        q = out[at]
        up = q * b
        out[at] = up / (up + (1 - q) * (1 - b))
    return out


def aggregate(p: np.ndarray, ptr: np.ndarray) -> np.ndarray:
    """Document features of the marginals: log-odds of the highest, and the expected number
    of toxic tokens."""
    n = len(ptr) - 1
    top, total = np.zeros(n), np.zeros(n)
    some = np.flatnonzero(np.diff(ptr) > 0)
    if len(some):
        top[some] = np.maximum.reduceat(p, ptr[:-1][some])
        total[some] = np.add.reduceat(p, ptr[:-1][some])
    top = np.clip(top, 1e-6, 1 - 1e-6)
    return np.stack([np.log(top / (1 - top)) / 4, np.log1p(total), np.ones(n)], 1)


@dataclass
class Model:
    table: np.ndarray
    chain: np.ndarray
    document: np.ndarray

    def score(self, features: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(features @ self.document, -30, 30)))


def _token_labels(tokens: Tokens, toxic: np.ndarray, spec: ToxicSpec) -> np.ndarray:
    """Tokens of toxic documents that have a marking feature."""
    doc = textops.doc_of(tokens.ptr)
    n_toxic, n_clean = int(toxic.sum()), int((~toxic).sum())
    marked = np.zeros(tokens.features.shape[1], bool)
    for f in tokens.features:
        each = f[tokens.each]
        kind, which = np.unique(each, return_inverse=True)
        pair = np.unique(which.astype(np.int64) * len(toxic) + doc)
        bad = toxic[pair % len(toxic)]
        a, b = np.bincount(pair // len(toxic), bad, len(kind)), np.bincount(pair // len(toxic), ~bad, len(kind))
        rate = n_toxic / len(toxic)
        ratio = a * np.log(np.maximum(a, 1) / (a + b) / rate) + b * np.log(np.maximum(b, 1) / (a + b) / (1 - rate))
        marks = (ratio >= spec.evidence) & (b / n_clean <= spec.most_clean * a / n_toxic) & (kind != 0)
        marked |= marks[np.searchsorted(kind, f)]
    return marked[tokens.each] & toxic[doc]


def fit(texts: list[str], toxic: np.ndarray, spec: ToxicSpec = ToxicSpec()) -> Model:
    table, chain = np.zeros(1 << spec.bits), np.zeros((2, 2))
    if not toxic.any() or toxic.all():
        return Model(table, chain, np.array([0.0, 0.0, -np.inf]))
    data, offsets = textops.column(pa.array(texts, pa.string()))
    tokens = Tokens(data, offsets)
    # near copies share their least five-word hash; one of them is enough
    grams = textops.gram_hashes(tokens.words, 5)
    sign = np.array([grams[a : b - 4].min() if b - a > 4 else i for i, (a, b) in enumerate(zip(tokens.ptr, tokens.ptr[1:]))], np.uint64)
    _, one = np.unique(sign, return_index=True)
    keep = np.zeros(len(toxic), bool)
    keep[one] = True
    if not keep.all():
        return fit([t for t, k in zip(texts, keep, strict=True) if k], toxic[keep], spec)
    y = _token_labels(tokens, toxic, spec)
    doc, n = textops.doc_of(tokens.ptr), len(y)
    rng = np.random.default_rng(7)
    centres = np.concatenate([np.flatnonzero(y), rng.choice(n, min(n, 3 * int(y.sum()) + 2000), replace=False)])
    width = 2 * spec.side + 1
    spot = centres[:, None] + np.arange(-spec.side, spec.side + 1)
    inside = (spot >= tokens.ptr[doc[centres]][:, None]) & (spot < tokens.ptr[doc[centres] + 1][:, None])
    spot = np.clip(spot, 0, n - 1)
    own, before, after = tokens.columns(spec.bits)
    each = tokens.each
    squares = np.full(len(table), 1e-6)
    chain_squares = np.full((2, 2), 1e-6)
    for _ in range(spec.epochs):
        for part in np.array_split(rng.permutation(len(centres)), max(1, len(centres) // 400)):
            at, ok = spot[part], inside[part]
            w = each[at]
            left = np.where(np.roll(ok, 1, 1) & (np.arange(width) > 0), before[each[np.maximum(at - 1, 0)]], -1)
            right = np.where(np.roll(ok, -1, 1) & (np.arange(width) < width - 1), after[each[np.minimum(at + 1, n - 1)]], -1)
            index = np.concatenate([own[:, w], left[None], right[None]])
            value = np.where(index >= 0, table[index], 0.0).sum(0)
            gradient, moves = _gradient(value, y[at], ok, chain)
            flat = np.broadcast_to(gradient, index.shape)[index >= 0]
            g = np.bincount(index[index >= 0], flat, len(table)) / len(part) + spec.decay * table
            squares += g * g
            table -= spec.rate * g / np.sqrt(squares) * (g != 0)
            moves /= len(part)
            chain_squares += moves * moves
            chain -= spec.rate * moves / np.sqrt(chain_squares) * (moves != 0)
    features = aggregate(marginals(tokens.evidence(table, spec.bits), tokens.ptr, chain), tokens.ptr)
    weight = np.zeros(3)
    for _ in range(400):  # Newton steps would do too; the three weights converge fast
        p = 1 / (1 + np.exp(-features @ weight))
        weight -= 2.0 * (features.T @ (p - toxic) / len(toxic) + 1e-4 * weight)
    return Model(table.astype(np.float32), chain, weight)


def _gradient(s: np.ndarray, y: np.ndarray, ok: np.ndarray, chain: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Gradient of the negative log-likelihood of segments: by token evidence and by chain
    weight. Places outside the document carry label 0 for sure."""
    m, width = s.shape
    e = np.stack([np.ones((m, width)), np.where(ok, np.exp(np.clip(s, -30, 30)), 0.0)], 2)
    a = np.exp(chain)
    forward = np.zeros((m, width, 2))
    backward = np.ones((m, width, 2))
    forward[:, 0] = e[:, 0] / e[:, 0].sum(1, keepdims=True)
    for t in range(1, width):
        f = (forward[:, t - 1] @ a) * e[:, t]
        forward[:, t] = f / f.sum(1, keepdims=True)
    for t in range(width - 2, -1, -1):
        b = (backward[:, t + 1] * e[:, t + 1]) @ a.T
        backward[:, t] = b / b.sum(1, keepdims=True)
    p = forward * backward
    p /= p.sum(2, keepdims=True)
    pair = forward[:, :-1, :, None] * a[None, None] * (e[:, 1:] * backward[:, 1:])[:, :, None, :]
    pair /= pair.sum((2, 3), keepdims=True)
    seen = np.zeros_like(pair)
    lab = y.astype(int) * ok
    i, j = np.indices((m, width - 1))
    seen[i, j, lab[:, :-1], lab[:, 1:]] = 1
    inner = (ok[:, 1:] & ok[:, :-1])[:, :, None, None]
    return np.where(ok, p[:, :, 1] - lab, 0.0), ((pair - seen) * inner).sum((0, 1))


_SPAN = store.schema("first_word long, last_word long")
SCHEMA = store.schema("doc_id long, held_out boolean, score double, predicted int, n_toxic double", spans=T.ArrayType(_SPAN))


def held_out(doc_id, folds: int):
    """True for the ids that training leaves out."""
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit(""))), F.lit(folds)) == 0


def train(docs: DataFrame, labels: DataFrame, spec: ToxicSpec = ToxicSpec()) -> Model:
    """Fit on at most ``sample`` distinct-text documents of either label, chosen by hash."""
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("toxic")).where("doc_id is not null and toxic is not null")
    known = known.where(~held_out(F.col("doc_id"), spec.folds)).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    order = F.xxhash64("doc_id")
    sample = known.where("toxic = 1").orderBy(order, "doc_id").limit(spec.sample).unionByName(known.where("toxic = 0").orderBy(order, "doc_id").limit(spec.sample))
    texts = docs.join(F.broadcast(sample), "doc_id").select("doc_id", "text", "toxic")  # at most 2 * sample rows of two numbers
    rows = texts.toArrow().sort_by("doc_id")
    if not rows.num_rows:
        return fit([], np.zeros(0, bool), spec)
    return fit(rows["text"].to_pylist(), rows["toxic"].to_numpy() == 1, spec)


def score(docs: DataFrame, labels: DataFrame, spec: ToxicSpec = ToxicSpec()) -> DataFrame:
    docs = store.documents(docs, "doc_id", "text")
    model = train(docs, labels, spec)

    def run(batches):
        for batch, data, offsets in textops.blocks(batches):
            tokens = Tokens(data, offsets)
            p = marginals(tokens.evidence(model.table, spec.bits), tokens.ptr, model.chain)
            s = model.score(aggregate(p, tokens.ptr))
            first, last = textops.runs(p >= spec.span_from)
            doc = np.searchsorted(tokens.ptr, first, "right") - 1
            spans: list[list] = [[] for _ in s]
            for d, a, z in zip(doc.tolist(), first.tolist(), last.tolist(), strict=True):
                while a < z:  # a run may pass a document's end
                    stop = min(z, int(tokens.ptr[d + 1]))
                    if stop > a:
                        spans[d].append({"first_word": a - int(tokens.ptr[d]), "last_word": stop - 1 - int(tokens.ptr[d])})
                    a, d = stop, d + 1
            total = np.bincount(textops.doc_of(tokens.ptr), p, minlength=len(s))
            yield store.rows(
                _SCORED, doc_id=batch.column(0), score=pa.array(s), predicted=pa.array((s >= 0.5).astype(np.int32)), n_toxic=pa.array(total), spans=spans
            )

    out = docs.mapInArrow(run, _SCORED)
    return out.withColumn("held_out", held_out(F.col("doc_id"), spec.folds)).select(*SCHEMA.names)


_SCORED = T.StructType([f for f in SCHEMA if f.name != "held_out"])
