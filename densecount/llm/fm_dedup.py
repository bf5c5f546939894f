"""Substring dedup of word windows with an FM-index per shard.

Contexts of repeated minimisers are dealt out to shards by the minimiser's hash, so equal
windows meet in one shard. There the distinct contexts form a text over words, with the
minimiser itself as one symbol, and a compressed FM-index is built over it. The documents'
contexts are streamed through the index backwards, a batch at a time; matching statistics
give the longest pattern from each word on that stands elsewhere too, and intervals as long
as a window are reported. Of an interval's places, all but the first in (doc_id, place)
order are covered. (Only what surrounds a repeated minimiser is streamed, and only through
the one shard that can hold it, as the rest can't be in a repeat.)

Edge cases: null and empty texts have no words; texts shorter than a window keep all words;
a very long text is one block of its own; ties (equal windows) go by doc_id, then place; a null doc_id can't be ordered, so such rows stay whole; rows that repeat a doc_id count as
one document, each keeping its own row; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import anchors, store, textops


@dataclass(frozen=True)
class FmSpec:
    window: int = 20
    gram: int = 8
    per_bucket: int = 100_000  # minimisers of all documents to a shard
    stream: int = 1 << 15  # contexts that go through an index together

    @property
    def shape(self) -> anchors.Shape:
        return anchors.Shape(self.window, self.gram, across=False, words=True)


def repeated_windows(matrix: np.ndarray, real: np.ndarray, doc: np.ndarray, place: np.ndarray, spec: FmSpec) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(doc_id, start, end) of what windows of a shard's contexts that start earlier as well
    cover."""
    from .fm_index import FMIndex

    side, gram = spec.window - spec.gram, spec.gram
    order = np.lexsort((place, doc))
    # the same place may come twice, from rows that repeat a document
    new = np.ones(len(order), bool)
    d, p = doc[order], place[order]
    new[1:] = (d[1:] != d[:-1]) | (p[1:] != p[:-1])
    order = order[new]
    matrix, real, doc, place = matrix[order], real[order], doc[order], place[order]
    _, first, each = np.unique(anchors.row_hashes(matrix, real), return_index=True, return_inverse=True)
    m = len(first)
    rows, spans = matrix[first], real[first]
    middle = textops.gram_hashes(rows[:, side : side + gram].ravel(), gram)[::gram][:m]
    # words beyond the document are no symbols
    outer = np.concatenate([rows[:, :side], rows[:, side + gram :]], 1)
    column = np.concatenate([np.arange(side), np.arange(side + gram, 2 * side + gram)])
    inside = (column >= spans[:, :1]) & (column < spans[:, 1:])
    _, word = np.unique(outer, return_inverse=True)
    word = np.where(inside, word.reshape(outer.shape) + 1, 0)
    _, mid = np.unique(middle, return_inverse=True)
    queries = np.concatenate([word[:, :side], mid[:, None] + int(word.max(initial=0)) + 1, word[:, side:]], 1)
    depth = side + 1
    text = np.concatenate([queries, np.zeros((m, 1), np.int64)], 1).ravel()
    index = FMIndex(text, int(text.max(initial=0)) + 1, depth)
    block = np.concatenate([[0], np.cumsum(index.lcp[1 : index.n] < depth)])
    owner = first[index.order // (2 * side + 2)]  # contexts are in (doc_id, place) order
    least = np.minimum.reduceat(owner, np.flatnonzero(np.concatenate([[True], index.lcp[1 : index.n] < depth])))
    del index.order
    reach = anchors.Reach(len(doc))
    members = np.argsort(each, kind="stable")
    for a in range(0, m, spec.stream):
        here = slice(a, a + spec.stream)
        lowest, inner = first[here], spans[here]
        these = members[np.searchsorted(each[members], a) : np.searchsorted(each[members], a + spec.stream)]
        local = each[these] - a
        for c, size, lo, _ in index.matching(queries[here], 2):
            if c > side:
                continue
            # for copies of a whole context, its window counts even if it stands nowhere else
            earliest = np.where(size == depth, least[block[np.minimum(lo, index.n - 1)]], lowest)
            fits = (inner[:, 0] <= c) & (inner[:, 1] >= c + spec.window)
            reach.add(these[fits[local] & (earliest[local] < these)], c)
    return reach.spans(doc, place, spec.window)


_OUT = store.schema("doc_id long, n_words long, n_removed long, kept_sha256 string")
_TEXT = store.schema("doc_id long, text string, n_removed long")


def covered(docs: DataFrame, spec: FmSpec = FmSpec()) -> DataFrame:
    """(doc_id, spans): chunks of the word ranges that go."""
    shape = spec.shape
    docs = docs.where("doc_id is not null")
    total = anchors.text_bytes(docs)
    grams = anchors.bucket_count(total, 1 / 6, 2 / (shape.side + 2), 600_000)
    shards = anchors.bucket_count(total, 1 / 6, 2 / (shape.side + 2), spec.per_bucket)
    found = anchors.anchors(docs, shape, grams, max(8, total >> 25))
    joined = docs.join(found, "doc_id").select("doc_id", "text", "places")

    def encode(s: anchors.Symbols, spot: np.ndarray, valid: np.ndarray) -> np.ndarray:
        return np.where(valid, s.hash[spot] & np.uint64((1 << 40) - 1), np.uint64(0))

    def search(matrix, real, doc, place, _):
        return repeated_windows(matrix, real, doc, place, spec)

    spans = anchors.contexts(joined, shape, shards, encode).groupBy("bucket").applyInArrow(anchors.resolve(shape, np.uint64, search, max(8, total >> 25)), anchors.SPANS)
    return anchors.by_document(spans)


def dedup(docs: DataFrame, spec: FmSpec = FmSpec(), digest: bool = True) -> DataFrame:
    """Per document what is removed, and the kept words joined by single spaces or their
    digest."""
    docs = store.documents(docs, "doc_id", "text")
    spans = covered(docs, spec)

    def finish(batches):
        for batch, data, offsets in textops.blocks(batches):
            raw = data.tobytes()
            starts, ends, ptr = textops.words(data, offsets, textops.SPACED)
            chunks = batch.column(batch.schema.get_field_index("spans")).to_pylist()
            removed, out = [], []
            for a, b, chunk in zip(ptr[:-1].tolist(), ptr[1:].tolist(), chunks, strict=True):
                keep = np.ones(b - a, bool)
                for x, y in anchors.merged(chunk).tolist() if chunk else ():
                    keep[x:y] = False
                left = b" ".join([raw[x:y] for x, y in zip(starts[a:b][keep].tolist(), ends[a:b][keep].tolist(), strict=True)])
                removed.append(b - a - int(keep.sum()))
                out.append(hashlib.sha256(left).hexdigest() if digest else left.decode("utf-8", "replace"))
            if digest:
                yield store.rows(_OUT, doc_id=batch.column(0), n_words=pa.array(np.diff(ptr)), n_removed=removed, kept_sha256=out)
            else:
                yield store.rows(_TEXT, doc_id=batch.column(0), text=out, n_removed=removed)

    return anchors.with_spans(docs, spans, finish, _OUT if digest else _TEXT)
