"""Substring dedup by merging shard Burrows-Wheeler transforms.

Each block of documents is a shard. Of its suffixes only those at anchors matter, as every
repeated window holds an anchor. The shard sorts them once and sends its sparse transform:
the suffixes' first bytes in sorted order, each with the bytes in front of it (a transform
has the one byte in front), and the order of the same rows by what is in front, read
backwards.

A bucket merges its shards without sorting suffixes again: the interleave of the shards'
orders, at first one shard after the other, is refined round by round. In each round the
rows of a block, which agree so far, are dealt out by their next symbols (eight bytes),
rows of one shard staying in the order they came in; blocks of one row are settled and drop
out, so rounds end when the interleave is stable. A round in which neighbours part gives
their common prefix. Common prefixes give, for every length, the intervals of equal right
contexts, and the merge of the backward orders those of equal left ones. A window around an
anchor is a left part and a right part; windows whose two intervals agree are equal, and all
of them but those of the least document are covered.

Contexts meet only contexts with the same anchor hash, and identical ones of a block are
merged before they are sent, so a passage that a third of all documents share costs a row
per shard; that many rows of one anchor meet in one bucket, packed.

Edge cases: null and empty texts have no bytes; texts shorter than the window keep all
bytes; a very long text is one block of its own; a null doc_id can't be ordered, so such rows
stay whole; rows that repeat a doc_id count as one document, each keeping its own row; an
empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import anchors, store, textops


@dataclass(frozen=True)
class BwtSpec:
    window: int = 50
    gram: int = 16
    per_bucket: int = 400_000  # minimisers

    @property
    def shape(self) -> anchors.Shape:
        return anchors.Shape(self.window, self.gram, across=True, words=False, block_bytes=(1 << 20) - 1024)


def words_of(columns: np.ndarray) -> np.ndarray:
    """Rows of bytes as rows of numbers that compare like them, eight bytes each."""
    n, width = columns.shape
    padded = np.zeros((n, -(-width // 8) * 8), np.uint8)
    padded[:, :width] = columns
    return padded.view(">u8").astype(np.uint64)


def sides(matrix: np.ndarray, side: int) -> tuple[np.ndarray, np.ndarray]:
    """(from the anchor on, from the anchor back) as words."""
    return words_of(matrix[:, side:]), words_of(matrix[:, :side][:, ::-1])


def sorted_shard(matrix: np.ndarray, side: int) -> tuple[np.ndarray, np.ndarray]:
    """A shard's order of its rows by what follows, and by what precedes, the anchor."""
    return tuple(np.lexsort(x.T[::-1]) for x in sides(matrix, side))


def _equal_bytes(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Leading bytes that two different words share."""
    differ = x ^ y
    return sum((differ < np.uint64(1 << bits)).astype(np.int64) for bits in range(8, 64, 8))


def interleave(words: np.ndarray, order: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(merged order, common prefix of each place with the one before, in bytes).

    ``order`` has the shards' sorted orders one after the other."""
    n, rounds = words.shape
    order, lcp = order.copy(), np.full(n, 8 * rounds, np.int64)
    lcp[:1] = 0
    place, block = np.arange(n), np.zeros(n, np.int64)  # of rows not settled yet
    for j in range(rounds):
        if not len(place):
            break
        symbol = words[order[place], j]
        by = np.lexsort((symbol, block))
        order[place], symbol = order[place[by]], symbol[by]
        inside = np.zeros(len(place), bool)
        inside[1:] = block[1:] == block[:-1]
        parted = inside.copy()
        parted[1:] &= symbol[1:] != symbol[:-1]
        at = np.flatnonzero(parted)
        lcp[place[at]] = 8 * j + _equal_bytes(symbol[at], symbol[at - 1])
        block = np.cumsum(parted | ~inside)
        again = np.bincount(block)[block] > 1
        place, block = place[again], block[again]
    return order, lcp


def repeated_windows(matrix: np.ndarray, real: np.ndarray, doc: np.ndarray, place: np.ndarray, left: np.ndarray, spec: BwtSpec) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(doc_id, start, end) of what windows that a smaller document holds as well cover.

    matrix: contexts x bytes, shard after shard, each sorted from the anchor on; real: [first,
    last) column inside the document; left: the shards' orders from the anchor back."""
    side, n = spec.window - spec.gram, len(matrix)
    after, before = sides(matrix, side)
    r_order, r_lcp = interleave(after, np.arange(n))
    l_order, l_lcp = interleave(before, left)
    r_rank, l_rank = np.empty(n, np.int64), np.empty(n, np.int64)
    r_rank[r_order], l_rank[l_order] = np.arange(n), np.arange(n)

    # contexts that agree on both sides once, with their least document
    whole = np.cumsum(r_lcp < spec.window)[r_rank] << 39 | np.cumsum(l_lcp < side)[l_rank] << 14 | real[:, 0] << 7 | real[:, 1]
    by = np.argsort(doc, kind="stable")
    _, first, each = np.unique(whole[by], return_index=True, return_inverse=True)
    first, back = by[first], np.empty(n, np.int64)
    back[by] = each
    each, least, spans, m = back, doc[first], real[first], len(first)
    r_rank, l_rank = r_rank[first], l_rank[first]
    reach = anchors.Reach(n)
    for k in range(side + 1):  # bytes of the window left of the anchor
        fits = (spans[:, 0] <= side - k) & (spans[:, 1] >= side - k + spec.window)
        some = np.flatnonzero(fits)
        if not len(some):
            continue
        r_class, l_class = np.cumsum(r_lcp < spec.window - k), np.cumsum(l_lcp < k)
        pair = (r_class[r_rank[some]] << 32) + l_class[l_rank[some]]
        by = np.argsort(pair, kind="stable")
        p = pair[by]
        begin = np.flatnonzero(np.concatenate([[True], p[1:] != p[:-1]]))
        low = np.full(m, np.iinfo(np.int64).max)
        low[some[by]] = np.repeat(np.minimum.reduceat(least[some[by]], begin), np.diff(np.append(begin, len(p))))
        hit = np.flatnonzero(low[each] < doc)
        reach.add(hit, side - k)
    return reach.spans(doc, place, spec.window)


_OUT = store.schema("doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")
_TEXT = store.schema("doc_id long, text string, n_removed long")


def covered(docs: DataFrame, spec: BwtSpec = BwtSpec()) -> DataFrame:
    """(doc_id, spans): chunks of the byte ranges that go."""
    shape = spec.shape
    docs = docs.where("doc_id is not null")
    total = anchors.text_bytes(docs)
    buckets = anchors.bucket_count(total, 1.0, 2 / (shape.side + 2), spec.per_bucket)
    found = anchors.anchors(docs, shape, buckets, max(8, total >> 25))
    joined = docs.join(found, "doc_id").select("doc_id", "text", "places")

    def encode(s: anchors.Symbols, spot: np.ndarray, valid: np.ndarray) -> np.ndarray:
        return np.where(valid, s.data[spot], np.uint8(0))

    def merge(matrix, real, doc, place, left):
        return repeated_windows(matrix, real, doc, place, left, spec)

    def shard(matrix):
        return sorted_shard(matrix, shape.side)

    spans = anchors.contexts(joined, shape, buckets, encode, shard).groupBy("bucket").applyInArrow(anchors.resolve(shape, np.uint8, merge, max(8, total >> 25)), anchors.SPANS)
    return anchors.by_document(spans)


def dedup(docs: DataFrame, spec: BwtSpec = BwtSpec(), digest: bool = True) -> DataFrame:
    """Per document what is removed and the digest of what is left, or the text itself
    (bytes that no longer form UTF-8 are replaced)."""
    docs = store.documents(docs, "doc_id", "text")
    spans = covered(docs, spec)

    def finish(batches):
        for batch, data, offsets in textops.blocks(batches):
            raw = data.tobytes()
            chunks = batch.column(batch.schema.get_field_index("spans")).to_pylist()
            removed, count, out = [], [], []
            for a, b, chunk in zip(offsets[:-1].tolist(), offsets[1:].tolist(), chunks, strict=True):
                gone = anchors.merged(chunk).tolist() if chunk else []
                kept, at = [], a
                for x, y in gone:
                    kept.append(raw[at : a + x])
                    at = a + y
                kept.append(raw[at:b])
                left = b"".join(kept)
                removed.append(b - a - len(left))
                count.append(len(gone))
                out.append(hashlib.sha256(left).hexdigest() if digest else left.decode("utf-8", "replace"))
            if digest:
                yield store.rows(_OUT, doc_id=batch.column(0), n_bytes=pa.array(np.diff(offsets)), n_removed=removed, n_spans=count, kept_sha256=out)
            else:
                yield store.rows(_TEXT, doc_id=batch.column(0), text=out, n_removed=removed)

    return anchors.with_spans(docs, spans, finish, _OUT if digest else _TEXT)
