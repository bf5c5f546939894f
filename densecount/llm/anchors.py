"""Shared front of the two substring dedup operators: where can a repeat be at all?

A repeat of a whole window (so many words or bytes) always shares a *minimiser* of that
window, a short gram chosen by its hash. Minimisers of all documents are counted, a row of
packed arrays per (block, bucket); those that occur again (for bytes: in another document)
are anchors, and only their surroundings (*contexts*) go on. Both steps are exact: what they
leave out can't be in a repeat.

A context has a fixed number of symbols on each side of its anchor, so that every window
around the anchor lies in it; places beyond the document's ends hold symbols that equal
nothing.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import store, textops

_U = np.uint64
_LOW40 = _U((1 << 40) - 1)


@dataclass(frozen=True)
class Shape:
    window: int  # symbols in a repeat
    gram: int  # symbols in a minimiser
    across: bool  # only repeats in another document count
    words: bool  # symbols are words, not bytes
    block_bytes: int = textops.BLOCK_BYTES  # of text looked at together

    @property
    def side(self) -> int:
        return self.window - self.gram


class Symbols:
    """Symbol hashes of a block, the documents' pointers and the minimisers."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, shape: Shape) -> None:
        self.data, self.offsets = data, offsets
        if shape.words:
            self.starts, self.ends, self.ptr = textops.words(data, offsets, textops.SPACED)
            self.hash = textops.word_hashes(data, self.starts, self.ends)
            self.grams = textops.gram_hashes(self.hash, shape.gram)
        else:
            self.ptr = offsets
            self.grams = textops.byte_grams(data, shape.gram)
        ok = textops.in_document(self.ptr, len(self.grams), shape.gram)
        self.places = textops.minimisers(self.grams, ok, shape.side + 1)
        self.doc = np.searchsorted(self.ptr, self.places, "right") - 1


def split(bucket: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(order, buckets, begins, ends) that deal rows out by bucket, keeping their order."""
    order = np.argsort(bucket.astype(np.uint16) if len(bucket) and bucket.max() < 65536 else bucket, kind="stable")
    here, begin = np.unique(bucket[order], return_index=True)
    return order, here.astype(np.int32), begin, np.append(begin[1:], len(bucket))


_GRAMS = store.schema("bucket int, keys binary, docs binary, places binary")
_PART = store.schema("part int, docs binary, places binary")
_FOUND = store.schema("doc_id long, places binary")


def anchors(docs: DataFrame, shape: Shape, buckets: int, parts: int) -> DataFrame:
    """(doc_id, places): for documents with anchors, their places as int32 bytes. Found
    places go back to documents a row per (bucket, part of the documents)."""

    def grams(batches):
        for batch, data, offsets in textops.blocks(batches, shape.block_bytes):
            s = Symbols(data, offsets, shape)
            h, ids = s.grams[s.places], np.asarray(batch.column(0))[s.doc]
            place = (s.places - s.ptr[s.doc]).astype(np.int32)
            order, here, begin, end = split(((h >> _U(40)) % _U(buckets)).astype(np.int32))
            h, ids, place = h[order] & _LOW40, ids[order], place[order]
            yield store.rows(
                _GRAMS, bucket=pa.array(here), keys=[store.pack(h[a:b]) for a, b in zip(begin, end)], docs=[store.pack(ids[a:b]) for a, b in zip(begin, end)],
                places=[store.pack(place[a:b]) for a, b in zip(begin, end)],
            )

    def again(table: pa.Table) -> pa.Table:
        key = np.concatenate([store.unpack(x, np.uint64) for x in table["keys"].to_pylist()])
        doc = np.concatenate([store.unpack(x, np.int64) for x in table["docs"].to_pylist()])
        place = np.concatenate([store.unpack(x, np.int32) for x in table["places"].to_pylist()])
        order = np.argsort(key, kind="stable")
        key = key[order]
        begin = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, np.int64)
        if shape.across:
            d = doc[order]
            many = np.minimum.reduceat(d, begin) != np.maximum.reduceat(d, begin) if len(begin) else np.zeros(0, bool)
        else:
            many = np.diff(np.append(begin, len(key))) > 1
        found = order[np.repeat(many, np.diff(np.append(begin, len(key))))]
        doc, place = doc[found], place[found]
        order, here, begin, end = split((textops.mix(doc.view(np.uint64)) % _U(parts)).astype(np.int32))
        doc, place = doc[order], place[order]
        return pa.table({"part": pa.array(here), "docs": pa.array([store.pack(doc[a:b]) for a, b in zip(begin, end)], pa.binary()), "places": pa.array([store.pack(place[a:b]) for a, b in zip(begin, end)], pa.binary())})

    def by_document(table: pa.Table) -> pa.Table:
        doc = np.concatenate([store.unpack(x, np.int64) for x in table["docs"].to_pylist()])
        place = np.concatenate([store.unpack(x, np.int32) for x in table["places"].to_pylist()])
        order = np.lexsort((place, doc))
        doc, place = doc[order], place[order]
        new = np.ones(len(doc), bool)  # rows that repeat a document give its places again
        new[1:] = (doc[1:] != doc[:-1]) | (place[1:] != place[:-1])
        doc, place = doc[new], place[new]
        ids, begin = np.unique(doc, return_index=True)
        return pa.table({"doc_id": pa.array(ids), "places": pa.array([place[a:b].tobytes() for a, b in zip(begin, np.append(begin[1:], len(doc)))], pa.binary())})

    found = docs.mapInArrow(grams, _GRAMS).groupBy("bucket").applyInArrow(again, _PART)
    return found.groupBy("part").applyInArrow(by_document, _FOUND)


_CONTEXTS = store.schema("bucket int, symbols binary, real binary, docs binary, places binary, left binary, gone_docs binary, gone_spans binary")


def contexts(joined: DataFrame, shape: Shape, buckets: int, encode: Callable, shard: Callable | None = None) -> DataFrame:
    """Contexts of all anchors, dealt out by the anchor's hash, as packed arrays.

    ``joined`` has doc_id, text and the anchors' places; ``encode(Symbols, places, valid)``
    gives the matrix of symbols that travels. Equal contexts of a block are merged before
    they are sent: the first one's (doc_id, place) stays, as often as rows repeat it, and what
    the others hold is covered. ``shard(matrix)`` gives two orders of a block's contexts; they
    are sent in the first, with the second as places in it."""
    width = 2 * shape.side + shape.gram

    def run(batches):
        for batch, data, offsets in textops.blocks(batches, shape.block_bytes):
            s = Symbols(data, offsets, shape)
            chunks = batch.column(batch.schema.get_field_index("places")).to_pylist()
            at = [np.frombuffer(x, np.int32) for x in chunks]
            doc = np.repeat(np.arange(len(at)), np.array([len(x) for x in at], np.int64))
            place = s.ptr[doc] + np.concatenate([*at, np.zeros(0, np.int32)])
            ids = np.asarray(batch.column(0))
            order = np.lexsort((place - s.ptr[doc], ids[doc]))
            doc, place = doc[order], place[order]
            bucket = ((s.grams[place] >> _U(40)) % _U(buckets)).astype(np.int32)
            order, here, begin, end = split(bucket)
            doc, place = doc[order], place[order]
            for k, a, b in zip(here, begin, end):
                d, start = doc[a:b], place[a:b] - shape.side
                spot = start[:, None] + np.arange(width)
                valid = (spot >= s.ptr[d, None]) & (spot < s.ptr[d + 1, None])
                matrix = encode(s, np.clip(spot, 0, max(int(s.ptr[-1]) - 1, 0)), valid)
                real = np.stack([valid.argmax(1), width - valid[:, ::-1].argmax(1)], 1).astype(np.uint8)
                _, first, each = np.unique(row_hashes(matrix, real), return_index=True, return_inverse=True)
                least = ids[d[first]][each]
                start = (start - s.ptr[d]).astype(np.int32)
                stays = ids[d] == least
                if not shape.across:
                    stays &= start == start[first][each]
                long = ~stays & (real[:, 1].astype(int) - real[:, 0] >= shape.window)
                gone = start[long, None] + real[long].astype(np.int32)
                some, left = np.flatnonzero(stays), np.zeros(0, np.int32)
                if shard:
                    first, second = shard(matrix[some])
                    at = np.empty(len(some), np.int32)
                    at[first] = np.arange(len(some))
                    some, left = some[first], at[second]
                yield store.rows(
                    _CONTEXTS, bucket=pa.array([k], pa.int32()), symbols=[store.pack(matrix[some].ravel())], real=[store.pack(real[some].ravel())], docs=[store.pack(ids[d[some]])],
                    places=[store.pack(start[some])], left=[store.pack(left)], gone_docs=[store.pack(ids[d[long]])], gone_spans=[store.pack(gone.ravel())],
                )

    return joined.mapInArrow(run, _CONTEXTS)


def row_hashes(matrix: np.ndarray, real: np.ndarray) -> np.ndarray:
    """64-bit hashes of context rows, eight bytes at a time."""
    raw = np.ascontiguousarray(matrix).view(np.uint8).reshape(len(matrix), -1)
    size = raw.shape[1] + 2
    rows = np.zeros((len(raw), -(-size // 8) * 8), np.uint8)
    rows[:, : size - 2], rows[:, size - 2 : size] = raw, real
    h = np.zeros(len(rows), np.uint64)
    for word in np.ascontiguousarray(rows.view(np.uint64).T):
        h = textops.mix((h ^ word) * _U(0x9FB21C651E98DF25) + _U(size))
    return h


def resolve(shape: Shape, dtype, repeated: Callable, parts: int):
    """The reducer of a bucket: ``repeated(matrix, real, doc, place, left)`` gives (doc_id, start,
    end) of what to cover; what blocks have covered already is added. ``left``: the shards'
    second orders, one after the other, as rows."""
    width = 2 * shape.side + shape.gram

    def all_of(table: pa.Table, name: str, kind) -> np.ndarray:
        return np.concatenate([store.unpack(x, kind) for x in table[name].to_pylist()])

    def run(table: pa.Table) -> pa.Table:
        matrix = all_of(table, "symbols", dtype).reshape(-1, width)
        real = all_of(table, "real", np.uint8).reshape(-1, 2).astype(np.int64)
        orders = [store.unpack(x, np.int32).astype(np.int64) for x in table["left"].to_pylist()]
        from_ = np.cumsum([0, *map(len, orders)])
        left = np.concatenate([x + a for x, a in zip(orders, from_)])
        doc, start, end = repeated(matrix, real, all_of(table, "docs", np.int64), all_of(table, "places", np.int32), left)
        gone = all_of(table, "gone_spans", np.int32).reshape(-1, 2)
        doc, start, end = np.concatenate([doc, all_of(table, "gone_docs", np.int64)]), np.concatenate([start, gone[:, 0]]), np.concatenate([end, gone[:, 1]])
        order, here, begin, stop = split((textops.mix(doc.view(np.uint64)) % _U(parts)).astype(np.int32))
        packed = {n: pa.array([store.pack(x[order][a:b]) for a, b in zip(begin, stop)], pa.binary()) for n, x in (("docs", doc), ("starts", start.astype(np.int32)), ("ends", end.astype(np.int32)))}
        return pa.table({"part": pa.array(here), **packed})

    return run


SPANS = store.schema("part int, docs binary, starts binary, ends binary")


def by_document(spans: DataFrame) -> DataFrame:
    """(doc_id, spans) from packed spans: a row per (bucket, part of the documents) came in."""

    def run(table: pa.Table) -> pa.Table:
        columns = [np.concatenate([store.unpack(x, kind) for x in table[n].to_pylist()]) for n, kind in (("docs", np.int64), ("starts", np.int32), ("ends", np.int32))]
        return covers(*columns)

    return spans.groupBy("part").applyInArrow(run, COVER).select("doc_id", F.array("spans").alias("spans"))


class Reach:
    """First and last covered window of each context. All windows of a context overlap, so
    together they are one span."""

    def __init__(self, n: int) -> None:
        self.low, self.high = np.full(n, 1 << 30), np.full(n, -1)

    def add(self, hit: np.ndarray, column: int) -> None:
        self.low[hit] = np.minimum(self.low[hit], column)
        self.high[hit] = np.maximum(self.high[hit], column)

    def spans(self, doc: np.ndarray, place: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        some = np.flatnonzero(self.high >= 0)
        return doc[some], place[some] + self.low[some], place[some] + self.high[some] + window


COVER = store.schema("doc_id long, spans binary")


def covers(doc: np.ndarray, start: np.ndarray, end: np.ndarray) -> pa.Table:
    """Spans of documents, those that overlap merged, as packed (start, end) int32."""
    order = np.lexsort((start, doc))
    doc, start, end = doc[order], start[order].astype(np.int64), end[order].astype(np.int64)
    row = np.cumsum(np.concatenate([[0], doc[1:] != doc[:-1]])) if len(doc) else doc
    reach = np.maximum.accumulate(end + (row << 32)) - (row << 32) if len(doc) else end
    new = np.ones(len(doc), bool)
    new[1:] = (doc[1:] != doc[:-1]) | (start[1:] > reach[:-1])
    first = np.flatnonzero(new)
    last = np.append(first[1:], len(doc)) - 1 if len(doc) else first
    spans = np.stack([start[first], reach[last]], 1).astype(np.int32)
    owner = doc[first]
    ids, begin = np.unique(owner, return_index=True)
    return pa.table({"doc_id": pa.array(ids), "spans": pa.array([spans[a:b].tobytes() for a, b in zip(begin, np.append(begin[1:], len(owner)))], pa.binary())})


def merged(chunks: list[bytes]) -> np.ndarray:
    """Union of packed spans, as sorted disjoint (start, end) rows that don't touch."""
    x = np.frombuffer(b"".join(chunks), np.int32).reshape(-1, 2)
    x = x[np.argsort(x[:, 0], kind="stable")]
    if not len(x):
        return x
    reach = np.maximum.accumulate(x[:, 1])
    new = np.ones(len(x), bool)
    new[1:] = x[1:, 0] > reach[:-1]
    first = np.flatnonzero(new)
    return np.stack([x[first, 0], reach[np.append(first[1:], len(x)) - 1]], 1)


def bucket_count(total: int, symbols_per_byte: float, density: float, per_bucket: int) -> int:
    """Buckets for about so many minimisers each, from the bytes of all texts."""
    return max(8, int(total * symbols_per_byte * density / per_bucket))


def text_bytes(docs: DataFrame) -> int:
    return docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0


def with_spans(docs: DataFrame, spans: DataFrame, finish: Callable, schema) -> DataFrame:
    """``finish`` over (doc_id, text, spans) of all documents.

    Documents with an id are joined as they were for the contexts, so Spark shuffles their
    texts once for both; those without an id keep everything."""
    known = docs.where("doc_id is not null").join(spans, "doc_id", "left").select("doc_id", "text", "spans")
    others = docs.where("doc_id is null").select("doc_id", "text", F.lit(None).cast("array<binary>").alias("spans"))
    return known.mapInArrow(finish, schema).unionByName(others.mapInArrow(finish, schema))
