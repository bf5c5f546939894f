"""Exact n-gram Jaccard self-join with token-combination prefixes.

A document is its set of word n-grams (48-bit hashes). Equal sets form one class. Tokens
are ordered rare before frequent; two sets that are similar enough share at least two
tokens within prefixes that are two tokens longer than the unavoidable loss. So in an
extended prefix every rarer token is indexed alone, and frequent tokens, those in more sets
than one key's pairs are listed for (``all_pairs``), are indexed as combinations of two: a
similar pair shares a rarer one, or two frequent ones. A combination goes to the bucket of
its first token, so splitting a crowded token by its combinations needs no further exchange.
(A prefix of p tokens has p * p / 2 combinations. Sets with longer prefixes than
``combined`` index frequent tokens alone; sizes near that border do both, so no pair is
lost.) Tokens that no other set holds fill prefixes but need no index.

How frequent a token is, is counted over all documents: blocks of documents ask for their
distinct tokens, a row of packed arrays per (block, bucket), and get a frequency class for
each back in the same order. Index entries travel the same way. Of a key in few sets all
pairs of fitting sizes are candidates; for verification their sets meet by their least
token, each sent once to where most of its pairs are. Sets under a key that many hold
(*hot*) are dealt into chunks, those of one most common key together; every two chunks with
a hot key in common meet in one cell of a grid, where all pairs of the two are verified at
once. A pair is verified in one place only, and every pair of classes that is similar is
found. Cells return the number of links of each set and who is joined to whom, not pairs,
so rows don't grow with the square of a group.

Edge cases: null and empty texts have empty sets and link with nothing; texts with fewer
words than n have one shingle, their whole sequence; a null doc_id links with nothing and
is its own (null) component; rows that repeat a doc_id are one node; extra columns are
ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import packs, store, textops
from .components import components

_U = np.uint64
_LOW = _U((1 << 48) - 1)


@dataclass(frozen=True)
class JoinSpec:
    n: int = 5
    percent: int = 80
    all_pairs: int = 24  # sets under a key up to which its pairs are listed; a token in more is frequent
    combined: int = 64  # longest prefix whose frequent tokens are combined
    bucket_bytes: int = 8 << 20
    meet: int = 400  # sets that meet in one place, or in a chunk of the grid
    slice: int = 4096  # tokens looked at together in a cell

    @property
    def combine_below(self) -> int:
        """Set size up to which prefixes are no longer than ``combined``."""
        return self.combined * 100 // max(100 - self.percent, 1)


class Sets:
    """Shingle sets of a block: tokens of document i are tokens[ptr[i]:ptr[i+1]], sorted."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, n: int) -> None:
        data = textops.lower(data)
        starts, ends, ptr = textops.words(data, offsets, textops.SPACED)
        w = textops.word_hashes(data, starts, ends)
        docs = len(offsets) - 1
        grams = textops.gram_hashes(w, n)
        ok = textops.in_document(ptr, len(grams), n)
        doc = textops.doc_of(ptr)[: len(grams)][ok]
        grams = grams[ok]
        size = np.diff(ptr)
        few = np.flatnonzero((size > 0) & (size < n))
        if len(few):
            whole = np.array([textops.gram_hashes(w[ptr[i] : ptr[i + 1]], int(size[i]))[0] + _U(int(size[i])) for i in few], np.uint64)
            grams, doc = np.concatenate([grams, textops.mix(whole)]), np.concatenate([doc, few])
        v = (doc.astype(np.uint64) << _U(48)) | (grams >> _U(16))
        v.sort()
        first = np.ones(len(v), bool)
        first[1:] = v[1:] != v[:-1]
        v = v[first]
        self.doc, self.tokens = (v >> _U(48)).astype(np.int64), v & _LOW
        self.ptr = np.searchsorted(self.doc, np.arange(docs + 1))
        self.size = np.diff(self.ptr)

    def signature(self) -> np.ndarray:
        """A 64-bit sum over each set, mixed with its size."""
        total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(textops.mix(self.tokens + _U(0x51ED27)))])
        return textops.mix((total[self.ptr[1:]] - total[self.ptr[:-1]]) ^ (self.size.astype(np.uint64) << _U(40))).view(np.int64)


def _need(size, percent: int):
    """Least intersection of a set of this size with a similar one."""
    return -(-percent * size // 100)


_ASK = store.schema("bucket int, block long, tokens binary, counts binary, sizes binary")
_CLASS = store.schema("block long, bucket int, classes binary")
_FACT = store.schema("doc_id long, sig long, n long")
_FACTS_BUCKET = -1


class Asked:
    """A block's sets, which of them stand for their class, and the distinct tokens of
    those, dealt out by bucket."""

    def __init__(self, row: dict, spec: JoinSpec, buckets: int) -> None:
        self.pack = packs.Pack(row)
        self.sets = Sets(self.pack.data, self.pack.offsets, spec.n)
        self.sig = self.sets.signature()
        _, first = np.unique(np.where(self.pack.known & (self.sets.size > 0), self.sig, 0), return_index=True)
        self.one = np.zeros(len(self.sig), bool)
        self.one[first] = True
        self.one &= self.pack.known & (self.sets.size > 0)
        token, self.count = np.unique(self.sets.tokens[self.one[self.sets.doc]], return_counts=True)
        bucket = (token * _U(buckets) >> _U(48)).astype(np.int32)  # by range, so order stays
        self.token, self.buckets, self.begin = token, *np.unique(bucket, return_index=True)
        self.end = np.append(self.begin[1:], len(token))


def _asks(blocks: DataFrame, spec: JoinSpec, buckets: int) -> DataFrame:
    def run(batches):
        for row in store.each_row(batches):
            x = Asked(row, spec, buckets)
            ids = np.where(x.pack.known, x.pack.ids, 0)
            yield store.rows(_ASK, bucket=[_FACTS_BUCKET], block=[x.pack.block], tokens=[store.pack(ids)], counts=[store.pack(x.sig)], sizes=[store.pack(np.where(x.pack.known, x.sets.size, -1 - x.sets.size))])
            for k, a, b in zip(x.buckets.tolist(), x.begin, x.end):
                step = np.diff(x.token[a:b], prepend=np.uint64(0))
                yield store.rows(_ASK, bucket=[k], block=[x.pack.block], tokens=[store.pack(step)], counts=[store.pack(x.count[a:b].astype(np.int32))], sizes=[None])

    return blocks.mapInArrow(run, _ASK)


def _facts(asked: DataFrame) -> DataFrame:
    """(doc_id, sig, n) of every document."""

    def run(batches):
        for row in store.each_row(batches):
            ids, size = store.unpack(row["tokens"], np.int64), store.unpack(row["sizes"], np.int64)
            yield store.rows(_FACT, doc_id=pa.array(ids, pa.int64(), mask=size < 0), sig=pa.array(store.unpack(row["counts"], np.int64)), n=pa.array(np.where(size < 0, -1 - size, size)))

    return asked.where(F.col("bucket") == _FACTS_BUCKET).mapInArrow(run, _FACT)


def _classes(spec: JoinSpec):
    """Frequency classes of a bucket's tokens: 0 in one set only, up to 3 frequent."""

    def run(table: pa.Table) -> pa.Table:
        asked = [np.cumsum(store.unpack(x, np.uint64)) for x in table["tokens"].to_pylist()]
        counts = [store.unpack(x, np.int32) for x in table["counts"].to_pylist()]
        token, each = np.unique(np.concatenate(asked), return_inverse=True)
        total = np.bincount(each, np.concatenate(counts))
        level = np.searchsorted([2, min(8, spec.all_pairs), spec.all_pairs + 1], total, "right").astype(np.uint8)[each]
        cut = np.cumsum([len(x) for x in asked])[:-1]
        return pa.table({"block": table["block"], "bucket": table["bucket"], "classes": pa.array([store.pack(x) for x in np.split(level, cut)], pa.binary())})

    return run


_INDEX = store.schema("bucket int, firsts binary, keys binary, sets binary, sizes binary, sig long, n int, least long, tokens binary")


def _prefix(x: Asked, level: np.ndarray, spec: JoinSpec):
    """Index keys of a block: (first token, key, document) arrays. The key is the token
    itself or the hash of a combination."""
    sets, size = x.sets, x.sets.size
    length = np.where(x.one & (size > 1), np.minimum(size - _need(size, spec.percent) + 2, size), 0)
    order = np.argsort((sets.doc << 2) | level, kind="stable")  # tokens of a set are in order already
    take = order[textops.ranges(sets.ptr[:-1], length)]
    doc, token, rank = sets.doc[take], sets.tokens[take], level[take]
    common = rank == 3
    alone = ((rank > 0) & ~common) | (common & (size[doc] >= spec.combine_below * spec.percent // 100))
    pairable = common & (size[doc] <= spec.combine_below * 100 // spec.percent)
    one, owner = token[alone], doc[alone]
    token, doc = token[pairable], doc[pairable]  # in order within a document
    after = np.searchsorted(doc, doc, "right") - np.arange(len(doc)) - 1  # tokens of the same set that follow
    first = np.repeat(np.arange(len(doc)), after)
    second = textops.ranges(np.arange(len(doc)) + 1, after)
    both = textops.mix(token[first] * _U(0x9E3779B97F4A7C15) + token[second]) | ~_LOW  # never a token
    return np.concatenate([one, token[first]]), np.concatenate([one, both]), np.concatenate([owner, doc[first]])


def _index(joined: DataFrame, asks: int, buckets: int, spec: JoinSpec) -> DataFrame:
    """Index rows by bucket, and a row (sig, n, least token, tokens) per indexed set."""

    def run(batches):
        for row in store.each_row(batches):
            x = Asked(row, spec, asks)
            found = [store.unpack(r["classes"], np.uint8) for r in sorted(row["answers"], key=lambda r: r["bucket"])]
            level = np.concatenate([*found, np.zeros(0, np.uint8)])
            if len(x.token):
                at = np.minimum(np.searchsorted(x.token, x.sets.tokens), len(x.token) - 1)
                first, key, doc = _prefix(x, np.where(x.one[x.sets.doc], level[at], 0), spec)
            else:
                first, key, doc = np.zeros(0, np.uint64), np.zeros(0, np.uint64), np.zeros(0, np.int64)
            bucket = (textops.mix(first) % _U(buckets)).astype(np.int32)
            order = np.lexsort((first, bucket))
            first, key, owner, bucket = first[order], key[order], doc[order], bucket[order]
            here, begin = np.unique(bucket, return_index=True)
            nothing = dict(sig=[None], n=[None], least=[None], tokens=[None])
            for k, a, b in zip(here.tolist(), begin, np.append(begin[1:], len(bucket))):
                yield store.rows(_INDEX, bucket=[k], firsts=[store.pack(first[a:b])], keys=[store.pack(key[a:b])], sets=[store.pack(x.sig[owner[a:b]])], sizes=[store.pack(x.sets.size[owner[a:b]].astype(np.int32))], **nothing)
            some = np.unique(doc)
            if len(some):
                a, b = x.sets.ptr[some], x.sets.ptr[some + 1]
                none = pa.nulls(len(some), pa.binary())
                yield store.rows(
                    _INDEX, bucket=pa.nulls(len(some), pa.int32()), firsts=none, keys=none, sets=none, sizes=none, sig=pa.array(x.sig[some]), n=pa.array(x.sets.size[some].astype(np.int32)),
                    least=pa.array(x.sets.tokens[a].view(np.int64)), tokens=[_six(x.sets.tokens[i:j]) for i, j in zip(a, b, strict=True)],
                )

    return joined.mapInArrow(run, _INDEX)


#: key is null for a pair (a, b); else the row says that set a is under a hot key that is
#: this token or a combination with it
_PAIRS = store.schema("key long, a long, b long")


def _fits(na, nb, percent: int):
    return 100 * np.minimum(na, nb) >= percent * np.maximum(na, nb)


def _bucket_pairs(spec: JoinSpec):
    def run(table: pa.Table) -> pa.Table:
        first = np.concatenate([store.unpack(x, np.uint64) for x in table["firsts"].to_pylist()])
        key = np.concatenate([store.unpack(x, np.uint64) for x in table["keys"].to_pylist()])
        sets = np.concatenate([store.unpack(x, np.int64) for x in table["sets"].to_pylist()])
        size = np.concatenate([store.unpack(x, np.int32) for x in table["sizes"].to_pylist()])
        order = np.lexsort((sets, size, key))
        key, sets, size, first = key[order], sets[order], size[order], first[order]
        keep = np.ones(len(key), bool)
        keep[1:] = (key[1:] != key[:-1]) | (sets[1:] != sets[:-1])
        key, sets, size, first = key[keep], sets[keep], size[keep], first[keep]
        begin = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, np.int64)
        count = np.diff(np.append(begin, len(key)))
        a, b = [], []
        small = count <= spec.all_pairs
        for m in np.unique(count[(count > 1) & small]):
            at = begin[count == m]
            i, j = np.triu_indices(int(m), 1)
            a.append((at[:, None] + i).ravel())
            b.append((at[:, None] + j).ravel())
        large = textops.ranges(begin[~small], count[~small])
        hot = np.unique(np.stack([first[large].view(np.int64), sets[large]], 1), axis=0)  # a row per token, whatever its combinations
        a, b = (np.concatenate([np.zeros(0, np.int64), *x]).astype(np.int64) for x in (a, b))
        ok = _fits(size[a], size[b], spec.percent) & (sets[a] != sets[b])
        pair = np.unique(np.stack([np.minimum(sets[a[ok]], sets[b[ok]]), np.maximum(sets[a[ok]], sets[b[ok]])], 1), axis=0)
        k = len(pair)
        return pa.table(
            {
                "key": pa.chunked_array([pa.nulls(k, pa.int64()), pa.array(hot[:, 0])]),
                "a": pa.chunked_array([pa.array(pair[:, 0]), pa.array(hot[:, 1])]),
                "b": pa.chunked_array([pa.array(pair[:, 1]), pa.nulls(len(hot), pa.int64())]),
            }
        )

    return run


def _six(x: np.ndarray) -> bytes:
    """48-bit tokens, six bytes each."""
    return x.view(np.uint8).reshape(-1, 8)[:, :6].tobytes()


def _eight(blobs: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    raw = np.frombuffer(b"".join(blobs), np.uint8).reshape(-1, 6)
    out = np.zeros((len(raw), 8), np.uint8)
    out[:, :6] = raw
    return out.view(np.uint64).ravel(), np.concatenate([[0], np.cumsum([len(x) // 6 for x in blobs])]).astype(np.int64)


_LINK = store.schema("a long, b long")


def _verify(pairs: DataFrame, sets: DataFrame, places: int, spec: JoinSpec) -> DataFrame:
    """The pairs (a, b) of sets that are similar.

    Pairs meet where their common least token says (large gatherings in a grid of chunks),
    or else at one of the two; every set is sent once to each place that needs it."""
    many = sets.groupBy("least").agg(F.ceil(F.count(F.lit(1)) / spec.meet).alias("chunks"))
    attrs = sets.select("sig", "least").join(many, "least")
    a = attrs.select(F.col("sig").alias("a"), F.col("least").alias("la"), "chunks")
    b = attrs.select(F.col("sig").alias("b"), F.col("least").alias("lb"))
    chunk = lambda c: F.pmod(F.xxhash64(c), F.col("chunks"))
    place = F.when(F.col("la") == F.col("lb"), F.xxhash64("la", chunk("a"), chunk("b"))).otherwise(F.xxhash64("a"))
    met = pairs.join(a, "a").join(b, "b").select("a", "b", F.pmod(place, F.lit(places)).cast("int").alias("place"))
    need = met.select("place", F.explode(F.array("a", "b")).alias("sig")).distinct()
    sent = need.join(sets.select("sig", "tokens"), "sig").select(F.col("place").alias("spot"), "sig", "tokens")

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        sig, (token, ptr) = right["sig"].to_numpy(), _eight(right["tokens"].to_pylist())
        order = np.argsort(sig)
        x, y = (order[np.searchsorted(sig, left[c].to_numpy(), sorter=order)] for c in ("a", "b"))
        size = np.diff(ptr)
        good = []
        for at in range(0, len(x), 300):
            i, j = x[at : at + 300], y[at : at + 300]
            row = np.arange(len(i)).astype(np.uint64) << _U(48)
            both = np.concatenate([token[textops.ranges(ptr[i], size[i])] | np.repeat(row, size[i]), token[textops.ranges(ptr[j], size[j])] | np.repeat(row, size[j])])
            both.sort()
            shared = np.bincount((both[1:][both[1:] == both[:-1]] >> _U(48)).astype(np.int64), minlength=len(i))
            good.append(100 * shared >= spec.percent * (size[i] + size[j] - shared))
        keep = pa.array(np.concatenate([np.zeros(0, bool), *good]))
        return left.select(["a", "b"]).filter(keep)

    return met.groupBy("place").cogroup(sent.groupBy("spot")).applyInArrow(run, _LINK)


_CELL = store.schema("a long, b long, links long")


def _chunks(hot: DataFrame, spec: JoinSpec) -> DataFrame:
    """(sig, chunk) of every set under a hot key: those with the same most common key are
    together, dealt into chunks of about ``meet``."""
    many = hot.groupBy("key").agg(F.count(F.lit(1)).alias("m"))
    home = hot.join(many, "key").groupBy("sig").agg(F.max(F.struct("m", "key")).alias("h")).select("sig", F.col("h.key").alias("home"))
    parts = home.groupBy("home").agg(F.ceil(F.count(F.lit(1)) / spec.meet).alias("parts"))
    return home.join(parts, "home").select("sig", F.xxhash64("home", F.pmod(F.xxhash64("sig"), F.col("parts"))).alias("chunk"))


def _cells(hot: DataFrame, chunks: DataFrame) -> DataFrame:
    """(c, d), c <= d: chunks that have a hot key in common."""
    held = hot.join(chunks, "sig").select("key", F.col("chunk").alias("c")).distinct()
    other = held.select(F.col("key").alias("k"), F.col("c").alias("d"))
    return held.join(other, (F.col("key") == F.col("k")) & (F.col("c") <= F.col("d"))).select("c", "d").distinct()


def _shared(token: np.ndarray, ptr: np.ndarray, left: np.ndarray, right: np.ndarray, width: int) -> np.ndarray:
    """Tokens that each left set shares with each right one, a slice of tokens at a time."""
    owner = textops.doc_of(ptr)
    _, each, count = np.unique(token, return_inverse=True, return_counts=True)
    rank = np.cumsum(count > 1) - 1
    some = count[each] > 1  # others are shared by none
    column, owner = rank[each][some], owner[some]
    order = np.argsort(column, kind="stable")
    column, owner = column[order], owner[order]
    out = np.zeros((len(left), len(right)), np.float32)
    for at in range(0, int(column[-1]) + 1 if len(column) else 0, width):
        i, j = np.searchsorted(column, [at, at + width])
        held = np.zeros((len(ptr) - 1, width), np.float32)
        held[owner[i:j], column[i:j] - at] = 1
        out += held[left] @ held[right].T
    return out.astype(np.int64)


def _joined(similar: np.ndarray) -> np.ndarray:
    """The least row that each row of a symmetric matrix reaches."""
    label = np.arange(len(similar))
    while True:
        low = np.minimum(label, np.where(similar, label, len(label)).min(1, initial=len(label)))
        low = np.minimum(low, low[low])
        if (low == label).all():
            return label
        label = low


def _cell_links(spec: JoinSpec):
    """Of a cell, (a, b, links): the links of set a in it, and a set b that they join it to."""

    def run(table: pa.Table) -> pa.Table:
        sig, (token, ptr) = table["sig"].to_numpy(), _eight(table["tokens"].to_pylist())
        size, chunk = np.diff(ptr), table["chunk"].to_numpy()
        left = np.flatnonzero(chunk == table["c"].to_numpy())
        right = np.flatnonzero(chunk == table["d"].to_numpy())
        shared = _shared(token, ptr, left, right, spec.slice)
        good = (100 * shared >= spec.percent * (size[left][:, None] + size[right] - shared)) & (sig[left][:, None] != sig[right])
        similar = np.zeros((len(sig), len(sig)), bool)
        similar[np.ix_(left, right)] = good
        similar |= similar.T
        links = similar.sum(1)
        some = links > 0
        return pa.table({"a": pa.array(sig[some]), "b": pa.array(sig[_joined(similar)][some]), "links": pa.array(links[some].astype(np.int64))})

    return run


def _meet(cells: DataFrame, chunks: DataFrame, sets: DataFrame, spec: JoinSpec) -> DataFrame:
    need = cells.select("c", "d", F.explode(F.array_distinct(F.array("c", "d"))).alias("chunk"))
    sent = need.join(sets.join(chunks, "sig").select("sig", "chunk", "tokens"), "chunk")
    return sent.groupBy("c", "d").applyInArrow(_cell_links(spec), _CELL)


def join(docs: DataFrame, spec: JoinSpec = JoinSpec()) -> DataFrame:
    """(doc_id, n_shingles, class_id, component_id, n_links): the least doc_id with the same
    set, the least doc_id reachable over links between sets that are similar enough, and with
    how many other classes the document's class has such a link."""
    blocks = store.settle(packs.packs(store.documents(docs, "doc_id", "text")), "packs")
    size = blocks.agg(F.sum("bytes")).first()[0] or 0
    asks = max(8, size // (24 << 20))
    asked = store.settle(_asks(blocks, spec, asks), "asks")
    answers = asked.where(F.col("bucket") != _FACTS_BUCKET).groupBy("bucket").applyInArrow(_classes(spec), _CLASS)
    answers = answers.groupBy("block").agg(F.collect_list(F.struct("bucket", "classes")).alias("answers"))  # as many as a block asked
    sized = store.settle(_facts(asked), "facts")

    buckets = max(8, size // (spec.bucket_bytes * 4))
    index = store.settle(_index(blocks.join(answers, "block"), asks, buckets, spec), "index")
    store.drop(blocks, asked)
    raw = store.settle(index.where("bucket is not null").select("bucket", "firsts", "keys", "sets", "sizes").groupBy("bucket").applyInArrow(_bucket_pairs(spec), _PAIRS), "candidates")
    pairs = raw.where("key is null").select("a", "b").distinct()
    hot = raw.where("key is not null").select("key", F.col("a").alias("sig"))
    wanted = pairs.select(F.explode(F.array("a", "b")).alias("sig")).unionByName(hot.select("sig")).distinct()
    sets = index.where("bucket is null").select("sig", "n", "least", "tokens").dropDuplicates(["sig"]).join(wanted, "sig", "left_semi")
    sets = store.settle(sets, "tokens")
    store.drop(index)
    places = max(8, (sets.agg(F.sum("n")).first()[0] or 0) * 12 // spec.bucket_bytes)

    crowded = hot.limit(1).count() > 0
    if crowded:
        chunks = store.settle(_chunks(hot, spec), "chunks")
        cells = store.settle(_cells(hot, chunks), "cells")
        first, second = (chunks.select(F.col("sig").alias(x), F.col("chunk").alias(f"c{x}")) for x in ("a", "b"))
        placed = pairs.join(first, "a", "left").join(second, "b", "left").select("a", "b", F.least("ca", "cb").alias("x"), F.greatest("ca", "cb").alias("y"), (F.col("ca").isNotNull() & F.col("cb").isNotNull()).alias("both"))
        # a pair whose chunks meet is verified there
        pairs = placed.join(cells, F.col("both") & (F.col("x") == F.col("c")) & (F.col("y") == F.col("d")), "left_anti").select("a", "b")
    links = store.settle(_verify(pairs, sets, places, spec), "verified")
    ends = links.select(F.explode(F.array("a", "b")).alias("sig"), F.lit(1).cast("long").alias("links"))
    if crowded:
        met = store.settle(_meet(cells, chunks, sets, spec), "met")
        links = links.unionByName(met.select("a", "b"))
        ends = ends.unionByName(met.select(F.col("a").alias("sig"), "links"))
    degree = ends.groupBy("sig").agg(F.sum("links").alias("n_links"))
    label = store.settle(components(links), "labels").select(F.col("node").alias("sig"), F.col("least").alias("label"))

    # from classes to documents: the least document of each class and component
    classes = sized.where("doc_id is not null and n > 0").groupBy("sig", "n").agg(F.min("doc_id").alias("class_id"))
    classes = classes.join(label, "sig", "left").join(degree, "sig", "left").withColumns({"label": F.coalesce("label", "sig"), "n_links": F.coalesce("n_links", F.lit(0).cast("long"))})
    classes = store.settle(classes, "classes")
    low = classes.groupBy("label").agg(F.min("class_id").alias("component_id"))
    ids = classes.join(low, "label").select("sig", "n", "class_id", "component_id", "n_links")
    each = sized.join(ids, ["sig", "n"], "left")
    alone = F.col("n") == 0
    return each.select("doc_id", F.col("n").alias("n_shingles"), F.when(alone, F.col("doc_id")).otherwise(F.coalesce("class_id", "doc_id")).alias("class_id"), F.when(alone, F.col("doc_id")).otherwise(F.coalesce("component_id", "doc_id")).alias("component_id"), F.when(F.col("doc_id").isNull(), 0).otherwise(F.coalesce("n_links", F.lit(0))).cast("long").alias("n_links"))


def one_of_each(docs: DataFrame, spec: JoinSpec = JoinSpec()) -> DataFrame:
    """The documents without near copies: of each component, the least doc_id stays."""
    gone = join(docs, spec).where("component_id <> doc_id").select(F.col("doc_id").alias("_gone")).distinct()
    return docs.join(gone, docs["doc_id"] == gone["_gone"], "left_anti")
