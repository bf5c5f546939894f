"""Language-model scores from a probabilistic suffix tree.

Symbols are the bytes of the lower-cased words, joined by single spaces, and a text's end.
Every context of up to ``depth`` bytes is counted over all training texts. A context is
retained if it stands at least ``least`` times and if its next-symbol counts diverge enough
from its parent's (the context without its farthest byte), or if a longer retained context
needs it. Next-symbol distributions are smoothed towards the parent's, down
to a root with half a count per symbol. A token is spelled with the longest retained suffix
of what precedes each symbol, across word borders; the probability of a token seen in
training mixes that with its share of the training tokens. All unseen tokens are one symbol,
as in the unigram base, with the probability mass of tokens seen once.

The retained contexts grow with the corpus, so the tree is nowhere as a whole. It is dealt
out by the three nearest bytes: blocks of documents send their distinct grams with training
counts, a row per (block, bucket); a bucket builds its part of the tree from them and sends
their probabilities back in the same order. Only the counts of contexts of up to two bytes,
at most 256 ** 3 at any size, go to all tasks.

The unigram base needs the count of every word. Blocks of documents ask for their distinct
words by hash, a row per (block, bucket), and get the counts back in the same order, so
neither the vocabulary nor the texts are gathered anywhere.

Edge cases: null and empty texts are their end alone; a null doc_id counts as the text "";
repeated rows are separate documents; a very long text is a block of its own; without any
training text all counts are zero; an empty table gives an empty result; extra columns are
ignored.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import store, textops

_U = np.uint64


@dataclass(frozen=True)
class TreeSpec:
    depth: int = 6  # at most 6: contexts and symbol share a 64-bit key
    least: int = 8  # occurrences of a retained context, at any corpus size
    gain: float = 30.0  # least log-likelihood ratio (nats) against the parent context
    tree_share: float = 0.5  # of the tree in a known token's probability
    bucket_bytes: int = 4 << 20  # of texts for each bucket
    strength: float = 4.0  # of the parent's distribution, in counts
    folds: int = 5
    held_fold: int = 1


END = 0  # byte 0 stands for the end of a text (and for what precedes its start)
SYMBOLS = 256


def fold(doc_ids: list, folds: int) -> np.ndarray:
    """crc32 of each id's decimal text, modulo the number of folds."""
    return np.array([zlib.crc32(b"" if x is None else str(x).encode()) % folds for x in doc_ids], np.int64)


BLOCK = 4 << 20  # bytes of texts: a gram is sent once for each block that has it
_PACK = store.schema("block long, ids binary, known binary, held binary, offsets binary, bytes long, texts binary")


def packs(docs: DataFrame, spec: TreeSpec) -> DataFrame:
    """Documents in compressed blocks, each with a number of its own."""

    def run(batches):
        base = TaskContext.get().partitionId() << 32
        for k, (batch, data, offsets) in enumerate(textops.blocks(batches, BLOCK)):
            ids = batch.column(0).to_pylist()
            known = np.array([x is not None for x in ids])
            number = np.array([x or 0 for x in ids], np.int64)
            yield store.rows(
                _PACK, block=[base + k], ids=[store.pack(number)], known=[store.pack(known)], held=[store.pack(fold(ids, spec.folds) == spec.held_fold)],
                offsets=[store.pack(offsets)], bytes=[len(data)], texts=[pa.compress(data.tobytes(), codec="zstd", asbytes=True)],
            )

    return store.documents(docs, "doc_id", "text").mapInArrow(run, _PACK)


class Block:
    """An unpacked block: lower-cased bytes, words and fold flags."""

    def __init__(self, row: dict) -> None:
        self.offsets = store.unpack(row["offsets"], np.int64)
        self.held = store.unpack(row["held"], bool)
        size = row["bytes"]
        raw = pa.decompress(row["texts"], decompressed_size=size, codec="zstd", asbytes=True) if size else b""
        data = textops.lower(np.frombuffer(raw, np.uint8))
        self.data = data
        self.starts, self.ends, self.ptr = textops.words(data, self.offsets, textops.SPACED)

    @cached_property
    def words(self) -> np.ndarray:
        return textops.word_hashes(self.data, self.starts, self.ends)

    def symbols(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The texts as bytes (each word with a space, then the end), the documents'
        offsets in them, and where each token starts: words and ends in order."""
        size = self.ends - self.starts + 1
        n_docs = len(self.offsets) - 1
        run = np.concatenate([[0], np.cumsum(size)])
        offsets = run[self.ptr] + np.arange(n_docs + 1)
        at = run[:-1] + textops.doc_of(self.ptr)
        out = np.full(int(offsets[-1]), 32, np.uint8)
        out[textops.ranges(at, size - 1)] = self.data[textops.ranges(self.starts, size - 1)]
        out[offsets[1:] - 1] = END
        tokens = np.sort(np.concatenate([at, offsets[1:] - 1]))
        return out, offsets, tokens


def grams(symbols: np.ndarray, offsets: np.ndarray, depth: int) -> np.ndarray:
    """Per symbol a key: nearest context byte on top, the farthest below, the symbol last."""
    size = np.diff(offsets)
    at = np.arange(len(symbols)) + np.repeat(np.arange(1, len(size) + 1) * depth, size)
    padded = np.full(len(symbols) + len(size) * depth + 8, END, np.uint8)  # each text after its own ends
    padded[at] = symbols
    near = np.ndarray(len(padded) - 7, "<u8", padded, strides=(1,))  # eight bytes from each place on
    return ((near[at - depth] & _U((1 << 8 * depth) - 1)) << _U(8)) | symbols


def _merge(keys: list[np.ndarray], counts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    key, count = np.concatenate(keys), np.concatenate(counts)
    order = np.argsort(key, kind="stable")
    key, count = key[order], count[order]
    del order
    begin = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, np.int64)
    return key[begin], np.add.reduceat(count, begin, dtype=np.int64) if len(key) else count.astype(np.int64)


_GRAM = store.schema("bucket int, block long, keys binary, counts binary")
_SHORT = store.schema("gram long, n long")
NEAR = 3  # nearest bytes that deal grams out; shorter contexts are counted apart


def _gram_bucket(key: np.ndarray, spec: TreeSpec, buckets: int) -> np.ndarray:
    return (textops.mix(key >> _U(8 * (spec.depth - NEAR + 1))) % _U(buckets)).astype(np.int32)


def gram_counts(blocks: DataFrame, spec: TreeSpec, buckets: int) -> DataFrame:
    """The distinct grams of each block with their counts in its training texts, dealt out
    by their three nearest bytes."""

    def run(batches):
        for row in store.each_row(batches):
            b = Block(row)
            symbols, offsets, _ = b.symbols()
            key = (grams(symbols, offsets, spec.depth) << _U(1)) | np.repeat(~b.held, np.diff(offsets))
            key.sort()  # of 57 bits, the last tells training texts
            key, train = key >> _U(1), (key & _U(1)).astype(np.int32)
            begin = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, np.int64)
            key, count = key[begin], np.add.reduceat(train, begin, dtype=np.int32) if len(begin) else train
            bucket = _gram_bucket(key, spec, buckets)
            order = np.argsort(bucket, kind="stable")
            here, first = np.unique(bucket[order], return_index=True)
            parts = np.split(order, first[1:]) if len(here) else []
            yield store.rows(
                _GRAM, bucket=pa.array(here, pa.int32()), block=[row["block"]] * len(here), keys=[store.pack(np.diff(key[x], prepend=_U(0))) for x in parts],
                counts=[store.pack(count[x]) for x in parts],
            )

    return blocks.mapInArrow(run, _GRAM)


def _keys(blob: bytes) -> np.ndarray:
    return np.cumsum(store.unpack(blob, np.uint64))


def short_counts(blocks: DataFrame) -> DataFrame:
    """(gram, n) of contexts of two bytes in the training texts; a sum of sums."""

    def run(batches):
        gram, n = np.zeros(0, np.uint64), np.zeros(0, np.int64)
        for row in store.each_row(batches):
            b = Block(row)
            symbols, offsets, _ = b.symbols()
            here, count = np.unique(grams(symbols, offsets, 2)[np.repeat(~b.held, np.diff(offsets))], return_counts=True)
            gram, n = _merge([gram, here], [n, count])
        yield store.rows(_SHORT, gram=pa.array(gram.view(np.int64)), n=pa.array(n))

    return blocks.mapInArrow(run, _SHORT).groupBy("gram").agg(F.sum("n").alias("n"))


def short_states(gram: np.ndarray, n: np.ndarray) -> pa.Table:
    """(level, context, symbol, n) of the contexts of at most one byte, from those of two."""
    root = np.bincount((gram & _U(255)).astype(np.int64), n, minlength=SYMBOLS).astype(np.int64)
    symbol = np.flatnonzero(root)
    pair, c = _merge([(gram >> _U(16) << _U(8)) | (gram & _U(255))], [n])
    return pa.table(
        [np.repeat([0, 1], [len(symbol), len(pair)]).astype(np.int32), np.concatenate([np.zeros(len(symbol), np.int64), (pair >> _U(8)).view(np.int64)]),
         np.concatenate([symbol, (pair & _U(255)).view(np.int64)]).astype(np.int32), np.concatenate([root[symbol], c])], schema=SHORT,
    )


def states(key: np.ndarray, count: np.ndarray, spec: TreeSpec, above: tuple[np.ndarray, np.ndarray] | None = None) -> pa.Table:
    """(level, context, symbol, n): next-symbol counts of the retained contexts of two or
    more bytes, from all grams of a bucket, sorted. ``above`` has the grams of two-byte
    contexts, sorted, and their counts; without it they are counted here."""
    symbol = key & _U(255)

    def level(n: int) -> tuple:
        context = key >> _U(8 * (spec.depth - n + 1))
        pair, c = above if n == 2 and above else _merge([(context << _U(8)) | symbol], [count])
        owner = pair >> _U(8)
        begin = np.flatnonzero(np.concatenate([[True], owner[1:] != owner[:-1]])) if len(owner) else np.zeros(0, np.int64)
        each = np.repeat(np.arange(len(begin), dtype=np.int32), np.diff(np.append(begin, len(owner))))
        return owner[begin], pair, c, each, np.add.reduceat(c, begin) if len(begin) else c

    out = []
    wanted = np.zeros(0, np.uint64)  # contexts that longer retained ones need
    parents = level(spec.depth)
    for n in range(spec.depth, 1, -1):
        (owner, pair, c, each, total), parents = parents, level(n - 1) if n >= 3 else None  # two levels at a time
        keep = total >= spec.least
        if n >= 3:  # of two bytes, all are kept that stand often enough
            p_owner, p_pair, p_c, _, p_total = parents
            up = (pair >> _U(16) << _U(8)) | (pair & _U(255))
            at = np.searchsorted(p_pair, up)
            parent = p_c[at] / p_total[np.searchsorted(p_owner, up >> _U(8))]
            keep &= np.bincount(each, c * np.log(c / total[each] / parent), minlength=len(owner)) >= spec.gain
        keep |= np.isin(owner, wanted)
        wanted = np.unique(owner[keep] >> _U(8))
        some = keep[each]
        out.append((np.full(int(some.sum()), n, np.int32), (pair[some] >> _U(8)).view(np.int64), (pair[some] & _U(255)).astype(np.int32), c[some]))
    return pa.table(dict(zip(("level", "context", "symbol", "n"), (np.concatenate(x) for x in zip(*out)), strict=True)))


_SPELLED = store.schema("block long, bucket int, logs binary")


def spell(counted: DataFrame, short: pa.Table, above: tuple[np.ndarray, np.ndarray], spec: TreeSpec) -> DataFrame:
    """(block, bucket, logs): log10 P(symbol | longest retained suffix) of the grams that a
    block sent to a bucket, in their order."""

    def run(table: pa.Table) -> pa.Table:
        asked = table["keys"].to_pylist()  # unpacked twice rather than held
        key, count = _merge([_keys(x) for x in asked], [store.unpack(x, np.int32) for x in table["counts"].to_pylist()])
        tree = Tree(pa.concat_tables([short, states(key[count > 0], count[count > 0], spec, above)]), spec)
        logs = np.log10(tree.probability(key)).astype(np.float32)
        back = [store.pack(logs[np.searchsorted(key, _keys(x))]) for x in asked]
        return pa.table({"block": table["block"], "bucket": table["bucket"], "logs": pa.array(back, pa.binary())})

    return counted.groupBy("bucket").applyInArrow(run, _SPELLED)


SHORT = pa.schema([("level", pa.int32()), ("context", pa.int64()), ("symbol", pa.int32()), ("n", pa.int64())])


class Tree:
    """Retained contexts by level: totals and next-symbol counts, sorted for lookup."""

    def __init__(self, table: pa.Table, spec: TreeSpec) -> None:
        level, context = table["level"].to_numpy(), table["context"].to_numpy().view(np.uint64)
        symbol, n = table["symbol"].to_numpy().astype(np.uint64), table["n"].to_numpy()
        self.depth, self.strength = spec.depth, spec.strength
        root = np.full(SYMBOLS, 0.5)
        at = level == 0
        np.add.at(root, symbol[at].astype(np.int64), n[at])
        self.root = root / root.sum()
        self.levels = []
        for k in range(1, spec.depth + 1):
            at = level == k
            pair = (context[at] << _U(8)) | symbol[at]
            order = np.argsort(pair)
            pair, c = pair[order], n[at][order]
            owner = pair >> _U(8)
            begin = np.flatnonzero(np.concatenate([[True], owner[1:] != owner[:-1]])) if len(owner) else np.zeros(0, np.int64)
            self.levels.append((owner[begin], np.add.reduceat(c, begin) if len(begin) else c, pair, c))

    def probability(self, key: np.ndarray) -> np.ndarray:
        """P(symbol | longest retained suffix) of each gram key."""
        symbol = key & _U(255)
        p = self.root[symbol.astype(np.int64)]
        alive = np.arange(len(key))
        for k, (owner, total, pair, c) in enumerate(self.levels, 1):
            if not len(owner) or not len(alive):
                break
            context = key[alive] >> _U(8 * (self.depth - k + 1))
            at = np.minimum(np.searchsorted(owner, context), len(owner) - 1)
            here = owner[at] == context
            alive, at = alive[here], at[here]
            want = (context[here] << _U(8)) | symbol[alive]
            j = np.minimum(np.searchsorted(pair, want), len(pair) - 1)
            n = np.where(pair[j] == want, c[j], 0)
            p[alive] = (n + self.strength * p[alive]) / (total[at] + self.strength)
        return p


_ASK = store.schema("bucket int, block long, words binary, counts binary, docs long, tokens long")
_ANSWER = store.schema("block long, bucket int, counts binary, known long, once long")
_OUT = store.schema("doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")


def _deal(words: np.ndarray, buckets: int) -> np.ndarray:
    return ((words >> _U(32)) % _U(buckets)).astype(np.int32)


def score(docs: DataFrame, spec: TreeSpec = TreeSpec()) -> DataFrame:
    """Unigram base and suffix-tree log10 probabilities of every text."""
    blocks = store.settle(packs(docs, spec), "packs")
    size = blocks.agg(F.sum("bytes")).first()[0] or 0
    buckets = max(8, size // spec.bucket_bytes)

    counts = short_counts(blocks).toArrow()  # at most 256 ** 3 rows
    above = _merge([counts["gram"].to_numpy().view(np.uint64)], [counts["n"].to_numpy()])
    spelt = spell(gram_counts(blocks, spec, buckets), short_states(*above), above, spec).groupBy("block").agg(F.collect_list(F.struct("bucket", "logs")).alias("spelt"))  # as many as a block asked

    def ask(batches):
        for row in store.each_row(batches):
            b = Block(row)
            word, each = np.unique(b.words, return_inverse=True)
            train = ~b.held[textops.doc_of(b.ptr)]
            count = np.bincount(each[train], minlength=len(word))
            bucket = _deal(word, buckets)
            order = np.argsort(bucket, kind="stable")
            here, begin = np.unique(bucket[order], return_index=True)
            head = (int((~b.held).sum()), int(train.sum()))
            for k, x, y in zip(here.tolist(), begin, np.append(begin[1:], len(word))):
                part = order[x:y]
                yield store.rows(_ASK, bucket=[k], block=[row["block"]], words=[store.pack(word[part])], counts=[store.pack(count[part].astype(np.int32))], docs=[head[0]], tokens=[head[1]])
                head = (0, 0)
            if not len(word):
                yield store.rows(_ASK, bucket=[0], block=[row["block"]], words=[store.pack(word)], counts=[store.pack(np.zeros(0, np.int32))], docs=[head[0]], tokens=[0])

    def answer(table: pa.Table) -> pa.Table:
        asked = [store.unpack(x, np.uint64) for x in table["words"].to_pylist()]
        counts = [store.unpack(x, np.int32).astype(np.int64) for x in table["counts"].to_pylist()]
        word, total = _merge(asked, counts)
        back = [store.pack(total[np.searchsorted(word, x)].astype(np.int32)) for x in asked]
        known = np.zeros(len(back), np.int64)
        once = known.copy()
        known[0], once[0] = int((total > 0).sum()), int((total == 1).sum())
        return pa.table({"block": table["block"], "bucket": table["bucket"], "counts": pa.array(back, pa.binary()), "known": pa.array(known), "once": pa.array(once)})

    asked = store.settle(blocks.mapInArrow(ask, _ASK), "words")
    answers = store.settle(asked.groupBy("bucket").applyInArrow(answer, _ANSWER), "counts")
    sums = asked.agg(F.sum("docs").alias("docs"), F.sum("tokens").alias("tokens")).first()
    store.drop(asked)
    train_docs, n_words = sums["docs"] or 0, sums["tokens"] or 0
    total = n_words + train_docs
    found = answers.agg(F.sum("known").alias("known"), F.sum("once").alias("once")).first()
    kinds = (found["known"] or 0) + (train_docs > 0)
    unknown = ((found["once"] or 0) + 0.5) / (total + 1.0)  # Good-Turing: what was seen once
    back = answers.groupBy("block").agg(F.collect_list(F.struct("bucket", "counts")).alias("answers"))  # as many as a block asked

    def finish(batches):
        low = total + 0.5 * (kinds + 1)
        for row in store.each_row(batches):
            b = Block(row)
            word, each = np.unique(b.words, return_inverse=True)
            order = np.argsort(_deal(word, buckets), kind="stable")
            count = np.zeros(len(word), np.int64)
            count[order] = np.concatenate([np.zeros(0, np.int32), *[store.unpack(x["counts"], np.int32) for x in sorted(row["answers"], key=lambda x: x["bucket"])]])
            c = count[each]
            n_docs = len(b.offsets) - 1
            doc = textops.doc_of(b.ptr)
            base = np.bincount(doc, np.log10((c + 0.5) / low), minlength=n_docs) + np.log10((train_docs + 0.5) / low)
            known = np.bincount(doc, c > 0, minlength=n_docs).astype(np.int64) + (train_docs > 0)
            symbols, offsets, tokens = b.symbols()
            gram, which = np.unique(grams(symbols, offsets, spec.depth), return_inverse=True)
            logs = np.zeros(len(gram))
            logs[np.argsort(_gram_bucket(gram, spec, buckets), kind="stable")] = np.concatenate([np.zeros(0, np.float32), *[store.unpack(x["logs"], np.float32) for x in sorted(row["spelt"], key=lambda x: x["bucket"])]])
            spelled = np.add.reduceat(logs[which], tokens) if n_docs else np.zeros(0)
            # a token seen in training: its share of the tokens mixed with its spelling
            count = np.empty(len(tokens))
            is_end = symbols[tokens] == END
            is_end[:-1] &= tokens[1:] == tokens[:-1] + 1
            count[is_end], count[~is_end] = train_docs, c
            share = (1 - spec.tree_share) * count / max(total, 1) + spec.tree_share * 10.0**spelled
            logs = np.where(count > 0, np.log10(np.maximum(share, 1e-300)) + np.log10(1 - unknown), np.log10(unknown))
            scored = np.bincount(np.repeat(np.arange(n_docs), np.diff(b.ptr) + 1), logs, minlength=n_docs)
            ids, has_id = store.unpack(row["ids"], np.int64), store.unpack(row["known"], bool)
            yield store.rows(
                _OUT, doc_id=pa.array(ids, pa.int64(), mask=~has_id), held_out=pa.array(b.held), n_tokens=pa.array(np.diff(b.ptr) + 1), n_known=pa.array(known),
                train_tokens=pa.array(np.full(n_docs, total)), base_score=pa.array(base), score=pa.array(scored),
            )

    return blocks.join(back, "block").join(spelt, "block").mapInArrow(finish, _OUT)
