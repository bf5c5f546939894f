"""Benchmark decontamination: rare n-gram seeds, then Smith-Waterman alignment.

Test items are cut into word n-grams. How many documents hold each n-gram is counted over
the whole table, and n-grams that are far commoner than their item's own median are no
seeds (an item that leaked everywhere keeps its seeds, as all of them are common alike).
Places where a seed stands in a document are grouped by item into passages, and each
passage is aligned with the item locally; the score is the alignment's share of a full
match, so edited, shortened and reworded copies are found.

Test items are a query set: they are sent to all tasks in blocks of at most ``block_chars``
characters (a checked bound), each block against every document.

Edge cases: null and empty texts match nothing; items shorter than a seed are compared by
their whole word sequence as one seed; ties keep every (document, item) pair; repeated rows
give repeated pairs; documents with a null id get rows with a null id.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import store, textops


@dataclass(frozen=True)
class LeakSpec:
    n: int = 3
    common: float = 20.0  # times its item's median count that make an n-gram no seed
    common_share: float = 1e-3  # of all documents, which it must exceed as well
    min_hits: int = 2
    threshold: float = 0.5
    match: int = 2
    mismatch: int = 1
    gap: int = 1
    block_chars: int = 8_000_000
    cells: int = 2_000_000  # of alignment tables held at once


class Items:
    """One block of test items: word hashes and seeds."""

    def __init__(self, ids: list, texts: list[str], n: int) -> None:
        self.ids = ids
        data, offsets = textops.column(pa.array(texts, pa.string()))
        data = textops.lower(data)
        starts, ends, ptr = textops.words(data, offsets, textops.ALNUM)
        w = textops.word_hashes(data, starts, ends)
        self.words = [w[a:b] for a, b in zip(ptr, ptr[1:])]
        hashes, item, at = [], [], []
        for i, x in enumerate(self.words):
            g = textops.gram_hashes(x, min(n, len(x))) if len(x) else x
            hashes.append(g)
            item.append(np.full(len(g), i))
            at.append(np.arange(len(g)))
        hashes, item, at = (np.concatenate(x) if x else np.zeros(0, np.int64) for x in (hashes, item, at))
        order = np.argsort(hashes, kind="stable")
        self.hash, self.item, self.at = hashes[order].astype(np.uint64), item[order], at[order]
        self.short = sorted({len(x) for x in self.words if 0 < len(x) < n})
        self.filter = np.zeros(1 << 20, bool)
        self.filter[self.hash & np.uint64((1 << 20) - 1)] = True

    def keep(self, mask: np.ndarray) -> None:
        self.hash, self.item, self.at = self.hash[mask], self.item[mask], self.at[mask]

    def hits(self, w: np.ndarray, ptr: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(document, word place in block, index of first equal seed) of all seed hits."""
        found = []
        for k in [*self.short, n]:
            g = textops.gram_hashes(w, k)
            maybe = np.flatnonzero(self.filter[g & np.uint64((1 << 20) - 1)])
            at = np.minimum(np.searchsorted(self.hash, g[maybe]), max(len(self.hash) - 1, 0))
            if not len(self.hash):
                continue
            same = self.hash[at] == g[maybe]
            place, at = maybe[same], at[same]
            doc = np.searchsorted(ptr, place, "right") - 1
            inside = place + k <= ptr[doc + 1]
            found.append((doc[inside], place[inside], at[inside]))
        return tuple(np.concatenate(x) for x in zip(*found)) if found else (np.zeros(0, np.int64),) * 3


def _block(data, offsets):
    data = textops.lower(data)
    starts, ends, ptr = textops.words(data, offsets, textops.ALNUM)
    return textops.word_hashes(data, starts, ends), ptr


def align(windows: list[np.ndarray], items: list[np.ndarray], spec: LeakSpec) -> tuple[np.ndarray, np.ndarray]:
    """Best local alignment score of each pair and the word after its end in the window.

    One row step per item word for all pairs at once; gaps along the window are resolved
    with a running maximum."""
    b, width, depth = len(windows), max(map(len, windows)), max(map(len, items))
    win = np.zeros((b, width), np.uint64)
    item = np.full((b, depth), 1, np.uint64)
    for i, (x, y) in enumerate(zip(windows, items, strict=True)):
        win[i, : len(x)] = x
        item[i, : len(y)] = y
    h = np.zeros((b, width + 1), np.int32)
    slope = np.arange(width + 1, dtype=np.int32) * spec.gap
    best, end = np.zeros(b, np.int32), np.zeros(b, np.int64)
    for j in range(depth):
        step = np.where(win == item[:, j : j + 1], spec.match, -spec.mismatch).astype(np.int32)
        new = np.zeros_like(h)
        new[:, 1:] = np.maximum(np.maximum(h[:, :-1] + step, h[:, 1:] - spec.gap), 0)
        h = np.maximum.accumulate(new + slope, axis=1) - slope
        top = h.argmax(axis=1)
        score = h[np.arange(b), top]
        better = score > best
        best[better], end[better] = score[better], top[better]
    return best, end


OUT = store.schema("doc_id long, item_id long, score double, n_hits long, first_word long, last_word long")


def _passages(doc, place, item, q, size) -> tuple[np.ndarray, ...]:
    """Group hits of one (document, item) that stand within an item's length: first and
    last index of each group in the sorted hits, and that order."""
    order = np.lexsort((place, item, doc))
    d, p, i = doc[order], place[order], item[order]
    new = np.ones(len(d), bool)
    new[1:] = (d[1:] != d[:-1]) | (i[1:] != i[:-1]) | (p[1:] - p[:-1] > size[i[1:]])
    first = np.flatnonzero(new)
    return order, first, np.append(first[1:], len(d)) - 1


def _search(items: Items, spec: LeakSpec, batches):
    size = np.array([len(x) for x in items.words], np.int64)
    need = np.minimum(spec.min_hits, np.maximum(1, size - spec.n + 1))
    for batch, data, offsets in textops.blocks(batches):
        w, ptr = _block(data, offsets)
        doc, place, at = items.hits(w, ptr, spec.n)
        # an n-gram may stand in several items
        many = np.searchsorted(items.hash, items.hash[at], "right") - at if len(at) else at
        seed = textops.ranges(at, many)
        doc, place = np.repeat(doc, many), np.repeat(place, many)
        item, q = items.item[seed], items.at[seed]
        order, first, last = _passages(doc, place, item, q, size)
        hits = last - first + 1
        keep = hits >= need[item[order[first]]] if len(first) else np.zeros(0, bool)
        first, last, hits = first[keep], last[keep], hits[keep]
        a, z = order[first], order[last]
        d, it = doc[a], item[a]
        lo = np.maximum(place[a] - size[it], ptr[d])
        hi = np.minimum(place[z] + size[it] + spec.n, ptr[d + 1])
        out = []
        todo = np.argsort(hi - lo, kind="stable")
        while len(todo):
            span = (hi - lo)[todo]
            k = max(1, int(np.searchsorted(span * np.arange(1, len(todo) + 1), spec.cells, "right")))
            part, todo = todo[:k], todo[k:]
            texts, words_ = [w[lo[x] : hi[x]] for x in part], [items.words[it[x]] for x in part]
            best, end = align(texts, words_, spec)
            share = best / (spec.match * size[it[part]])
            good = np.flatnonzero(share >= spec.threshold)
            if len(good):
                back, start = align([texts[g][: end[g]][::-1] for g in good], [words_[g][::-1] for g in good], spec)
                for g, s in zip(good.tolist(), start.tolist(), strict=True):
                    x = part[g]
                    zero = lo[x] - ptr[d[x]]
                    out.append((int(d[x]), int(it[x]), float(share[g]), int(hits[x]), int(zero + end[g] - s), int(zero + end[g] - 1)))
        best_of: dict[tuple[int, int], tuple] = {}
        for r in out:  # the best passage of a document and item; of equals, the first
            if (k := r[:2]) not in best_of or (r[2], -r[4]) > (best_of[k][2], -best_of[k][4]):
                best_of[k] = r
        if best_of:
            d_, i_, s_, n_, f_, l_ = zip(*best_of.values(), strict=True)
            yield store.rows(
                OUT, doc_id=batch.column(0).take(pa.array(d_)), item_id=pa.array([items.ids[i] for i in i_], pa.int64()), score=pa.array(s_),
                n_hits=pa.array(n_), first_word=pa.array(f_), last_word=pa.array(l_),
            )


_COUNT = store.schema("seed int, n long")


def _counts(docs: DataFrame, items: Items, spec: LeakSpec) -> tuple[np.ndarray, int]:
    """Documents that hold each seed, and all documents."""

    def run(batches):
        total, n = np.zeros(len(items.hash) + 1, np.int64), 0
        for batch, data, offsets in textops.blocks(batches):
            w, ptr = _block(data, offsets)
            doc, _, at = items.hits(w, ptr, spec.n)
            pair = np.unique(doc * (len(items.hash) + 1) + at)
            total += np.bincount(pair % (len(items.hash) + 1), minlength=len(total))
            n += batch.num_rows
        total[-1] = n
        some = np.flatnonzero(total)
        yield store.rows(_COUNT, seed=pa.array(some.astype(np.int32)), n=pa.array(total[some]))

    out = np.zeros(len(items.hash) + 1, np.int64)
    for r in docs.mapInArrow(run, _COUNT).groupBy("seed").agg(F.sum("n").alias("n")).collect():  # a row per seed of the block
        out[r["seed"]] = r["n"]
    return out[:-1], int(out[-1])


def _rare(items: Items, counts: np.ndarray, n_docs: int, spec: LeakSpec) -> np.ndarray:
    at = np.searchsorted(items.hash, items.hash)  # equal seeds are counted at the first
    c = counts[at]
    median = np.array([np.median(c[items.item == i]) if (items.item == i).any() else 0 for i in range(len(items.ids))])
    return ~((c > spec.common_share * n_docs) & (c > spec.common * np.maximum(1, median[items.item])))


def leaks(docs: DataFrame, benchmark: DataFrame, spec: LeakSpec = LeakSpec()) -> DataFrame:
    """(doc_id, item_id, score, n_hits, first_word, last_word) of every leaked item."""
    docs = store.documents(docs, "doc_id", "text")
    bench = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"))
    chars = bench.agg(F.sum(F.length("text"))).first()[0] or 0
    n_blocks = -(-chars // spec.block_chars) or 1
    out = None
    for k in range(n_blocks):
        part = bench.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(n_blocks)) == k).orderBy("item_id", "text").collect()
        items = Items([r["item_id"] for r in part], [r["text"] for r in part], spec.n)
        counts, n_docs = _counts(docs, items, spec)
        if len(items.hash):
            items.keep(_rare(items, counts, n_docs, spec))
        found = docs.mapInArrow(lambda batches, items=items: _search(items, spec, batches), OUT)
        out = found if out is None else out.unionByName(found)
    return out


def clean(docs: DataFrame, benchmark: DataFrame, spec: LeakSpec = LeakSpec()) -> DataFrame:
    """The documents in which no test item leaked."""
    bad = leaks(docs, benchmark, spec).select(F.col("doc_id").alias("_bad")).distinct()
    return docs.join(bad, docs["doc_id"] == bad["_bad"], "left_anti")
