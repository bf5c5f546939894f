"""Best-fit packing by length patterns.

Documents are tokenised whole and cut into pieces of at most a sequence's length. Only the
histogram of piece lengths (at most 1024 numbers) reaches the driver. There, patterns of
two or three lengths that fill a sequence exactly are enumerated, non-negative least squares
fits how often each is used, the counts are rounded down and the residual pieces are packed
best-fit, also as counts. The plan says which ranks of each length go to which sequences;
pieces get their rank from per-partition counts, so nothing is gathered anywhere.

Tokenising is exact and cheap: a byte-level BPE surely splits text at certain places (say,
a single space between visible characters), so distinct chunks are tokenised once each.

Edge cases: null texts are empty (their only token is the end id); an empty table packs
into nothing; repeated rows are separate documents; extra columns are ignored.
"""

from __future__ import annotations

import json
import os
import zlib
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import store, textops


@dataclass(frozen=True)
class PackSpec:
    tokenizer: str = ""  # path of the tokenizer file; empty: the public byte-level one
    capacity: int = 1024
    end_id: int = 2
    triples: int = 3000  # patterns of three lengths that enter the fit, commonest first
    sweeps: int = 60


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


#: how the byte-level vocabulary splits a text before merging (fixed value of the public tokenizer)
SPLIT = r"""'(?:[sdmt]|ll|ve|re)| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""


def _byte_letters() -> dict[str, int]:
    """The printable stand-ins that byte-level vocabularies write for bytes."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in plain]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


class ChunkTokenizer:
    """Token ids of whole texts from the ids of their distinct chunks.

    Chunks that are a space and letters can stand in any order without changing how a text
    splits, so all new ones of a block are encoded as one text; others one by one. Other
    kinds of tokenizers encode each text as it is."""

    #: distinct chunks remembered between blocks of a task; more only costs time
    REMEMBER = 1_200_000

    def __init__(self, path: str) -> None:
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.special = [t.content.encode() for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.fast = self._byte_level(path)
        self._forget()

    def _byte_level(self, path: str):
        """A merge engine for a byte-level vocabulary whose ids are its merge ranks, or None."""
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        split, model = spec.get("pre_tokenizer") or {}, spec["model"]
        if split.get("type") != "ByteLevel" or split.get("add_prefix_space") or not split.get("use_regex", True) or spec.get("normalizer") or model.get("type") != "BPE":
            return None
        import tiktoken

        letters, added = _byte_letters(), {t["id"] for t in spec.get("added_tokens", [])}
        ranks = {bytes(letters[c] for c in token): i for token, i in model["vocab"].items() if i not in added}
        self.size_of = np.zeros(max(ranks.values()) + 1, np.int64)
        self.size_of[list(ranks.values())] = [len(t) for t in ranks]
        return tiktoken.Encoding("chunks", pat_str=SPLIT, mergeable_ranks=ranks, special_tokens={})

    def _forget(self) -> None:
        self.hashes, self.start, self.size = np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64)
        self.ids = np.zeros(0, np.uint32)

    @staticmethod
    def letters(data: np.ndarray) -> np.ndarray:
        """True for bytes of ASCII and Latin-1 letters (two bytes, the first C3)."""
        low = data | np.uint8(32)
        out = (low >= 97) & (low <= 122)
        lead = data == 0xC3
        if lead.any():
            pair = np.zeros(len(data), bool)
            pair[:-1] = lead[:-1] & (data[1:] != 0x97) & (data[1:] != 0xB7)
            out |= pair
            out[1:] |= pair[:-1]
        return out

    @classmethod
    def cuts(cls, data: np.ndarray, offsets: np.ndarray, letter: np.ndarray) -> np.ndarray:
        """Where a text surely splits: documents, a single space or newline between visible
        characters (a newline also behind), and a letter before ASCII punctuation."""
        n = len(data)
        first = np.zeros(n, bool)
        first[offsets[:-1][offsets[:-1] < n]] = True
        visible = ((data > 32) & (data < 127)) | letter
        mark = visible & ~letter & ~((data >= 48) & (data <= 57))
        ok = first.copy()
        if n > 2:
            gap = np.zeros(n, bool)
            gap[1:-1] = ((data[1:-1] == 32) | (data[1:-1] == 10)) & visible[:-2] & visible[2:] & ~first[1:-1] & ~first[2:]
            ok |= gap
            ok[1:] |= gap[:-1] & (data[:-1] == 10)
            ok[1:] |= letter[:-1] & mark[1:]
        return np.flatnonzero(ok)

    def _learn(self, hashes: np.ndarray, raw: bytes, starts: np.ndarray, ends: np.ndarray, pure: np.ndarray) -> None:
        size, found = np.zeros(len(starts), np.int64), []
        order = np.concatenate([np.flatnonzero(pure), np.flatnonzero(~pure)])
        k = int(pure.sum())
        if k:
            chunks = [raw[a:b] for a, b in zip(starts[pure].tolist(), ends[pure].tolist(), strict=True)]
            ids = np.array(self.fast.encode_ordinary(b"".join(chunks).decode()), np.uint32)
            till = np.cumsum(self.size_of[ids])
            last = np.searchsorted(till, np.cumsum((ends - starts)[pure]))
            size[:k] = np.diff(np.concatenate([[-1], last]))
            found.append(ids)
        rest = [self.fast.encode_ordinary(raw[a:b].decode("utf-8", "replace")) for a, b in zip(starts[~pure].tolist(), ends[~pure].tolist(), strict=True)]
        size[k:] = [len(x) for x in rest]
        found.append(np.fromiter((x for f in rest for x in f), np.uint32))
        start = len(self.ids) + np.concatenate([[0], np.cumsum(size)[:-1]]).astype(np.int64) if len(size) else size
        hashes = np.concatenate([self.hashes, hashes[order]])
        by = np.argsort(hashes)
        self.hashes = hashes[by]
        self.start, self.size = np.concatenate([self.start, start])[by], np.concatenate([self.size, size])[by]
        self.ids = np.concatenate([self.ids, *found])

    def encode(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids, offsets by document) of a block."""
        raw = data.tobytes()
        if self.fast is None or any(s in raw for s in self.special):
            found = [self.tokenizer.encode(raw[a:b].decode("utf-8", "replace"), add_special_tokens=False).ids for a, b in zip(offsets, offsets[1:])]
            return np.fromiter((x for f in found for x in f), np.uint32), np.concatenate([[0], np.cumsum([len(f) for f in found])]).astype(np.int64)
        letter = self.letters(data)
        starts = self.cuts(data, offsets, letter)
        ends = np.append(starts[1:], len(data)) if len(starts) else starts
        unique, first, each = np.unique(textops.word_hashes(data, starts, ends), return_index=True, return_inverse=True)

        def unknown() -> np.ndarray:
            if not len(self.hashes):
                return np.ones(len(unique), bool)
            at = np.minimum(np.searchsorted(self.hashes, unique), len(self.hashes) - 1)
            return self.hashes[at] != unique

        new = unknown()
        if len(self.hashes) + new.sum() > self.REMEMBER:
            self._forget()
            new = unknown()
        if new.any():
            a, b = starts[first[new]], ends[first[new]]
            count = np.concatenate([[0], np.cumsum(letter)])
            pure = (data[a] == 32) & (count[b] - count[a] == b - a - 1) & (b - a > 1)
            self._learn(unique[new], raw, a, b, pure)
        at = np.searchsorted(self.hashes, unique)
        begin, size = self.start[at][each], self.size[at][each]
        total = np.concatenate([[0], np.cumsum(size)])
        return self.ids[textops.ranges(begin, size)], total[np.searchsorted(starts, offsets)]


PIECES = store.schema("doc_id long, piece int, start long, length long, ids_crc32 long, part int, place long")


def pieces(docs: DataFrame, spec: PackSpec = PackSpec()) -> DataFrame:
    """One row per piece, with its number among its partition's pieces of that length."""
    path = spec.tokenizer or default_tokenizer()

    def run(batches):
        tokenizer, part = ChunkTokenizer(path), TaskContext.get().partitionId()
        seen = np.zeros(spec.capacity + 1, np.int64)
        for batch, data, offsets in textops.blocks(batches):
            ids, ptr = tokenizer.encode(data, offsets)
            n = np.diff(ptr) + 1  # with the end id
            count = -(-n // spec.capacity)
            doc = np.repeat(np.arange(len(n)), count)
            piece = textops.ranges(np.zeros(len(n), np.int64), count)
            head = n - (count - 1) * spec.capacity
            length = np.where(piece == 0, head[doc], spec.capacity)
            start = np.where(piece == 0, 0, head[doc] + (piece - 1) * spec.capacity)
            end_id = np.uint32(spec.end_id).tobytes()
            crc = []
            for d, s, m, last in zip(doc.tolist(), start.tolist(), length.tolist(), (piece == count[doc] - 1).tolist(), strict=True):
                at = int(ptr[d]) + s
                x = zlib.crc32(ids[at : at + m - last].astype("<u4").tobytes())
                crc.append(zlib.crc32(end_id, x) if last else x)
            order = np.argsort(length, kind="stable")
            sizes, begin, many = np.unique(length[order], return_index=True, return_counts=True)
            place = np.empty(len(length), np.int64)
            place[order] = np.arange(len(length)) - np.repeat(begin, many) + np.repeat(seen[sizes], many)
            seen[sizes] += many
            yield store.rows(
                PIECES, doc_id=batch.column(0).take(pa.array(doc)), piece=pa.array(piece.astype(np.int32)), start=pa.array(start), length=pa.array(length),
                ids_crc32=pa.array(crc, pa.int64()), part=pa.array(np.full(len(doc), part, np.int32)), place=pa.array(place),
            )

    return store.documents(docs, "doc_id", "text").mapInArrow(run, PIECES)


def patterns(histogram: dict[int, int], capacity: int, triples: int) -> list[tuple[int, ...]]:
    """Patterns of one, two and three present lengths that fill a sequence exactly."""
    have = set(histogram)
    out: list[tuple[int, ...]] = [(capacity,)] if capacity in have else []
    out += [(a, capacity - a) for a in sorted(have) if capacity - a in have and capacity - a <= a < capacity]
    common = sorted(have, key=lambda n: (-histogram[n], n))
    found: list[tuple[int, ...]] = []
    for i, a in enumerate(common):
        for b in common[: i + 1]:
            c = capacity - a - b
            if c in have and c > 0 and (histogram[c], -c) >= (histogram[a], -a):
                found.append(tuple(sorted((a, b, c), reverse=True)))
        if len(found) >= 4 * triples:
            break
    return out + list(dict.fromkeys(found))[:triples]


def fit(chosen: list[tuple[int, ...]], histogram: dict[int, int], sweeps: int) -> np.ndarray:
    """Non-negative least squares of pattern counts to the histogram, by coordinates."""
    use = [Counter(p) for p in chosen]
    left = dict(histogram)
    x = np.zeros(len(chosen))
    for _ in range(sweeps):
        moved = 0.0
        for j, c in enumerate(use):
            step = sum(left[n] * k for n, k in c.items()) / sum(k * k for k in c.values())
            step = max(step, -x[j])
            if step:
                x[j] += step
                for n, k in c.items():
                    left[n] -= step * k
                moved = max(moved, abs(step))
        if moved < 0.25:
            break
    return x


def plan(histogram: dict[int, int], spec: PackSpec) -> list[tuple[tuple[int, ...], int]]:
    """(lengths in a sequence, number of such sequences), covering the histogram."""
    left = {n: k for n, k in histogram.items() if k}
    chosen = patterns(left, spec.capacity, spec.triples)
    x = fit(chosen, left, spec.sweeps)
    out: Counter = Counter()
    for j in sorted(range(len(chosen)), key=lambda j: (-x[j], j)):
        c = Counter(chosen[j])
        k = min(int(x[j] + 1e-9), *(left[n] // m for n, m in c.items()))
        if k > 0:
            out[chosen[j]] += k
            for n, m in c.items():
                left[n] -= k * m
    # residual pieces: best fit by falling length, on counts of equal bins
    bins: dict[int, Counter] = {}
    for n in sorted((n for n, k in left.items() if k), reverse=True):
        todo = left[n]
        while todo:
            room = min((r for r in bins if r >= n), default=None)
            if room is None:
                fits = spec.capacity // n
                full, rest = divmod(todo, fits)
                for copies, bins_made in ((fits, full), (rest, 1)):
                    if copies and bins_made:
                        bins.setdefault(spec.capacity - n * copies, Counter())[(n,) * copies] += bins_made
                break
            held, count = next(iter(bins[room].items()))
            k = min(todo, count)
            bins[room][held] -= k
            if count == k:
                del bins[room][held]
            bins.setdefault(room - n, Counter())[(*held, n)] += k
            todo -= k
            if not bins[room]:
                del bins[room]
    for group in bins.values():
        for p, k in group.items():
            if k:
                out[p] += k
    return sorted(out.items(), reverse=True)


PACKED = store.schema("doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")


def pack(docs: DataFrame, spec: PackSpec = PackSpec()) -> DataFrame:
    """Where every piece goes: sequence_id and offset, beside the piece's own columns."""
    found = store.settle(pieces(docs, spec), "pieces")
    each = found.groupBy("part", "length").agg(F.count(F.lit(1)).alias("n"))
    before = W.partitionBy("length").orderBy("part").rowsBetween(W.unboundedPreceding, -1)
    base = each.withColumn("base", F.coalesce(F.sum("n").over(before), F.lit(0)))
    histogram = {r["length"]: r["n"] for r in each.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # at most ``capacity`` rows
    starts, firsts, offsets = _slots(plan(histogram, spec))

    def place(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            get = {n: batch.column(i) for i, n in enumerate(batch.schema.names)}
            rank = get["place"].to_numpy() + get["base"].to_numpy()
            key = (get["length"].to_numpy() << 48) + rank
            at = np.searchsorted(starts, key, "right") - 1
            columns = {n: get[n] for n in ("doc_id", "piece", "start", "length", "ids_crc32")}
            yield store.rows(PACKED, **columns, sequence_id=pa.array(firsts[at] + key - starts[at]), offset=pa.array(offsets[at]))

    return found.join(base.select("part", "length", "base"), ["part", "length"]).mapInArrow(place, PACKED)


def _slots(chosen: list[tuple[tuple[int, ...], int]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For each run of ranks of a length: its first (length, rank) key, the sequence of that
    first rank, and the piece's offset in its sequence; sorted by key."""
    used: Counter = Counter()
    rows, first = [], 0
    for lengths, k in chosen:
        offset = 0
        for n in lengths:
            rows.append(((n << 48) + used[n], first, offset))
            used[n] += k
            offset += n
        first += k
    table = np.array(sorted(rows), np.int64).reshape(-1, 3)
    return table[:, 0], table[:, 1], table[:, 2]
