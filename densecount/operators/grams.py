"""Bitmaps of all substrings of texts, in NumPy: MD5 keys, mix, registers.

A text of n characters has as many substrings of each length, so each costs no object: the
bytes stand in one array, MD5 runs over columns of words, and every task keeps one table of
levels seen per group, which is all that leaves it.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import hashing

LEVELS = 64
#: bytes of text looked at together, hashes computed together, groups held by a task
PIECE, LANES, GROUPS = 1 << 19, 1 << 15, 1 << 5
#: slots of the substrings last marked, of those of up to eight bytes
SLOTS = 18

_SINES = np.floor(np.abs(np.sin(np.arange(64) + 1.0)) * 2.0**32).astype(np.uint64).astype(np.uint32)
_TURNS = [x for four in ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)) for x in four * 4]
_WORDS = [*range(16)] + [(5 * i + 1) % 16 for i in range(16)] + [(3 * i + 5) % 16 for i in range(16)] + [7 * i % 16 for i in range(16)]
_START = np.array([0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476], np.uint32)


def _md5_block(state: list[np.ndarray], words: list) -> list[np.ndarray]:
    """One block of MD5: ``words`` are arrays, or integers where all lanes are alike."""
    a, b, c, d = (x.copy() for x in state)
    f, g = np.empty_like(a), np.empty_like(a)
    for i in range(64):
        if i < 16:
            np.bitwise_xor(c, d, out=f), np.bitwise_and(f, b, out=f), np.bitwise_xor(f, d, out=f)
        elif i < 32:
            np.bitwise_xor(b, c, out=f), np.bitwise_and(f, d, out=f), np.bitwise_xor(f, c, out=f)
        elif i < 48:
            np.bitwise_xor(b, c, out=f), np.bitwise_xor(f, d, out=f)
        else:
            np.invert(d, out=f), np.bitwise_or(f, b, out=f), np.bitwise_xor(f, c, out=f)
        word, fixed = words[_WORDS[i]], int(_SINES[i])
        if isinstance(word, int):
            fixed = (fixed + word) & 0xFFFFFFFF
        else:
            np.add(f, word, out=f)
        np.add(f, a, out=f), np.add(f, np.uint32(fixed), out=f)
        np.right_shift(f, np.uint32(32 - _TURNS[i]), out=g), np.left_shift(f, np.uint32(_TURNS[i]), out=f), np.bitwise_or(f, g, out=f)
        np.add(f, b, out=a)
        a, b, c, d = d, a, b, c
    return [x + y for x, y in zip(state, (a, b, c, d), strict=True)]


def _md5_key(four: np.ndarray, at: np.ndarray, size: int) -> np.ndarray:
    """The first 60 bits of the MD5 of the ``size`` bytes at each of the places ``at``;
    ``four[p]`` is the little-endian word of the bytes from p."""
    blocks = (size + 8) // 64 + 1
    words: list = [0] * (16 * blocks)
    for j in range(size // 4):
        words[j] = four[at + 4 * j]
    rest = size % 4
    words[size // 4] = (four[at + size - rest] & np.uint32((1 << 8 * rest) - 1)) | np.uint32(0x80 << 8 * rest) if rest else 0x80
    words[16 * blocks - 2] = 8 * size
    state = [np.full(len(at), x, np.uint32) for x in _START]
    for k in range(blocks):
        state = _md5_block(state, words[16 * k : 16 * k + 16])
    high, low = (x.byteswap().astype(np.uint64) for x in state[:2])
    return ((high << np.uint64(32)) | low) >> np.uint64(4)


def _mark(seen: np.ndarray, key: np.ndarray, registers: int) -> None:
    h = hashing.mix64_np(key.view(np.int64))
    bucket = h - h // np.uint64(registers) * np.uint64(registers)
    top = h >> np.uint64(11)  # exact as a double, whose exponent is the place of the highest bit
    z = np.uint64(52 + 1023) - (top.astype(np.float64).view(np.uint64) >> np.uint64(52))
    few = np.flatnonzero(top == 0)
    z[few] = hashing.rank_np(h[few]).astype(np.uint64)
    seen[(bucket * np.uint64(LEVELS) + z).astype(np.int64)] = True


def slots() -> np.ndarray:
    return np.full(1 << SLOTS, (1 << 64) - 1, np.uint64)  # no UTF-8


def _unmarked(last: np.ndarray, four: np.ndarray, at: np.ndarray, size: int) -> np.ndarray:
    """The places whose substring is not in its slot of ``last``, where it then is. Short
    substrings come again and again; those left out are marked already."""
    word = four[at].astype(np.uint64)
    if size > 4:
        word |= four[at + 4].astype(np.uint64) << np.uint64(32)
    word &= np.uint64((1 << 8 * size) - 1)
    slot = ((word * np.uint64(hashing.SEED_STEP)) >> np.uint64(64 - SLOTS)).astype(np.int64)
    new = last[slot] != word
    last[slot[new]] = word[new]
    return at[new]


def mark_all(seen: dict[int, np.ndarray], last: dict[int, np.ndarray], data: np.ndarray, ends: np.ndarray, registers: int) -> None:
    """Mark in ``seen[k]`` the levels of all substrings of k characters of the texts that
    stand in ``data`` (UTF-8) one after the other, each up to its place in ``ends``. ``last[k]``
    goes with ``seen[k]`` and begins as ``slots()``."""
    place = np.flatnonzero((data & 0xC0) != 0x80)  # where characters begin
    place = np.append(place, len(data))
    until = np.searchsorted(place, ends)  # the number of the character at which each text ends
    stop = np.repeat(until, np.diff(until, prepend=0))  # of each character's text
    n, padded = len(data) + 1, np.append(data, np.zeros(4, np.uint8)).astype(np.uint32)
    four = padded[:n] | padded[1 : n + 1] << np.uint32(8) | padded[2 : n + 2] << np.uint32(16) | padded[3:] << np.uint32(24)
    for k, table in seen.items():
        first = np.flatnonzero(np.arange(len(stop)) + k <= stop)
        at, size = place[first], place[first + k] - place[first]
        for bytes_ in np.unique(size):
            some = at[size == bytes_]
            if bytes_ <= 8:
                some = np.concatenate([_unmarked(last[k], four, some[i : i + LANES], int(bytes_)) for i in range(0, len(some), LANES)])
            for i in range(0, len(some), LANES):
                _mark(table, _md5_key(four, some[i : i + LANES], int(bytes_)), registers)


def _pieces(data: np.ndarray, offsets: np.ndarray, rows: np.ndarray, most: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(bytes, ends) of the texts ``rows`` in pieces of about PIECE bytes. A longer text comes
    in parts that share ``most`` characters at least: what is marked twice changes nothing."""
    held, size = [], 0
    for r in rows:
        text = data[offsets[r] : offsets[r + 1]]
        at = 0
        while True:
            end = at + PIECE
            while end < len(text) and text[end] & 0xC0 == 0x80:
                end += 1
            held.append(text[at:end])
            size += len(held[-1])
            if size >= PIECE:
                yield np.concatenate(held), np.cumsum([len(x) for x in held])
                held, size = [], 0
            if end >= len(text):
                break
            at = end - 4 * most
            while text[at] & 0xC0 == 0x80:
                at -= 1
    if size:
        yield np.concatenate(held), np.cumsum([len(x) for x in held])


def substring_bitmaps(texts: DataFrame, group: str, text: str, sizes: tuple[int, ...], registers: int) -> DataFrame:
    """(g: (group, n), bucket, bitmap): bitmaps of all substrings of n characters, for each of
    the ``sizes``, as ``register_bitmaps`` makes them of MD5 keys."""

    def rows(tables: dict) -> pa.RecordBatch:
        out = ([], [], [], [])
        weight = np.left_shift(np.int64(1), np.arange(LEVELS - 1, dtype=np.int64))
        for name, seen in tables.items():
            for k, table in seen.items():
                bitmap = table.reshape(registers, LEVELS)[:, : LEVELS - 1] @ weight
                filled = np.flatnonzero(bitmap)
                for column, x in zip(out, ([name] * len(filled), [k] * len(filled), filled, bitmap[filled]), strict=True):
                    column.extend(x)
        kinds = (pa.string(), pa.int32(), pa.int32(), pa.int64())
        return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(out, kinds, strict=True)], ["name", "n", "bucket", "bitmap"])

    def run(batches):
        tables: dict = {}
        last: dict = {}
        for batch in batches:
            names, column = batch.column(0).to_pylist(), batch.column(1).cast(pa.large_string())
            _, offsets, data = column.buffers()
            offsets = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
            data = np.frombuffer(data, np.uint8) if data else np.zeros(0, np.uint8)
            by: dict = {}
            for i, name in enumerate(names):
                by.setdefault(name, []).append(i)
            for name, where in by.items():
                if name not in tables:
                    if len(tables) >= GROUPS:
                        yield rows(tables)
                        tables, last = {}, {}
                    tables[name] = {k: np.zeros(registers * LEVELS, bool) for k in sizes}
                    last[name] = {k: slots() for k in sizes if k <= 8}
                for piece, ends in _pieces(data, offsets, np.array(where), max(sizes)):
                    mark_all(tables[name], last[name], piece, ends, registers)
        yield rows(tables)

    given = texts.select(F.col(group).cast("string"), F.col(text).cast("string")).where(F.col(text).isNotNull())
    parts = given.mapInArrow(run, "name string, n int, bucket int, bitmap long")
    return parts.groupBy(F.struct(F.col("name").alias(group), "n").alias("g"), "bucket").agg(F.bit_or("bitmap").alias("bitmap"))
