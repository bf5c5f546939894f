"""Vectorised text kernels shared by the training-data operators.

Every kernel works on one *block*: the UTF-8 bytes of a run of documents laid end to
end plus their offsets, exactly the layout of an Arrow string column. Words, n-gram
hashes and minimisers are computed with whole-array NumPy calls, so a Python worker
touches each byte a handful of times and never loops over words.

Null texts are read as empty. Blocks are cut by bytes (``blocks``), so a worker's
memory follows the block size or the longest single document, never the table.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: just under a power of two, as tables of powers double
BLOCK_BYTES = (4 << 20) - 4096

_U = np.uint64
_rng = np.random.default_rng(20240607)
_BYTE = _rng.integers(1, 2**63, 256, dtype=np.uint64) | _U(1)
_BASE = 0x9E3779B97F4A7C15 | 1
_BASE_INV = pow(_BASE, -1, 1 << 64)
_pow = np.ones(1, np.uint64)
_inv = np.ones(1, np.uint64)


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers 0..n-1 of the hash base and of its inverse modulo 2**64."""
    global _pow, _inv
    if len(_pow) < n:
        size = 1 << (n - 1).bit_length()
        for_base = np.full(size, _BASE, np.uint64)
        for_inv = np.full(size, _BASE_INV, np.uint64)
        for_base[0] = for_inv[0] = 1
        _pow, _inv = np.cumprod(for_base), np.cumprod(for_inv)
    return _pow[:n], _inv[:n]


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (xor-shift and multiply), applied elementwise."""
    x = x ^ (x >> _U(30))
    x = x * _U(0xBF58476D1CE4E5B9)
    x ^= x >> _U(27)
    x *= _U(0x94D049BB133111EB)
    x ^= x >> _U(31)
    return x


def table_of(separators: bytes) -> np.ndarray:
    """True for bytes that belong to a word."""
    inside = np.ones(256, bool)
    inside[list(separators)] = False
    return inside


#: words are runs of anything but space and \t..\r
SPACED = table_of(b" \t\n\x0b\x0c\r")
#: words are runs of digits, lower-case letters and all non-ASCII bytes
ALNUM = table_of(bytes([*range(0x00, 0x30), *range(0x3A, 0x61), *range(0x7B, 0x80)]))

_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


def lower(data: np.ndarray) -> np.ndarray:
    """A-Z to a-z; every other byte is unchanged."""
    return _LOWER[data]


def column(col) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of an Arrow string or binary column; nulls count as empty."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    kind = pa.large_binary() if pa.types.is_binary(col.type) or pa.types.is_large_binary(col.type) else pa.large_string()
    col = col.cast(kind)
    if col.null_count:
        col = pc.fill_null(col, b"" if kind == pa.large_binary() else "")
    _, off, dat = col.buffers()
    offsets = np.frombuffer(off, np.int64)[col.offset : col.offset + len(col) + 1] if len(col) else np.zeros(1, np.int64)
    data = np.frombuffer(dat, np.uint8) if dat is not None else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def blocks(batches, limit: int = BLOCK_BYTES, text: str = "text", rows: int = 1 << 30) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """Cut record batches into (rows, bytes, offsets) of about ``limit`` text bytes."""
    for batch in batches:
        if not batch.num_rows:
            continue
        data, offsets = column(batch.column(batch.schema.get_field_index(text)))
        start, n = 0, batch.num_rows
        while start < n:
            stop = int(np.searchsorted(offsets, offsets[start] + limit, "right")) - 1
            stop = min(max(stop, start + 1), start + rows, n)
            lo, hi = offsets[start], offsets[stop]
            yield batch.slice(start, stop - start), data[lo:hi], offsets[start : stop + 1] - lo
            start = stop


def words(data: np.ndarray, offsets: np.ndarray, inside: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Byte starts and ends of all words, and each document's first word index (n+1)."""
    if not len(data):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(offsets), np.int64)
    m = inside[data]
    first = m.copy()
    first[1:] &= ~m[:-1]
    cut = offsets[:-1][offsets[:-1] < len(data)]
    first[cut] |= m[cut]
    last = m.copy()
    last[:-1] &= ~m[1:]
    cut = offsets[1:][offsets[1:] > 0] - 1
    last[cut] |= m[cut]
    starts, ends = np.flatnonzero(first), np.flatnonzero(last) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def prefix_hash(data: np.ndarray) -> np.ndarray:
    """Running polynomial hash; with ``span_hash`` any substring hashes in O(1)."""
    out = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(_BYTE[data] * _powers(len(data) + 1)[0][:-1], out=out[1:])
    return out


def span_hash(running: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hashes of the substrings [start, end)."""
    inv = _powers(len(running))[1]
    h = (running[ends] - running[starts]) * inv[starts]
    return mix(h + (ends - starts).astype(np.uint64) * _U(0xD6E8FEB86659FD93))


def byte_grams(data: np.ndarray, k: int) -> np.ndarray:
    """Hash of each run of k bytes (len(data)-k+1 of them)."""
    n = len(data) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    running = prefix_hash(data)
    h = running[k:] - running[:n]
    h *= _powers(len(running))[1][:n]
    return mix(h)


def word_hashes(data, starts, ends) -> np.ndarray:
    return span_hash(prefix_hash(data), starts, ends)


def gram_hashes(w: np.ndarray, k: int) -> np.ndarray:
    """Hash of each run of k consecutive word hashes (len(w)-k+1 of them)."""
    n = len(w) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    h = np.zeros(n, np.uint64)
    for i in range(k):
        h *= _U(0x9FB21C651E98DF25)
        h += w[i : i + n]
    return mix(h)


def in_document(ptr: np.ndarray, n: int, k: int) -> np.ndarray:
    """For n grams of k items: True where the gram does not cross a document boundary."""
    doc = doc_of(ptr)
    if n <= 0:
        return np.zeros(0, bool)
    return doc[:n] == doc[k - 1 : k - 1 + n]


def doc_of(ptr: np.ndarray) -> np.ndarray:
    """Document row of each item, from the items' pointers."""
    return np.repeat(np.arange(len(ptr) - 1), np.diff(ptr))


def sliding(x: np.ndarray, w: int, op) -> np.ndarray:
    """op (np.minimum or np.maximum) over each run of w values, by doubling."""
    out, have = x, 1
    while have < w:
        step = min(have, w - have)
        out = op(out[: len(out) - step], out[step:])
        have += step
    return out


def minimisers(h: np.ndarray, ok: np.ndarray, w: int) -> np.ndarray:
    """Positions that hold the least hash of some window of w consecutive valid grams.

    Two equal runs of w grams select the same positions, so a repeat that is at least
    w grams long always shares a selected gram. Grams with ``ok`` False belong to no
    window (they cross a document boundary)."""
    n = len(h)
    if n < w:
        return np.zeros(0, np.int64)
    good = sliding(ok, w, np.logical_and)
    low = sliding(h, w, np.minimum)
    low = np.where(good, low, _U(0))
    pad = np.zeros(w - 1, np.uint64)
    high = sliding(np.concatenate([pad, low, pad]), w, np.maximum)
    return np.flatnonzero((high == h) & ok & (h > 0))


def ranges(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Concatenation of arange(start, start+length) for all pairs."""
    total = int(lengths.sum())
    if not total:
        return np.zeros(0, np.int64)
    out = np.repeat(starts - np.concatenate([[0], np.cumsum(lengths)[:-1]]), lengths)
    return out + np.arange(total)


def runs(mask: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the maximal True runs."""
    if not len(mask):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    edge = np.diff(np.concatenate([[0], mask.view(np.int8), [0]]))
    return np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
