"""The same sketches in DuckDB SQL, as oracles: hashes in 128-bit integers modulo 2**64."""

from __future__ import annotations

from ..functions import hashing

M = str(1 << 64)


def mixed(source: str, key: str, columns: str = "", seed: int = 0, seed_sql: str = "") -> str:
    """SELECT columns..., h from ``source``: the mix of the integer expression ``key``."""
    cols = f"{columns}, " if columns else ""
    names = ", ".join(c.split(" AS ")[-1].strip() for c in columns.split(",")) + ", " if columns else ""
    word = (seed * hashing.SEED_STEP) % (1 << 64)
    start = f"xor(CAST(k AS UBIGINT), CAST({seed_sql or word} AS UBIGINT))" if seed or seed_sql else "k"
    carry = "seed, " if seed_sql else ""

    def fold(n: int) -> str:
        return f"CAST(xor(CAST(k AS UBIGINT), CAST(k // {1 << n} AS UBIGINT)) AS HUGEINT)"

    q = f"SELECT {cols}{carry}CASE WHEN CAST({key} AS HUGEINT) < 0 THEN CAST({key} AS HUGEINT) + {M} ELSE CAST({key} AS HUGEINT) END AS k FROM {source} WHERE {key} IS NOT NULL"
    for e in (f"CAST({start} AS HUGEINT)", f"({int(M) - 1} - k + k * {1 << 21}) % {M}", fold(24), f"(k * 265) % {M}", fold(14), f"(k * 21) % {M}", fold(28), f"(k + k * {1 << 31}) % {M}"):
        q = f"SELECT {names}{carry}{e} AS k FROM ({q})"
    return f"SELECT {names}{carry}k AS h FROM ({q})"


RANK = "CASE WHEN h = 0 THEN 62 ELSE least(62, 64 - length(bin(CAST(h AS UBIGINT)))) END"


def hashed(source: str, key: str, columns: str = "", registers: int = 1408, seed: int = 0, seed_sql: str = "") -> str:
    names = ", ".join(c.split(" AS ")[-1].strip() for c in columns.split(",")) + ", " if columns else ""
    carry = "seed, " if seed_sql else ""
    return f"SELECT {names}{carry}h, CAST(h % {registers} AS INT) AS bucket, CAST({RANK} AS INT) AS z FROM ({mixed(source, key, columns, seed, seed_sql)})"


def bitmaps(source: str, key: str, columns: str = "", registers: int = 1408, seed: int = 0) -> str:
    names = ", ".join(c.split(" AS ")[-1].strip() for c in columns.split(",")) + ", " if columns else ""
    return f"SELECT {names}bucket, bit_or(CAST(1 AS BIGINT) << z) AS bitmap FROM ({hashed(source, key, columns, registers, seed)}) GROUP BY {names}bucket"


def levels(bitmaps_: str) -> str:
    z = "(length(bin(bitmap)) - 1)"
    return (
        f"SELECT *, CAST({z} AS INT) AS zmax, CAST((CASE WHEN {z} >= 1 THEN 2 * ((bitmap >> greatest({z} - 1, 0)) & 1) ELSE 0 END)"
        f" + (CASE WHEN {z} >= 2 THEN (bitmap >> greatest({z} - 2, 0)) & 1 ELSE 0 END) AS INT) AS hist FROM ({bitmaps_})"
    )


def histogram(bitmaps_: str, by: str = "") -> str:
    cols = f"{by}, " if by else ""
    return f"SELECT {cols}zmax AS z, hist, count(*) AS n FROM ({levels(bitmaps_)}) GROUP BY {cols}zmax, hist"


def text_key(expression: str) -> str:
    """60 bits of MD5 of a text as an integer."""
    return f"CAST(('0x' || substr(md5({expression}), 1, 15)) AS BIGINT)"


def parts(*columns: str) -> str:
    """The text of a composite key: every part with its length, ~ for a null."""
    return " || ".join(f"coalesce(length(CAST({c} AS VARCHAR)) || ':' || {c}, '~')" for c in columns)
