"""Register states and their packing: eleven base-56 digits in a 64-bit word.

A state holds a register's highest rank above the shared floor (0 empty, at most 18) and,
for ranks up to 13, which of the two ranks below it were seen. Tiers 1 and 2 have fewer
possible histories at floor -1, but keep their slots: state numbers are
0 | 1,2 (tier 1: history of one bit) | four per tier 2..13 | one per tier 14..18.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

RADIX = 56
DIGITS = 11
HISTORY_LIMIT = 13
MAX_EXPONENT = 18
MARGIN = 2


def registers_for(memory_bytes: int) -> int:
    """Registers of a sketch of so many bytes, in whole words of eleven."""
    return memory_bytes // 8 * DIGITS


def words_for(registers: int) -> int:
    return -(-registers // DIGITS)


def round_up(registers: int) -> int:
    return words_for(registers) * DIGITS


def state_of(r: Column, high: Column, low: Column) -> Column:
    """State from the exponent above the floor and the two history bits (integers)."""
    r = F.least(r, F.lit(MAX_EXPONENT))
    return (
        F.when(r <= 0, 0)
        .when(r == 1, 1 + high)
        .when(r <= HISTORY_LIMIT, 3 + (r - 2) * 4 + 2 * high + low)
        .otherwise(r - HISTORY_LIMIT - 1 + 51)
        .cast("int")
    )


def exponent_of(s: Column) -> Column:
    return F.when(s == 0, 0).when(s < 3, 1).when(s < 51, F.floor((s - 3) / 4) + 2).otherwise(s - 51 + HISTORY_LIMIT + 1).cast("int")


def history_of(s: Column) -> Column:
    return F.when(s == 0, 0).when(s < 3, (s - 1) * 2).when(s < 51, (s - 3) % 4).otherwise(0).cast("int")


def bit_at(bitmap: Column, k: Column) -> Column:
    """Bit k of a bitmap; 0 below bit 0."""
    return F.when(k < 0, 0).otherwise(F.call_function("shiftrightunsigned", bitmap, F.greatest(k, F.lit(0)).cast("int")).bitwiseAND(1)).cast("int")


def state_from_bitmap(bitmap: Column, z: Column, floor: Column) -> Column:
    """State of a register from its level bitmap, its highest rank (-1: empty) and the floor."""
    r = F.greatest(z - floor, F.lit(0))
    return state_of(F.when(z < 0, 0).otherwise(r), F.when(z - 1 >= floor, bit_at(bitmap, z - 1)).otherwise(0), F.when(z - 2 >= floor, bit_at(bitmap, z - 2)).otherwise(0))


# NumPy twins -----------------------------------------------------------------------------

_S = np.arange(RADIX)
EXPONENT = np.where(_S == 0, 0, np.where(_S < 3, 1, np.where(_S < 51, (_S - 3) // 4 + 2, _S - 51 + HISTORY_LIMIT + 1)))
HISTORY = np.where(_S == 0, 0, np.where(_S < 3, (_S - 1) * 2, np.where(_S < 51, (_S - 3) % 4, 0)))
POWERS = np.array([RADIX**i for i in range(DIGITS)], np.uint64)


def states_np(r: np.ndarray, history: np.ndarray) -> np.ndarray:
    r = np.minimum(r, MAX_EXPONENT)
    return np.where(r <= 0, 0, np.where(r == 1, 1 + history // 2, np.where(r <= HISTORY_LIMIT, 3 + (r - 2) * 4 + history, r - HISTORY_LIMIT - 1 + 51)))


def pack(states: np.ndarray) -> np.ndarray:
    """Words (as signed longs) of states, eleven each, the first digit lowest."""
    padded = np.zeros(words_for(len(states)) * DIGITS, np.uint64)
    padded[: len(states)] = states
    return (padded.reshape(-1, DIGITS) * POWERS).sum(1, dtype=np.uint64).view(np.int64)


def unpack(words: np.ndarray, registers: int) -> np.ndarray:
    w = np.asarray(words, np.int64).view(np.uint64)
    return (w[:, None] // POWERS % np.uint64(RADIX)).ravel()[:registers].astype(np.int64)


def read_digit(words: np.ndarray, register: int) -> int:
    w = int(np.asarray(words, np.int64).view(np.uint64)[register // DIGITS])
    return w // RADIX ** (register % DIGITS) % RADIX


def replace_digit(words: np.ndarray, register: int, state: int) -> None:
    """Change one digit in place by adding the difference times its power."""
    view = np.asarray(words, np.int64).view(np.uint64)
    at = register // DIGITS
    view[at] = np.uint64(int(view[at]) + (state - read_digit(words, register)) * RADIX ** (register % DIGITS))


def promote(states: np.ndarray, floor: int) -> tuple[np.ndarray, int]:
    """Raise the floor while every register stands above its margin; each step lowers all
    exponents by one and keeps histories (a tier without history comes down without)."""
    r, h = EXPONENT[states], HISTORY[states]
    step = max(0, int(r.min(initial=MAX_EXPONENT)) - MARGIN) if len(states) else 0
    if step:
        had = (states >= 51) | (states == 0)
        r = r - step
        states = states_np(r, np.where(had, 0, h))
        floor += step
    return states, floor
