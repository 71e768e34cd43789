"""System states as bit words, 62 components a word: columns and their NumPy twins."""

from __future__ import annotations

from math import comb

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

WORD = 62


def n_words(n: int) -> int:
    return max(1, -(-n // WORD))


# --- columns over ARRAY<BIGINT> -------------------------------------------------------------


def bit(words: Column, d) -> Column:
    """State of component d (0-based)."""
    d = d if isinstance(d, Column) else F.lit(d)
    word = F.element_at(words, (F.floor(d / WORD) + 1).cast("int"))
    return F.call_function("shiftrightunsigned", word, (d % WORD).cast("int")).bitwiseAND(F.lit(1).cast("long")).cast("int")


def popcount(words: Column) -> Column:
    return F.aggregate(words, F.lit(0), lambda s, w: s + F.bit_count(w))


def contains(x: Column, y: Column) -> Column:
    """Does x fail wherever y fails?"""
    return F.forall(F.zip_with(x, y, lambda a, b: a.bitwiseAND(b) == b), lambda t: t)


def members(words: Column, n: int) -> Column:
    """Failed components of a state, ascending."""
    return F.filter(F.sequence(F.lit(0), F.lit(n - 1)), lambda d: bit(words, d) == 1)


# --- NumPy: words[W, B] -----------------------------------------------------------------------


def pack(failed: np.ndarray) -> np.ndarray:
    """failed[n, B] to words[W, B]."""
    n, b = failed.shape
    out = np.zeros((n_words(n), b), np.int64)
    for d in range(n):
        out[d // WORD] |= failed[d].astype(np.int64) << (d % WORD)
    return out


def unpack(words: np.ndarray, n: int) -> np.ndarray:
    """words[W, B] to failed[n, B]."""
    return np.stack([(words[d // WORD] >> (d % WORD)) & 1 for d in range(n)]).astype(bool)


def to_words(components: list[int], n: int) -> list[int]:
    out = [0] * n_words(n)
    for d in components:
        out[d // WORD] |= 1 << (d % WORD)
    return out


def of_words(words: list[int]) -> list[int]:
    return [w * WORD + d for w, word in enumerate(words) for d in range(WORD) if word >> d & 1]


def unrank(n: int, k: int, ranks: np.ndarray) -> np.ndarray:
    """failed[n, B]: the k-subsets of n with these ranks, in the combinatorial number system."""
    left = np.asarray(ranks, np.int64).copy()
    out = np.zeros((n, len(left)), bool)
    need = np.full(len(left), k)
    choose = np.array([[min(comb(d, j), 2**62) for j in range(k + 1)] for d in range(n + 1)], np.int64)
    for d in range(n - 1, -1, -1):
        c = choose[d, need]
        take = (need > 0) & (left >= c)
        out[d] = take
        left = np.where(take, left - c, left)
        need = need - take
    return out
