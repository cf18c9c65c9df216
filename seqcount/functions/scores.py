"""Scores of packed m-mers: column expressions, and numpy twins that agree bit for bit."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from seqcount.functions.alphabet import low_complexity

#: A prime below 2^31, so products of reduced values stay below 2^62.
PRIME = 2_147_483_629
MASK32 = 0xFFFFFFFF
#: Above every score.
NO_SCORE = np.int64(1) << 62


def _coefficients(score: str, seed: int) -> tuple[int, int]:
    if score == "arith":
        return 1_103_515_245, 12_345
    rng = np.random.default_rng(seed)
    return int(rng.integers(1, PRIME)), int(rng.integers(0, PRIME))


def score_column(mmer: Column, m: int, score: str = "murmur3", seed: int = 42) -> Column:
    """Score of a packed m-mer as a BIGINT that isn't negative."""
    if score == "murmur3":  # Spark's hash is 32-bit Murmur3 with seed 42
        return F.hash(mmer).cast("long").bitwiseAND(F.lit(MASK32))
    if score == "lex":
        return mmer
    if score == "lex_mod":
        return F.when(low_complexity(mmer, m), mmer + F.lit(1 << (2 * m))).otherwise(mmer)
    a, b = _coefficients(score, seed)
    return F.pmod(F.lit(a) * F.pmod(mmer, F.lit(PRIME)) + F.lit(b), F.lit(PRIME))


def murmur3(values: np.ndarray, seed: int = 42) -> np.ndarray:
    """32-bit Murmur3 of 64-bit values, low word first, as unsigned numbers."""
    v = values.astype(np.uint64)
    h = np.full(v.shape, seed, np.uint32)
    for word in ((v & np.uint64(MASK32)).astype(np.uint32), (v >> np.uint64(32)).astype(np.uint32)):
        word *= np.uint32(0xCC9E2D51)
        word = (word << np.uint32(15)) | (word >> np.uint32(17))
        word *= np.uint32(0x1B873593)
        h ^= word
        h = (h << np.uint32(13)) | (h >> np.uint32(19))
        h = h * np.uint32(5) + np.uint32(0xE6546B64)
    h ^= np.uint32(8)
    h ^= h >> np.uint32(16)
    h *= np.uint32(0x85EBCA6B)
    h ^= h >> np.uint32(13)
    h *= np.uint32(0xC2B2AE35)
    h ^= h >> np.uint32(16)
    return h.astype(np.int64)


def lex_mod(mmers: np.ndarray, m: int) -> np.ndarray:
    """Lexical order, but m-mers that begin AAA or ACA, or have AA after the start, come last."""
    head = mmers >> (2 * (m - 3)) if m >= 3 else np.full(mmers.shape, -1)
    late = (head == 0) | (head == 4)
    for i in range(m - 2):
        late |= ((mmers >> (2 * i)) & 15) == 0
    return np.where(late, mmers + (np.int64(1) << (2 * m)), mmers)


def score_array(mmers: np.ndarray, m: int, score: str = "murmur3", seed: int = 42) -> np.ndarray:
    """The twin of ``score_column``."""
    if score == "murmur3":
        return murmur3(mmers)
    if score == "lex":
        return mmers
    if score == "lex_mod":
        return lex_mod(mmers, m)
    a, b = _coefficients(score, seed)
    return (np.int64(a) * (mmers % PRIME) + np.int64(b)) % PRIME


#: Seed of the hash that makes destinations, where it isn't the one that makes scores.
SECOND_SEED = 1_540_483_477


def second_hash(mmers: np.ndarray) -> np.ndarray:
    """A hash of packed m-mers that is independent of their scores."""
    return murmur3(mmers, SECOND_SEED)


def lexical_ranks(scores: np.ndarray, mmers: np.ndarray) -> np.ndarray:
    """Numbers in the order of (score, m-mer): equal only for equal m-mers, so their minimum breaks ties by the m-mer."""
    order = np.lexsort([mmers, scores])
    fresh = np.ones(len(order), bool)
    fresh[1:] = (scores[order][1:] != scores[order][:-1]) | (mmers[order][1:] != mmers[order][:-1])
    out = np.empty(len(order), np.int64)
    out[order] = np.cumsum(fresh) - 1
    return out


def task_column(score: Column, s: int) -> Column:
    return F.pmod(score, F.lit(s)).cast("int")
