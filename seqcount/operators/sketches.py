"""Sketches of the hash-table paradigm: distinct estimate, Bloom filters, counting filters."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqcount.functions.kernel import count_runs
from seqcount.operators.prepare import kmer_array, kmer_fields, words_of
from seqcount.spec import CountSpec

_M1, _M2 = np.uint64(0xFF51AFD7ED558CCD), np.uint64(0xC4CEB9FE1A85EC53)


def hash_words(words: list[np.ndarray], seed: int = 0) -> np.ndarray:
    h = np.full(len(words[0]), seed * 0x9E3779B97F4A7C15 & (2**64 - 1), np.uint64)
    for w in words:
        h = (h ^ w.astype(np.uint64)) * _M1
        h = (h ^ (h >> np.uint64(33))) * _M2
        h ^= h >> np.uint64(29)
    return h


class Bloom:
    """A bit array with double hashing, sized for ``n`` keys at a false-positive rate."""

    def __init__(self, n: int, fpp: float = 0.01):
        self.bits = max(64, int(-n * math.log(fpp) / math.log(2) ** 2))
        self.hashes = max(1, round(self.bits / max(1, n) * math.log(2)))
        self.array = np.zeros(self.bits, bool)

    def _places(self, words: list[np.ndarray]) -> np.ndarray:
        a, b = hash_words(words, 1), hash_words(words, 2) | np.uint64(1)
        return np.stack([((a + np.uint64(i) * b) % np.uint64(self.bits)).astype(np.int64) for i in range(self.hashes)])

    def add(self, words: list[np.ndarray]) -> None:
        self.array[self._places(words)] = True

    def to_bytes(self) -> bytes:
        return np.packbits(self.array).tobytes()

    @classmethod
    def of_bytes(cls, data: bytes, n: int, fpp: float) -> Bloom:
        out = cls(n, fpp)
        out.array = np.unpackbits(np.frombuffer(data, np.uint8), count=out.bits).astype(bool)
        return out

    def has(self, words: list[np.ndarray]) -> np.ndarray:
        return self.array[self._places(words)].all(axis=0)


def distinct_estimate(kmers: DataFrame, lg: int = 12) -> DataFrame:
    """(estimate, sketch_bytes): sketches of partitions, merged; their size doesn't depend on the data's."""
    key = F.xxhash64("kmer")
    part = kmers.groupBy(F.spark_partition_id().alias("p")).agg(F.hll_sketch_agg(key, F.lit(lg)).alias("s"))
    return part.agg(F.hll_union_agg("s").alias("s")).select(F.hll_sketch_estimate("s").alias("estimate"), F.octet_length("s").cast("long").alias("sketch_bytes"))


def counting_filter(dealt: DataFrame, spec: CountSpec, slots: int = 1 << 22, hashes: int = 3) -> DataFrame:
    """(kmer, cnt) with cnt the least of a key's slots in its partition: never below the true count, sometimes above.

    Counts come out once the whole partition has been added, so keys seen are kept in
    a list without repeats; it's the filter's slots that don't grow.
    """

    def run(batches):
        counters = np.zeros(slots, np.int64)
        keys = []

        def places(words):
            a, b = hash_words(words, 1), hash_words(words, 2) | np.uint64(1)
            return [((a + np.uint64(i) * b) % np.uint64(slots)).astype(np.int64) for i in range(hashes)]

        for batch in batches:
            words, n = count_runs(words_of(batch.column(0)))
            for at in places(words):
                np.add.at(counters, at, n)
            keys.append(words)
        if keys:
            words, _ = count_runs([np.concatenate([k[i] for k in keys]) for i in range(spec.words)])
            least = np.min([counters[at] for at in places(words)], axis=0)
            yield pa.RecordBatch.from_arrays([kmer_array(words), pa.array(least)], names=["kmer", "cnt"])

    return dealt.select("kmer").mapInArrow(run, kmer_fields(spec) + ", cnt long")


def hash_memory_model(keys: int, key_bytes: int = 8, load: float = 0.7) -> dict[str, float]:
    """Bytes of a table of (key, count) at a load factor, against sorted arrays with and without auxiliary space."""
    entry = key_bytes + 4
    return {"hash_table": keys * entry / load, "sorted_inplace": keys * key_bytes, "sorted_aux": 2 * keys * key_bytes}
