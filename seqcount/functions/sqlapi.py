"""Functions and views for SQL users: table functions, vectorised functions, read views."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import ArrayType, LongType, StructField, StructType

from seqcount.functions import kernel
from seqcount.spec import CountSpec


@udtf(returnType="pos int, kmer bigint")
class Kmers:
    """kmers(seq, k): place and packed word of each k-mer, k up to 31."""

    def eval(self, seq: str, k: int):
        for _, _, place, codes in kernel.groups(pa.array([seq or ""])):
            at = np.flatnonzero(kernel.window_valid(codes, k))
            words = kernel.kmer_words(codes, k)[0]
            yield from zip(place[at].tolist(), words[at].tolist(), strict=True)


@udtf(returnType="task int, start int, n_bases int, bases string")
class SupermersOf:
    """supermers(seq, k, m, s, score): the supermers of one sequence."""

    def eval(self, seq: str, k: int, m: int, s: int, score: str):
        spec = CountSpec(k=k, m=m, s=s, score=score)
        for _, _, place, codes in kernel.groups(pa.array([seq or ""])):
            found = kernel.find_supermers(codes, spec)
            for b, n, t in zip(found.begin.tolist(), found.n_bases.tolist(), found.task.tolist(), strict=True):
                at = int(place[b])
                yield t, at, n, seq[at : at + n]


@pandas_udf(ArrayType(LongType()))
def pack_kmers(seq: pd.Series, k: pd.Series) -> pd.Series:
    """Packed k-mers of each sequence, in order, without those that hold other symbols."""
    out = []
    for s, n in zip(seq, k, strict=True):
        parts = [kernel.valid_kmers(codes, int(n))[0] for _, _, _, codes in kernel.groups(pa.array([s or ""]))]
        out.append(np.concatenate(parts) if parts else np.zeros(0, np.int64))
    return pd.Series(out)


@pandas_udf(ArrayType(LongType()))
def mmer_scores(seq: pd.Series, m: pd.Series) -> pd.Series:
    """Murmur3 scores of each sequence's m-mers; those that hold other symbols are left out."""
    out = []
    for s, n in zip(seq, m, strict=True):
        spec = CountSpec(k=max(int(n) + 1, 2), m=int(n))
        parts = [x[kernel.window_valid(codes, int(n))] for _, _, _, codes in kernel.groups(pa.array([s or ""])) for x in [kernel.mmer_scores(codes, spec)]]
        out.append(np.concatenate(parts) if parts else np.zeros(0, np.int64))
    return pd.Series(out)


@pandas_udf(ArrayType(StructType([StructField("cnt", LongType()), StructField("n_kmers", LongType())])))
def spectrum_of(kmer: pd.Series) -> list:
    """Grouped aggregate: spectrum of the packed k-mers of a group; for groups that fit a task."""
    _, n = kernel.count_runs([kmer.dropna().to_numpy(np.int64)])
    value, times = np.unique(n, return_counts=True)
    return [{"cnt": int(v), "n_kmers": int(t)} for v, t in zip(value, times, strict=True)]


def register_all(spark, sf_dir: str | None = None) -> None:
    """Register functions, and with a folder of tables the read views."""
    spark.udtf.register("kmers", Kmers)
    spark.udtf.register("supermers", SupermersOf)
    spark.udf.register("pack_kmers", pack_kmers)
    spark.udf.register("mmer_scores", mmer_scores)
    spark.udf.register("spectrum_of", spectrum_of)
    if sf_dir:
        from seqcount.sources.reads import VIEWS, table

        for name, make in VIEWS.items():
            make(spark, sf_dir).createOrReplaceTempView(name)
        for name in ("documents", "pages", "events"):
            table(spark, sf_dir, name).createOrReplaceTempView(name)


def edges(counts, k: int):
    """(source, target, cnt): edges of the de Bruijn graph of decoded k-mers."""
    return counts.select(F.substring("kmer", 1, k - 1).alias("source"), F.substring("kmer", 2, k - 1).alias("target"), "cnt")
