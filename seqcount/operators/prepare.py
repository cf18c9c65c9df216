"""Parsing of reads: chunks of long reads, splits at symbols that aren't bases, k-mers."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqcount.functions import kernel
from seqcount.spec import CountSpec


def prepare_reads(reads: DataFrame, spec: CountSpec) -> DataFrame:
    """(read_id, frag_off, seq): rows of ``spec.chunk`` bases at most that overlap by k - 1, so each window is in one row.

    Reads that are null or shorter than k have no window and go: they have no pieces. A
    filter would be pushed below what makes the sequence, which then ran twice, and before
    reads are spread. Narrow: no shuffle.
    """
    step = spec.chunk - spec.k + 1
    starts = F.sequence(F.lit(0), F.greatest(F.lit(0), F.ceil((F.length("seq") - spec.chunk) / step)).cast("int"))
    starts = F.when(F.length("seq") >= spec.k, starts)
    body = reads.select("read_id", "seq").select("read_id", F.col("seq").cast("binary").alias("body"), F.explode(starts).alias("piece"))
    return body.select("read_id", (F.col("piece") * step).alias("frag_off"), F.substring("body", F.col("piece") * step + 1, F.lit(spec.chunk)).cast("string").alias("seq"))


def fragments(reads: DataFrame, spec: CountSpec) -> DataFrame:
    """(read_id, frag_off, seq): the stretches of bases between other symbols, with k bases or more."""
    chunks = prepare_reads(reads, spec)
    found = chunks.select("read_id", "frag_off", F.explode(F.regexp_extract_all("seq", F.lit(f"([ACGT]{{{spec.k},}})"), 1)).alias("seq"))
    return found


def balance_reads(reads: DataFrame, partitions: int, sizes_per_partition: int = 16) -> DataFrame:
    """Reads dealt evenly by size: blocks of reads by hash are packed onto partitions, largest first.

    The driver sees one size for each block, whatever the number of reads.
    """
    from seqcount.operators.tasks import assign_tasks

    blocks = partitions * sizes_per_partition
    block = F.pmod(F.xxhash64("read_id"), F.lit(blocks)).cast("int")
    sized = reads.groupBy(block.alias("task")).agg(F.sum(F.length("seq")).alias("n")).collect()
    sizes = np.zeros(blocks, np.int64)
    for r in sized:
        sizes[r["task"]] = r["n"] or 0
    place = assign_tasks(sizes, partitions)
    target = F.element_at(F.array(*[F.lit(int(p)) for p in place]), block + 1)
    return reads.repartitionById(partitions, target)


def kmer_fields(spec: CountSpec) -> str:
    return "kmer long" if spec.words == 1 else "kmer struct<hi: long, lo: long>"


def kmer_array(words: list[np.ndarray]) -> pa.Array:
    if len(words) == 1:
        return pa.array(words[0])
    return pa.StructArray.from_arrays([pa.array(words[0]), pa.array(words[1])], names=["hi", "lo"])


def words_of(column: pa.Array) -> list[np.ndarray]:
    if pa.types.is_struct(column.type):
        return [column.field(0).to_numpy(zero_copy_only=False), column.field(1).to_numpy(zero_copy_only=False)]
    return [column.to_numpy(zero_copy_only=False)]


def extract_kmers(reads: DataFrame, spec: CountSpec, ext: bool = False) -> DataFrame:
    """Packed k-mers, one row an occurrence; with ``ext`` also read_id and pos, from 0 in the read."""
    chunks = prepare_reads(reads, spec)

    def run(batches):
        for batch in batches:
            ids, offs = batch.column(0).to_numpy(zero_copy_only=False), batch.column(1).to_numpy(zero_copy_only=False)
            for first, row, place, codes in kernel.groups(batch.column(2)):
                ok = kernel.window_valid(codes, spec.k)
                kmer = kmer_array([w[ok] for w in kernel.kmer_words(codes, spec.k, spec.canonical)])
                if ext:
                    at = np.flatnonzero(ok)
                    rows = first + row[at]
                    yield pa.RecordBatch.from_arrays([kmer, pa.array(ids[rows]), pa.array((offs[rows] + place[at]).astype(np.int32))], names=["kmer", "read_id", "pos"])
                else:
                    yield pa.RecordBatch.from_arrays([kmer], names=["kmer"])

    return chunks.mapInArrow(run, kmer_fields(spec) + (", read_id long, pos int" if ext else ""))


def extract_kmers_native(reads: DataFrame, k: int) -> DataFrame:
    """(read_id, pos, kmer STRING) with built-in functions only; slices of binary, as slices of a string walk it."""
    windows = F.sequence(F.lit(1), F.octet_length("seq") - k + 1)
    body = reads.where(F.length("seq") >= k).select("read_id", F.col("seq").cast("binary").alias("body"), F.explode(windows).alias("at"))
    cut = body.select("read_id", (F.col("at") - 1).alias("pos"), F.substring("body", F.col("at"), F.lit(k)).cast("string").alias("kmer"))
    return cut.where(~F.col("kmer").rlike("[^ACGT]"))
