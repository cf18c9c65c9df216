"""The whole method: sizes, assignment, blocks, one exchange, sort and scan."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqcount.functions import kernel
from seqcount.operators import counting, exchange
from seqcount.operators.prepare import prepare_reads
from seqcount.operators.tasks import assign_tasks, heavy_tasks, size_vector
from seqcount.spec import CountSpec

#: Share of the pieces of reads, by a hash of the read and the place, that task sizes are estimated from; bases of a piece.
#: A long read is many pieces, so a repeat within a single read is seen like one in many.
SIZE_SAMPLE, SIZE_PIECE = 1 / 8, 1 << 10


@dataclass
class Plan:
    """What the driver decides from the task sizes: s numbers, whatever the data."""

    sizes: np.ndarray
    heavy: np.ndarray
    placed: np.ndarray
    partitions: int
    method: str = "aux_radix"


def kmers_per_task(reads: DataFrame, spec: CountSpec, share: float = 1.0) -> np.ndarray:
    """k-mers of each task over all reads, or estimated from a share of their pieces; a narrow pass and s sums.

    Sizes count k-mers, not bytes: a tandem repeat is a single supermer of many k-mers.
    """
    if share < 1:
        reads = sampled_pieces(reads, spec, share)

    def run(batches):
        total = np.zeros(spec.s, np.int64)
        for batch in batches:
            for _, _, _, codes in kernel.groups(batch.column(2)):
                found = kernel.find_supermers(codes, spec)
                total += np.bincount(found.task, found.n_bases - spec.k + 1, spec.s).astype(np.int64)
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(total[at])], names=["task", "n"])

    part = prepare_reads(reads, spec).mapInArrow(run, "task int, n long")
    sizes = size_vector(part.groupBy("task").agg(F.sum("n").alias("n_kmers")).collect(), spec.s)
    return np.round(sizes / share).astype(np.int64) if share < 1 else sizes


def sampled_pieces(reads: DataFrame, spec: CountSpec, share: float) -> DataFrame:
    """(read_id, seq): a share of the reads' pieces, by hash; pieces overlap by k - 1, so a window is in one of them."""
    pieces = F.when(F.length("seq") >= spec.k, F.sequence(F.lit(0), F.floor((F.length("seq") - spec.k) / SIZE_PIECE).cast("int")))
    taken = F.filter(pieces, lambda i: F.pmod(F.xxhash64(F.col("read_id"), i), F.lit(1 << 16)) < int(share * (1 << 16)))
    cut = reads.select("read_id", "seq").select("read_id", F.col("seq").cast("binary").alias("body"), F.explode(taken).alias("piece"))
    return cut.select("read_id", F.substring("body", F.col("piece") * SIZE_PIECE + 1, F.lit(SIZE_PIECE + spec.k - 1)).cast("string").alias("seq"))


def make_plan(reads: DataFrame, spec: CountSpec, partitions: int | None = None, heavy: bool = True, policy: str = "greedy", share: float = SIZE_SAMPLE, filled: bool = False) -> Plan:
    """Sizes, heavy tasks, the partition of each task, and the sort for tasks of that size.

    A heavy task costs its partition little: it travels as pairs. With ``filled`` its
    size is held against the mean of the tasks that have k-mers.
    """
    partitions = partitions or int(reads.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    sizes = kmers_per_task(reads, spec, share)
    found = heavy_tasks(sizes, spec.heavy_factor, filled) if heavy else np.zeros(0, np.int64)
    load = sizes.copy()
    load[found] = 0
    method = counting.choose_sort(int(load.max(initial=0)) * 8 * spec.words, spec.worker_bytes)
    return Plan(sizes, found, assign_tasks(load, partitions, spec.growth, policy), partitions, method)


def count_kmers(reads: DataFrame, spec: CountSpec, partitions: int | None = None, *, heavy: bool = True, policy: str = "greedy", method: str | None = None,
                share: float = SIZE_SAMPLE, plan: Plan | None = None, as_spectrum: bool = False, ranged: bool = False, heavy_target: str = "kmer") -> DataFrame:
    """(kmer, cnt) of all k-mers of reads (read_id, seq), or their spectrum (cnt, n_kmers).

    Reads are parsed into supermer blocks; heavy tasks are expanded and counted where
    they are and travel as (k-mer, count) pairs, dealt by k-mer; everything takes one
    exchange, after which each task is sorted and scanned by itself. Sizes from a share
    of the reads decide only where tasks go and which are heavy: the result is exact for
    any decision. The plan chooses the sort by the largest task unless ``method`` names one. Null reads, reads shorter than k and windows with other symbols count
    for nothing; an empty table gives no rows.
    """
    plan = plan or make_plan(reads, spec, partitions, heavy, policy, share)
    blocks = exchange.make_blocks(reads, spec, plan.placed, plan.heavy, plan.partitions, heavy_target=heavy_target)
    out = counting.count_blocks(exchange.exchange(blocks, plan.partitions), spec, method or plan.method, as_spectrum, ranged)
    return out.groupBy("cnt").agg(F.sum("n_kmers").alias("n_kmers")) if as_spectrum else out


#: The ladder of the ablation: what each rung adds to the one before.
RUNGS = ("supermer_sort", "task_layer", "heavy_tasks")


def rung_plan(reads: DataFrame, spec: CountSpec, name: str, partitions: int, per_worker: int = 3) -> tuple[CountSpec, Plan]:
    """What a rung runs with: as many tasks as partitions, dealt modulo; then more tasks, packed by size; then heavy tasks pre-counted.

    Sizes are counted over all reads: how many tasks are heavy is part of the ladder's result.
    """
    if name == "supermer_sort":
        return spec.but(s=partitions), Plan(np.zeros(partitions), np.zeros(0, np.int64), np.arange(partitions), partitions)
    layered = spec.but(s=max(spec.s, partitions * per_worker))
    return layered, make_plan(reads, layered, partitions, heavy=name == "heavy_tasks", share=1.0, filled=True)


def rung(reads: DataFrame, spec: CountSpec, name: str, partitions: int, per_worker: int = 3, as_spectrum: bool = True) -> DataFrame:
    """One rung of the ladder, counted."""
    own, plan = rung_plan(reads, spec, name, partitions, per_worker)
    return count_kmers(reads, own, plan=plan, as_spectrum=as_spectrum)
