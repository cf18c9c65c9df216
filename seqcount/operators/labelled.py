"""K-mer counts by a label of the reads, reduced where they are made."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqcount.functions import kernel
from seqcount.operators import exchange
from seqcount.operators.counting import Counter
from seqcount.operators.index import heavy_occurrences
from seqcount.operators.prepare import words_of
from seqcount.spec import CountSpec

#: Reduces runs of one range of k-mers: (first pair of each k-mer, and k-mer, label and count of every pair, in order).
Reduce = Callable[[np.ndarray, np.ndarray, np.ndarray, np.ndarray], pa.RecordBatch]


class LabelCounter(Counter):
    """Counts of one task by k-mer and label, which is the second word of a key."""

    def add_labelled(self, n: int, payload: bytes) -> None:
        n_bases, packed, labels, _ = exchange.unpack_block(n, payload, True)
        self.blocks.append((n_bases, packed, labels))

    def _expanded(self, blocks: list) -> list[np.ndarray]:
        n_bases, packed, labels = (np.concatenate([b[i] for b in blocks]) for i in (0, 1, 2))
        run, _, bits = kernel.run_starts(packed, n_bases, self.spec.k)
        return [*kernel.run_kmers(packed, n_bases, self.spec.k, self.spec.canonical, bits), labels[run]]


def _reduced(words: list[np.ndarray], n: np.ndarray, reduce: Reduce) -> pa.RecordBatch:
    fresh = np.ones(len(n), bool)
    fresh[1:] = words[0][1:] != words[0][:-1]
    return reduce(np.flatnonzero(fresh), *words, n)


def reduce_labelled(reads: DataFrame, spec: CountSpec, reduce: Reduce, fields: str, partitions: int | None = None) -> DataFrame:
    """What ``reduce`` makes of the counts of reads (label, seq) by k-mer and label, range by range; no k-mer is in two ranges.

    Supermer blocks with a label for each supermer take one exchange, so counts need none
    of their own. Heavy tasks are counted with partial sums and dealt by k-mer. For k-mers of one word and labels of at least 0.
    """
    from seqcount.plans.flagship import make_plan

    if spec.words > 1:
        raise ValueError("labels take the place of the second word")
    named = reads.select(F.col("label").cast("long").alias("read_id"), "seq")
    plan = make_plan(reads.select(F.xxhash64("seq").alias("read_id"), "seq"), spec, partitions)
    blocks = exchange.make_blocks(named, spec, plan.placed, np.zeros(0, np.int64), plan.partitions, ext=True, places=False)
    heavy = F.col("task").isin([int(t) for t in plan.heavy])

    def tasks(batches):
        task, counter = None, None
        for batch in batches:
            for t, n, payload in zip(batch.column("task").to_pylist(), batch.column("n").to_pylist(), batch.column("payload"), strict=True):
                if t != task:
                    if counter:
                        yield from counter.pieces()
                    task, counter = t, LabelCounter(spec, "aux_radix")
                counter.add_labelled(n, payload.as_buffer())
        if counter:
            yield from counter.pieces()

    def light(batches):
        for words, n in tasks(batches):
            if len(n):
                yield _reduced(words, n, reduce)

    if not len(plan.heavy):
        return exchange.exchange(blocks, plan.partitions).mapInArrow(light, fields)

    def dealt(batches):
        held = [(words_of(b.column(0))[0], b.column(1).to_numpy(), b.column(2).to_numpy()) for b in batches if b.num_rows]
        if held:
            words, n = kernel.count_runs([np.concatenate([h[i] for h in held]) for i in (0, 1)], np.concatenate([h[2] for h in held]))
            yield _reduced(words, n, reduce)

    found = heavy_occurrences(blocks.where(heavy), spec).groupBy("kmer", F.col("read_id").alias("label")).agg(F.count("*").alias("n"))
    rest = found.repartition(plan.partitions, "kmer").mapInArrow(dealt, fields)
    return exchange.exchange(blocks.where(~heavy), plan.partitions).mapInArrow(light, fields).unionByName(rest)
