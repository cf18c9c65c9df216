"""K-mers with locations, lookups, and read pairs that share k-mers."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqcount.functions import kernel
from seqcount.operators import exchange
from seqcount.operators.counting import EXPAND_KMERS, Counter
from seqcount.operators.prepare import extract_kmers, kmer_array, kmer_fields
from seqcount.spec import CountSpec


def occurrence_fields(spec: CountSpec) -> str:
    return kmer_fields(spec) + ", cnt long, occ array<struct<read_id: long, pos: int>>"


def index_rows(words: list[np.ndarray], read: np.ndarray, pos: np.ndarray, spec: CountSpec) -> pa.RecordBatch:
    """Index rows of occurrences: those of k-mers with spec.lo to spec.hi of them."""
    order = np.lexsort([pos, read, *words[::-1]])
    words, read, pos = [w[order] for w in words], read[order], pos[order]
    fresh = np.ones(len(order), bool)
    fresh[1:] = np.any([w[1:] != w[:-1] for w in words], axis=0)
    heads = np.flatnonzero(fresh)
    n = np.diff(np.append(heads, len(order)))
    ok = (n >= spec.lo) & (n <= spec.hi)
    each = np.repeat(ok, n)
    places = pa.StructArray.from_arrays([pa.array(read[each]), pa.array(pos[each].astype(np.int32))], names=["read_id", "pos"])
    lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(n[ok])]), pa.int32()), places)
    return pa.RecordBatch.from_arrays([kmer_array([w[heads[ok]] for w in words]), pa.array(n[ok].astype(np.int64)), lists], names=["kmer", "cnt", "occ"])


def members(words: list[np.ndarray], known: list[np.ndarray]) -> np.ndarray:
    """Which keys are among the known ones, both in any order."""
    if len(words) == 1:
        return np.isin(words[0], known[0])
    both = [np.concatenate([k, w]) for k, w in zip(known, words, strict=True)]
    order = np.lexsort(both[::-1])
    fresh = np.ones(len(order), bool)
    fresh[1:] = np.any([w[order][1:] != w[order][:-1] for w in both], axis=0)
    group = np.empty(len(order), np.int64)
    group[order] = np.cumsum(fresh) - 1
    marked = np.zeros(int(fresh.sum()), bool)
    marked[group[: len(known[0])]] = True
    return marked[group[len(known[0]) :]]


def _indexed(received: DataFrame, spec: CountSpec, locations: str) -> DataFrame:
    """Index rows of exchanged blocks with locations, one task at a time.

    A task's k-mers are counted part by part; then its blocks are expanded once more and
    the occurrences of k-mers in range are kept, which are what comes out.
    """

    def parts(blocks):
        held, waiting = [], 0
        for block in blocks:
            held.append(block)
            waiting += int(block[0].sum())
            if waiting >= EXPAND_KMERS:
                yield held
                held, waiting = [], 0
        if held:
            yield held

    def index(blocks):
        counter = Counter(spec, "aux_radix")
        for n_bases, packed, _, _ in blocks:
            counter.add_packed(n_bases, packed)
        words, n = counter.result()
        ok = (n >= spec.lo) & (n <= spec.hi)
        known, kept = [w[ok] for w in words], []
        for some in parts(blocks):
            n_bases = np.concatenate([b[0] for b in some])
            packed = np.concatenate([b[1] for b in some])
            run, place, bits = kernel.run_starts(packed, n_bases, spec.k)
            words = kernel.run_kmers(packed, n_bases, spec.k, spec.canonical, bits)
            take = np.flatnonzero(members(words, known))
            run, place = run[take], place[take]
            kept.append([*[w[take] for w in words], np.concatenate([b[2] for b in some])[run], np.concatenate([b[3] for b in some])[run] + place])
        *words, read, pos = [np.concatenate([k[i] for k in kept]) for i in range(spec.words + 2)]
        return index_rows(words, read, pos, spec)

    def run(batches):
        task, blocks = None, []
        for batch in batches:
            for t, n, payload in zip(batch.column("task").to_pylist(), batch.column("n").to_pylist(), batch.column("payload"), strict=True):
                if t != task:
                    if blocks:
                        yield index(blocks)
                    task, blocks = t, []
                blocks.append(exchange.unpack_block(n, payload.as_buffer(), True, locations))
        if blocks:
            yield index(blocks)

    return received.mapInArrow(run, occurrence_fields(spec))


def kmer_index(reads: DataFrame, spec: CountSpec, partitions: int | None = None, locations: str = "per_field") -> DataFrame:
    """(kmer, cnt, occ): k-mers with spec.lo to spec.hi occurrences and where they are, occ in order of read and place.

    Supermers carry one location each, that of their first k-mer, as differences unless ``locations`` is plain. Heavy tasks are left
    out of the exchange of blocks: their k-mers are counted with partial sums, which
    leaves those in range, and only the occurrences of these are exchanged. No list is
    longer than spec.hi.
    """
    from seqcount.plans.flagship import make_plan

    plan = make_plan(reads, spec, partitions)
    heavy = plan.heavy
    blocks = exchange.make_blocks(reads, spec, plan.placed, np.zeros(0, np.int64), plan.partitions, ext=True, locations=locations)
    if not len(heavy):
        return _indexed(exchange.exchange(blocks, plan.partitions), spec, locations)
    named = [int(t) for t in heavy]
    light = _indexed(exchange.exchange(blocks.where(~F.col("task").isin(named)), plan.partitions), spec, locations)
    found = heavy_occurrences(blocks.where(F.col("task").isin(named)), spec, locations)
    reliable = found.groupBy("kmer").agg(F.count("*").alias("cnt")).where(F.col("cnt").between(spec.lo, spec.hi))
    lists = found.join(reliable, "kmer").groupBy("kmer", "cnt").agg(F.array_sort(F.collect_list(F.struct("read_id", "pos"))).alias("occ"))
    return light.unionByName(lists.select("kmer", "cnt", "occ"))


def heavy_occurrences(blocks: DataFrame, spec: CountSpec, locations: str = "per_field") -> DataFrame:
    """(kmer, read_id, pos) of blocks with locations."""

    def run(batches):
        for batch in batches:
            for n, payload in zip(batch.column("n").to_pylist(), batch.column("payload"), strict=True):
                n_bases, packed, ids, starts = exchange.unpack_block(n, payload.as_buffer(), True, locations)
                run, place, bits = kernel.run_starts(packed, n_bases, spec.k)
                kmer = kmer_array(kernel.run_kmers(packed, n_bases, spec.k, spec.canonical, bits))
                yield pa.RecordBatch.from_arrays([kmer, pa.array(ids[run]), pa.array((starts[run] + place).astype(np.int32))], names=["kmer", "read_id", "pos"])

    return blocks.mapInArrow(run, kmer_fields(spec) + ", read_id long, pos int")


def kmer_index_native(reads: DataFrame, spec: CountSpec) -> DataFrame:
    """The same by Spark's aggregation: count, keep those in range, then collect."""
    found = extract_kmers(reads, spec, ext=True)
    reliable = found.groupBy("kmer").agg(F.count("*").alias("cnt")).where(F.col("cnt").between(spec.lo, spec.hi))
    return found.join(reliable, "kmer").groupBy("kmer", "cnt").agg(F.array_sort(F.collect_list(F.struct("read_id", "pos"))).alias("occ"))


def lookup(index: DataFrame, kmers: DataFrame, max_broadcast: int = 1_000_000) -> DataFrame:
    """Index rows of the asked k-mers; the question is broadcast if it's counted as small."""
    few = kmers.limit(max_broadcast + 1).count() <= max_broadcast
    return index.join(F.broadcast(kmers) if few else kmers, "kmer", "left_semi")


def overlap_candidates(index: DataFrame, shared: int = 2, band: int | None = None) -> DataFrame:
    """(read_a, read_b, shared, min_diff, max_diff): read pairs with at least ``shared`` k-mers in common.

    Pairs come from each k-mer's own list, which has spec.hi entries at most, so no
    k-mer is joined with itself over the cluster. ``band`` keeps places that differ by
    that much at most.
    """
    flat = index.select(F.explode(F.transform("occ", lambda a: F.struct(a.alias("a"), F.filter("occ", lambda b: b["read_id"] > a["read_id"]).alias("bs")))).alias("x"))
    pairs = flat.select(F.col("x.a").alias("a"), F.explode("x.bs").alias("b")).select(
        F.col("a.read_id").alias("read_a"), F.col("b.read_id").alias("read_b"), (F.col("b.pos") - F.col("a.pos")).alias("diff")
    )
    if band is not None:
        pairs = pairs.where(F.abs("diff") <= band)
    out = pairs.groupBy("read_a", "read_b").agg(F.count("*").alias("shared"), F.min("diff").alias("min_diff"), F.max("diff").alias("max_diff"))
    return out.where(F.col("shared") >= shared)


def prune_transitive(pairs: DataFrame) -> DataFrame:
    """Pairs (a, c) go if some b between them is paired with both by more shared k-mers."""
    ab = pairs.select("read_a", F.col("read_b").alias("mid"), F.col("shared").alias("s1"))
    bc = pairs.select(F.col("read_a").alias("mid"), "read_b", F.col("shared").alias("s2"))
    through = ab.join(bc, "mid").groupBy("read_a", "read_b").agg(F.max(F.least("s1", "s2")).alias("via"))
    return pairs.join(through, ["read_a", "read_b"], "left").where("via is null or via <= shared").drop("via")
