"""Counters that the method is compared with; all give the same (kmer, cnt), but for the approximate one."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqcount.functions import kernel
from seqcount.functions.minimizers import window_naive
from seqcount.operators import counting, exchange, sketches
from seqcount.operators.prepare import extract_kmers, kmer_array, kmer_fields, prepare_reads, words_of
from seqcount.operators.supermers import build_supermers
from seqcount.session import work_folder
from seqcount.spec import CountSpec


def _parts(df: DataFrame, partitions: int | None) -> int:
    return partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))


def count_dist_hash(reads: DataFrame, spec: CountSpec, partitions: int | None = None, partial: bool = False) -> DataFrame:
    """Every k-mer to its owner by hash, then a hash table; with ``partial`` also a table before the exchange."""
    kmers = extract_kmers(reads, spec)
    dealt = kmers if partial else kmers.repartition(_parts(reads, partitions), "kmer")
    return dealt.groupBy("kmer").agg(F.count("*").alias("cnt"))


def _reliable(reads: DataFrame, spec: CountSpec, partitions: int, fpp: float, ext: bool, result, fields: str) -> DataFrame:
    """What ``result`` makes of each task's (words, read, pos), those of k-mers that a first exchange has marked as repeated.

    Both exchanges carry supermer blocks to their owners. The first pass leaves one row
    for each owner: a filter of the keys it has met twice. It travels with the second
    pass's blocks, the only ones with locations, and comes before them.
    """
    estimate = sketches.distinct_estimate(extract_kmers(reads, spec)).first()["estimate"]
    expected = int(1.2 * estimate / partitions) + 1024
    dealt, none = np.arange(spec.s) % partitions, np.zeros(0, np.int64)

    def mark(batches):
        seen, again, pid = sketches.Bloom(expected, fpp), sketches.Bloom(expected, fpp), None
        for batch in batches:
            for p, n, payload in zip(batch.column("pid").to_pylist(), batch.column("n").to_pylist(), batch.column("payload"), strict=True):
                pid, (n_bases, packed, _, _) = p, exchange.unpack_block(n, payload.as_buffer())
                words, times = kernel.count_runs(kernel.run_kmers(packed, n_bases, spec.k, spec.canonical))
                twice = (times > 1) | seen.has(words)
                seen.add(words)
                again.add([w[twice] for w in words])
        if pid is not None:
            yield pa.RecordBatch.from_arrays([pa.array([pid], pa.int32()), pa.array([again.to_bytes()], pa.binary())], names=["pid", "payload"])

    first = exchange.make_blocks(reads, spec, dealt, none, partitions).repartitionById(partitions, F.col("pid"))
    filters = first.select("pid", "n", "payload").mapInArrow(mark, "pid int, payload binary").selectExpr("pid", "-1 as task", "0 as n", "payload")
    blocks = exchange.make_blocks(reads, spec, dealt, none, partitions, ext=ext).select("pid", "task", "n", "payload")
    second = blocks.unionByName(filters).repartitionById(partitions, F.col("pid")).sortWithinPartitions("task")

    def keep(batches):
        known, task, held = sketches.Bloom(expected, fpp), None, []
        for batch in batches:
            for t, n, payload in zip(batch.column("task").to_pylist(), batch.column("n").to_pylist(), batch.column("payload"), strict=True):
                if t < 0:
                    known = sketches.Bloom.of_bytes(payload.as_py(), expected, fpp)
                    continue
                if t != task:
                    if held:
                        yield result(held)
                    task, held = t, []
                n_bases, packed, ids, starts = exchange.unpack_block(n, payload.as_buffer(), ext)
                run, place, bits = kernel.run_starts(packed, n_bases, spec.k)
                words = kernel.run_kmers(packed, n_bases, spec.k, spec.canonical, bits)
                take = np.flatnonzero(known.has(words))
                held.append(([w[take] for w in words], *((ids[run[take]], starts[run[take]] + place[take]) if ext else ())))
        if held:
            yield result(held)

    return second.mapInArrow(keep, fields)


def count_two_pass(reads: DataFrame, spec: CountSpec, partitions: int | None = None, fpp: float = 0.01) -> DataFrame:
    """Estimate the keys, mark repeats with a filter in one exchange, count only those behind another.

    A false positive ends with count 1, so results from 2 up are exact; at lo = 1 this
    way loses singletons by design.
    """

    def count(held):
        words, n = kernel.count_runs([np.concatenate([h[0][i] for h in held]) for i in range(spec.words)])
        ok = n > 1
        return pa.RecordBatch.from_arrays([kmer_array([w[ok] for w in words]), pa.array(n[ok])], names=["kmer", "cnt"])

    return _reliable(reads, spec, _parts(reads, partitions), fpp, False, count, kmer_fields(spec) + ", cnt long")


def _summed(lists: list, spec: CountSpec):
    return kernel.count_runs([np.concatenate([x[0][i] for x in lists]) for i in range(spec.words)], np.concatenate([x[1] for x in lists]))


def index_two_pass(reads: DataFrame, spec: CountSpec, partitions: int | None = None, fpp: float = 0.01) -> DataFrame:
    """(kmer, cnt, occ) as ``index.kmer_index`` gives: the second pass carries locations, of repeated k-mers alone. For lo of 2 at least."""
    from seqcount.operators.index import index_rows, occurrence_fields

    if spec.lo < 2:
        raise ValueError("a two-pass counter loses k-mers that occur once")

    def build(held):
        words = [np.concatenate([h[0][i] for h in held]) for i in range(spec.words)]
        return index_rows(words, np.concatenate([h[1] for h in held]), np.concatenate([h[2] for h in held]).astype(np.int64), spec)

    return _reliable(reads, spec, _parts(reads, partitions), fpp, True, build, occurrence_fields(spec))


def count_supermer_hash(reads: DataFrame, spec: CountSpec, partitions: int | None = None, naive: bool = False) -> DataFrame:
    """Supermers through the exchange, a hash table behind it; ``naive`` finds each k-mer's minimizer by itself."""
    p = _parts(reads, partitions)
    if naive:
        blocks = _naive_blocks(reads, spec, p)
    else:
        blocks = exchange.make_blocks(reads, spec, np.arange(spec.s) % p, np.zeros(0, np.int64), p)
    return counting.count_blocks(exchange.exchange(blocks, p), spec, method="hash")


def _naive_blocks(reads: DataFrame, spec: CountSpec, partitions: int) -> DataFrame:
    def run(batches):
        sender = exchange.Sender(spec, np.arange(spec.s) % partitions, np.zeros(0, np.int64), partitions)
        for batch in batches:
            offs = batch.column(1).to_numpy(zero_copy_only=False)
            for _, _, _, codes in kernel.groups(batch.column(2)):
                valid = kernel.window_valid(codes, spec.k)
                least, _ = window_naive(kernel.mmer_scores(codes, spec), spec.w)
                # the k-mers of a destination go as supermers, each cut from its own windows
                same = np.flatnonzero(valid)
                task = least[same] % spec.s
                fresh = np.ones(len(same), bool)
                fresh[1:] = (same[1:] != same[:-1] + 1) | (task[1:] != task[:-1])
                heads = np.flatnonzero(fresh)
                n = np.diff(np.append(heads, len(same)))
                if len(n) and n.max() > kernel.MAX_BASES - spec.k:
                    sender.add(codes, offs, offs)
                    continue
                for t in np.unique(task[heads]).tolist():
                    mine = task[heads] == t
                    bases = n[mine] + spec.k - 1
                    packed, _ = kernel.pack_runs(codes, same[heads[mine]], bases)
                    sender.rows.append((t % partitions, t, exchange.SUPERMERS, len(bases), exchange.pack_block(bases, packed)))
                yield from sender.drain()
        sender.flush_blocks()
        yield from sender.drain()

    return prepare_reads(reads, spec).mapInArrow(run, exchange.BLOCKS)


def count_range_sort(reads: DataFrame, spec: CountSpec, partitions: int | None = None, sort_mode: str = "spark_radix") -> DataFrame:
    """Splitters from a sample, an exchange by range, a sort of each range and a scan: partition first."""
    keys = ["kmer"] if spec.words == 1 else ["kmer.hi", "kmer.lo"]
    dealt = extract_kmers(reads, spec).repartitionByRange(_parts(reads, partitions), *keys)
    return counting.count_sorted(dealt, spec, sort_mode)


def count_hash_exchange_sort(reads: DataFrame, spec: CountSpec, partitions: int | None = None, sort_mode: str = "spark_radix") -> DataFrame:
    """K-mers by hash, then Spark's own local sort and a scan."""
    return counting.count_sorted(extract_kmers(reads, spec).repartition(_parts(reads, partitions), "kmer"), spec, sort_mode)


def count_merge_last(reads: DataFrame, spec: CountSpec, partitions: int | None = None) -> DataFrame:
    """Sort and count what each input partition has, exchange the lists, merge them: merge last."""

    def run(batches):
        for batch in batches:
            for _, _, _, codes in kernel.groups(batch.column(2), 4 * kernel.PASS_BASES):
                words, n = kernel.count_runs(kernel.valid_kmers(codes, spec.k, spec.canonical))
                yield pa.RecordBatch.from_arrays([kmer_array(words), pa.array(n)], names=["kmer", "cnt"])

    lists = prepare_reads(reads, spec).mapInArrow(run, kmer_fields(spec) + ", cnt long")
    return lists.repartition(_parts(reads, partitions), "kmer").groupBy("kmer").agg(F.sum("cnt").alias("cnt"))


def count_shared_sort(reads: DataFrame, spec: CountSpec, threads: int | None = None, ram_only: bool = True) -> DataFrame:
    """One machine: bins by modified lexical order, held in memory or on disk, then each bin sorted by a thread.

    Bins are dealt to so many places that each is small, whatever the threads, which take
    one place after another. They are released once the counts are there, so this runs when it's called.
    """
    binned = spec.but(score="lex_mod")
    p = threads or max(reads.sparkSession.sparkContext.defaultParallelism, _parts(reads, None))
    blocks = exchange.make_blocks(reads, binned, np.arange(binned.s) % p, np.zeros(0, np.int64), p)
    held = exchange.exchange(blocks, p).persist(StorageLevel.MEMORY_ONLY if ram_only else StorageLevel.DISK_ONLY)
    work_folder(reads.sparkSession)
    counts = counting.count_blocks(held, binned).checkpoint()
    held.unpersist()
    return counts


def count_cbf(reads: DataFrame, spec: CountSpec, partitions: int | None = None, slots: int = 1 << 22, hashes: int = 3) -> DataFrame:
    """Approximate counts by a counting filter in each partition: never too low."""
    return sketches.counting_filter(extract_kmers(reads, spec).repartition(_parts(reads, partitions), "kmer"), spec, slots, hashes)


def heavy_kmers(reads: DataFrame, spec: CountSpec, share: float = 1e-3, sample: float = 1 / 16) -> list[np.ndarray]:
    """Words of the k-mers that hold more than half of ``share`` of a sample of the reads' pieces: 2 / share of them at most."""
    from seqcount.plans.flagship import sampled_pieces

    kmers = extract_kmers(sampled_pieces(reads, spec, sample), spec)
    counts = kmers.groupBy("kmer").agg(F.count("*").alias("n"))
    total = kmers.count()
    rows = counts.where(F.col("n") > max(1.0, share / 2 * total)).select("kmer").toArrow()
    return [np.ascontiguousarray(w) for w in words_of(rows["kmer"].combine_chunks())] if len(rows) else [np.zeros(0, np.int64)] * spec.words


def count_explicit_hh(reads: DataFrame, spec: CountSpec, partitions: int | None = None, share: float = 1e-3) -> DataFrame:
    """Find the frequent k-mers themselves in an extra pass; count them where they are; exchange these sums and all the rest."""
    from seqcount.operators.index import members

    top = reads.sparkSession.sparkContext.broadcast(heavy_kmers(reads, spec, share))

    def split(batches):
        held = []
        for batch in batches:
            words = words_of(batch.column(0))
            often = members(words, top.value)
            held.append(kernel.count_runs([w[often] for w in words]))
            if len(held) > 64:
                held = [_summed(held, spec)]
            rest = [w[~often] for w in words]
            yield pa.RecordBatch.from_arrays([kmer_array(rest), pa.array(np.ones(len(rest[0]), np.int64))], names=["kmer", "n"])
        if held:
            words, n = _summed(held, spec)
            yield pa.RecordBatch.from_arrays([kmer_array(words), pa.array(n)], names=["kmer", "n"])

    rows = extract_kmers(reads, spec).mapInArrow(split, kmer_fields(spec) + ", n long")
    return rows.repartition(_parts(reads, partitions), "kmer").groupBy("kmer").agg(F.sum("n").alias("cnt"))


def count_thread_owned(reads: DataFrame, spec: CountSpec, partitions: int | None = None, threads: int = 4) -> DataFrame:
    """Each thread of a process owns a part of its keys: a second split below the first, without another exchange."""
    p = _parts(reads, partitions)
    h = F.xxhash64("kmer")
    keyed = extract_kmers(reads, spec).select(F.pmod(h, F.lit(p)).cast("int").alias("pid"), F.pmod(F.shiftright(h, 32), F.lit(threads)).cast("int").alias("sub"), "kmer")
    return keyed.repartition(p, "pid").groupBy("pid", "sub", "kmer").agg(F.count("*").alias("cnt")).select("kmer", "cnt")


def count_heavy_native(supermers: DataFrame, spec: CountSpec) -> DataFrame:
    """Supermer rows expanded, then Spark's partial and final sums: what pre-counting does, for all tasks alike."""
    from seqcount.operators.supermers import expand_supermers

    return expand_supermers(supermers, spec).groupBy("kmer").agg(F.count("*").alias("cnt"))


def supermer_list(supermers: DataFrame) -> DataFrame:
    """Equal supermers once, with how often they occur, as a layout for heavy tasks that keeps them short."""
    return supermers.groupBy("task", "n_bases", "packed").agg(F.count("*").alias("times"))


def count_supermer_list(reads: DataFrame, spec: CountSpec) -> DataFrame:
    """Counts from supermers that were made distinct before they were expanded."""

    def run(batches):
        for batch in batches:
            n = batch.column("n_bases").to_numpy(zero_copy_only=False).astype(np.int64)
            times = batch.column("times").to_numpy(zero_copy_only=False)
            codes, _ = kernel.unpack_runs(np.frombuffer(b"".join(batch.column("packed").to_pylist()), np.uint8), n)
            weight = np.repeat(times, n - spec.k + 1)
            words, counts = kernel.count_runs(kernel.valid_kmers(codes, spec.k, spec.canonical), weight)
            yield pa.RecordBatch.from_arrays([kmer_array(words), pa.array(counts)], names=["kmer", "n"])

    once = supermer_list(build_supermers(reads, spec))
    return once.mapInArrow(run, kmer_fields(spec) + ", n long").groupBy("kmer").agg(F.sum("n").alias("cnt"))


def count_keys(rows: DataFrame, key: str, how: str = "sort", partitions: int | None = None) -> DataFrame:
    """(kmer, cnt) of any BIGINT column: the counters have no use for the alphabet."""
    spec, kmers = CountSpec(), rows.where(F.col(key).isNotNull()).select(F.col(key).cast("long").alias("kmer"))
    p = _parts(rows, partitions)
    if how == "sort":
        return counting.count_sorted(kmers.repartition(p, "kmer"), spec)
    if how == "range":
        return counting.count_sorted(kmers.repartitionByRange(p, "kmer"), spec)
    if how == "hash":
        return kmers.repartition(p, "kmer").groupBy("kmer").agg(F.count("*").alias("cnt"))
    if how == "precount":
        return kmers.groupBy("kmer").agg(F.count("*").alias("cnt"))
    raise ValueError(f"unknown way {how}")


