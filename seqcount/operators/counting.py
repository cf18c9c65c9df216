"""Counting by sort and scan, and forms of the result."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqcount.functions import kernel
from seqcount.operators import exchange
from seqcount.operators.prepare import kmer_array, kmer_fields, words_of
from seqcount.spec import CountSpec

#: k-mers that a receiver expands before it counts them.
EXPAND_KMERS = 1 << 20
#: Pairs (k-mer, count) of a task that are held at once; tasks with more are counted by ranges of k-mers, one after another.
HELD_PAIRS = 1 << 23
#: Lists with so many occurrences a pair at most are merged as k-mers, not as pairs.
REPEATED = 1.5


def choose_sort(task_bytes: int, free_bytes: int) -> str:
    """Sort for a task's expanded keys: with second arrays if there's room, else in place, else by Spark, which spills."""
    if 2 * task_bytes <= 0.6 * free_bytes:
        return "aux_radix"
    return "inplace" if task_bytes <= 0.6 * free_bytes else "spark_radix"


class Counter:
    """Counts of one task: expanded parts are sorted and scanned, and their lists merged by another sort and scan.

    What came stays packed. If the lists outgrow ``HELD_PAIRS``, the upper k-mers are put
    off to a further pass over it, so memory doesn't follow the different k-mers of a task.
    """

    def __init__(self, spec: CountSpec, method: str):
        self.spec, self.method = spec, method
        self.lists: list[tuple[list[np.ndarray], np.ndarray]] = []
        self.blocks: list[tuple[np.ndarray, np.ndarray]] = []
        self.pairs = 0

    def add_block(self, n: int, payload: bytes) -> None:
        n_bases, packed, _, _ = exchange.unpack_block(n, payload)
        self.add_packed(n_bases.astype(np.uint16), packed)

    def add_packed(self, n_bases: np.ndarray, packed: np.ndarray) -> None:
        self.blocks.append((n_bases, packed))

    def add_list(self, n: int, payload: bytes) -> None:
        self.lists.append(exchange.unpack_list(n, payload, self.spec.words))
        self.pairs += n
        if self.pairs >= EXPAND_KMERS and len(self.lists) > 1:
            self.lists, self.pairs = [self._merged(self.lists)], 0

    def _parts(self, span: list):
        """(occurrences, words, counts) of about EXPAND_KMERS k-mers each; counted is what lies in the span, which may narrow meanwhile."""
        for words, n in self.lists:
            yield int(n.sum()), *_within(words, n, *span)
        held, waiting = [], 0
        for i, block in enumerate(self.blocks, 1):
            held.append(block)
            waiting += int(block[0].sum()) - len(block[0]) * (self.spec.k - 1)
            if waiting >= EXPAND_KMERS or i == len(self.blocks):
                yield waiting, *self._count(_inside(self._expanded(held), *span))
                held, waiting = [], 0

    def _expanded(self, blocks: list) -> list[np.ndarray]:
        n_bases, packed = (np.concatenate([b[i] for b in blocks]) for i in (0, 1))
        return kernel.run_kmers(packed, n_bases.astype(np.int64, copy=False), self.spec.k, self.spec.canonical)

    def _count(self, words):
        return hash_count(words) if self.method == "hash" else kernel.count_runs(words, method=self.method)

    def _ranges(self, parts: list):
        """The lists' slices of one range of k-mers after another, each of about EXPAND_KMERS pairs; lists that aren't in order are one range."""
        firsts = [words[0] for words, _ in parts]
        ranges = -(-sum(map(len, firsts)) // EXPAND_KMERS)
        if ranges < 2 or any((w[1:] < w[:-1]).any() for w in firsts):
            yield from [parts] if parts else []
            return
        keys = _sampled(firsts)
        borders = keys[len(keys) * np.arange(1, ranges) // ranges]
        cuts = [[0, *np.searchsorted(w, borders).tolist(), len(w)] for w in firsts]
        for i in range(ranges):
            slices = [([w[at[i] : at[i + 1]] for w in words], n[at[i] : at[i + 1]]) for (words, n), at in zip(parts, cuts, strict=True) if at[i] < at[i + 1]]
            if slices:
                yield slices

    def _merged(self, parts: list):
        """One list of several. Where few k-mers repeat, they're sorted by themselves: pairs cost more, in time and memory."""
        if len(parts) == 1:
            return parts[0]
        n = np.concatenate([p[1] for p in parts])
        single = int(n.sum()) <= REPEATED * len(n)
        words = [np.concatenate([np.repeat(p[0][i], p[1]) if single else p[0][i] for p in parts]) for i in range(len(parts[0][0]))]
        return kernel.count_runs(words, None if single else n, "inplace" if self.method == "inplace" else "aux_radix")

    def pieces(self):
        """(words, counts) of one range of k-mers after another; each k-mer is in one of them."""
        total, least, more = sum(int(b[0].sum()) - len(b[0]) * (self.spec.k - 1) for b in self.blocks) + self.pairs, None, True
        while more:
            parts, held, seen, more, span = [], 0, 0, False, [least, None]
            for came, words, n in self._parts(span):
                seen += came
                parts.append((words, n))
                held += len(n)
                if held < HELD_PAIRS or len(parts) == 1:
                    continue
                ranges = list(self._ranges(parts))
                one = ranges[len(ranges) // 2]
                if held * len(self._merged(one)[1]) < HELD_PAIRS // 2 * sum(len(n) for _, n in one):  # repeats: as one list they have room again
                    parts = [self._merged(some) for some in ranges]
                    held = sum(len(n) for _, n in parts)
                del ranges, one
                if held >= HELD_PAIRS // 2:
                    keys = _sampled([words[0] for words, _ in parts])
                    # the rest of the task may bring as many again, so the range is cut by what has been seen of it
                    cut = int(keys[int(len(keys) * min(0.5, 0.75 * seen / max(seen, total)))])
                    if cut > int(keys[0]):
                        span[1], more = cut, True
                        parts = [_within(*part, None, cut) for part in parts]
                        held = sum(len(n) for _, n in parts)
            for some in self._ranges(parts):
                yield self._merged(some)
            least = span[1]

    def result(self) -> tuple[list[np.ndarray], np.ndarray]:
        found = list(self.pieces())
        if not found:
            return [np.zeros(0, np.int64)] * self.spec.words, np.zeros(0, np.int64)
        return [np.concatenate([f[0][i] for f in found]) for i in range(len(found[0][0]))], np.concatenate([f[1] for f in found])


def _sampled(lists: list[np.ndarray]) -> np.ndarray:
    """Keys in order, one of so many of each list, to cut ranges by; any cut gives exact counts."""
    return np.sort(np.concatenate([keys[:: max(1, EXPAND_KMERS >> 10)] for keys in lists]))


def _within(words: list[np.ndarray], n: np.ndarray, least: int | None, most: int | None) -> tuple[list[np.ndarray], np.ndarray]:
    """The pairs whose first word is from ``least`` on and below ``most``."""
    *words, n = _inside([*words, n], least, most)
    return words, n


def _inside(columns: list[np.ndarray], least: int | None, most: int | None) -> list[np.ndarray]:
    """The rows whose first column is from ``least`` on and below ``most``."""
    if least is None and most is None:
        return columns
    ok = (columns[0] >= (least or 0)) & (columns[0] < most) if most is not None else columns[0] >= least
    return [c[ok] for c in columns]


def hash_count(words: list[np.ndarray]) -> tuple[list[np.ndarray], np.ndarray]:
    """Counts by a hash table, for comparison."""
    table = pa.table({f"w{i}": w for i, w in enumerate(words)})
    got = table.group_by(table.column_names).aggregate([([], "count_all")])
    return [got[f"w{i}"].to_numpy() for i in range(len(words))], got["count_all"].to_numpy()


def count_spilling(received: DataFrame, spec: CountSpec) -> DataFrame:
    """(kmer, cnt) of exchanged blocks whose tasks don't fit a worker: expanded to rows, sorted by Spark, which spills, and scanned."""

    def expand(batches):
        for batch in batches:
            for kind, n, payload in zip(batch.column("kind").to_pylist(), batch.column("n").to_pylist(), batch.column("payload"), strict=True):
                body = payload.as_buffer()
                if kind == exchange.SUPERMERS:
                    n_bases, packed, _, _ = exchange.unpack_block(n, body)
                    words = kernel.run_kmers(packed, n_bases, spec.k, spec.canonical)
                    times = np.ones(len(words[0]), np.int64)
                else:
                    words, times = exchange.unpack_list(n, body, spec.words)
                yield pa.RecordBatch.from_arrays([kmer_array(words), pa.array(times)], names=["kmer", "n"])

    rows = received.mapInArrow(expand, kmer_fields(spec) + ", n long")
    return run_length(rows.sortWithinPartitions(*(["kmer"] if spec.words == 1 else ["kmer.hi", "kmer.lo"])), spec, "n")


def count_blocks(received: DataFrame, spec: CountSpec, method: str = "aux_radix", as_spectrum: bool = False, ranged: bool = False) -> DataFrame:
    """(kmer, cnt) of exchanged blocks, or with ``as_spectrum`` partial sums (cnt, n_kmers).

    method: aux_radix, inplace or hash, with one task held at a time, tasks coming one
    after another; or spark_radix, by rows that Spark can spill. ``ranged`` keeps the
    counts from spec.lo to spec.hi where they're made.
    """
    if method == "spark_radix":
        counts = count_spilling(received, spec)
        counts = counts.where(F.col("cnt").between(spec.lo, spec.hi)) if ranged else counts
        return spectrum(counts) if as_spectrum else counts

    def results(batches):
        task, counter = None, None
        for batch in batches:
            for t, kind, n, payload in zip(batch.column("task").to_pylist(), batch.column("kind").to_pylist(), batch.column("n").to_pylist(), batch.column("payload"), strict=True):
                if t != task:
                    if counter:
                        yield from counter.pieces()
                    task, counter = t, Counter(spec, method)
                body = payload.as_buffer()
                counter.add_block(n, body) if kind == exchange.SUPERMERS else counter.add_list(n, body)
        if counter:
            yield from counter.pieces()

    def kept(batches):
        for words, n in results(batches):
            if ranged:
                ok = (n >= spec.lo) & (n <= spec.hi)
                words, n = [w[ok] for w in words], n[ok]
            yield words, n

    def rows(batches):
        for words, n in kept(batches):
            yield pa.RecordBatch.from_arrays([kmer_array(words), pa.array(n)], names=["kmer", "cnt"])

    def sums(batches):
        for _, n in kept(batches):
            value, times = np.unique(n, return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(value.astype(np.int64)), pa.array(times.astype(np.int64))], names=["cnt", "n_kmers"])

    if as_spectrum:
        return received.mapInArrow(sums, "cnt long, n_kmers long")
    return received.mapInArrow(rows, kmer_fields(spec) + ", cnt long")


def run_length(sorted_kmers: DataFrame, spec: CountSpec, weight: str | None = None) -> DataFrame:
    """(kmer, cnt) of partitions in which equal k-mers are neighbours: one scan that carries the open run over batches.

    With a ``weight`` column, its sums take the place of the numbers of rows.
    """

    def run(batches):
        open_key, open_n = None, 0
        for batch in batches:
            words = words_of(batch.column(0))
            if not len(words[0]):
                continue
            fresh = np.ones(len(words[0]), bool)
            fresh[1:] = np.any([w[1:] != w[:-1] for w in words], axis=0)
            heads = np.flatnonzero(fresh)
            n = np.add.reduceat(batch.column(1).to_numpy(zero_copy_only=False), heads) if weight else np.diff(np.append(heads, len(fresh)))
            keys = [w[heads] for w in words]
            first = tuple(int(w[0]) for w in keys)
            if open_key == first:
                n[0] += open_n
            elif open_key is not None:
                keys, n = [np.r_[x, w] for x, w in zip(open_key, keys, strict=True)], np.r_[open_n, n]
            open_key, open_n = tuple(int(w[-1]) for w in keys), int(n[-1])
            yield pa.RecordBatch.from_arrays([kmer_array([w[:-1] for w in keys]), pa.array(n[:-1].astype(np.int64))], names=["kmer", "cnt"])
        if open_key is not None:
            yield pa.RecordBatch.from_arrays([kmer_array([np.array([x], np.int64) for x in open_key]), pa.array([open_n], pa.int64())], names=["kmer", "cnt"])

    return sorted_kmers.select("kmer", *([weight] if weight else [])).mapInArrow(run, kmer_fields(spec) + ", cnt long")


def count_sorted(kmers: DataFrame, spec: CountSpec, sort_mode: str = "spark_radix") -> DataFrame:
    """(kmer, cnt) of k-mer rows that have been exchanged so that equal ones share a partition.

    spark_radix: Spark's local sort by the packed key alone, which it can do by radix,
    spilling as needed. timsort: the same sort by a struct, which has to compare.
    sortagg: Spark's own aggregation over sorted input; a partial sum goes before any
    exchange that it finds necessary.
    """
    if sort_mode == "sortagg":
        one = F.max(F.struct("kmer"))  # a buffer that hash aggregation can't hold
        return kmers.groupBy("kmer").agg(F.count("*").alias("cnt"), one.alias("any")).where("any is not null").select("kmer", "cnt")
    keys = ["kmer"] if spec.words == 1 else ["kmer.hi", "kmer.lo"]
    if sort_mode == "timsort":
        return run_length(kmers.sortWithinPartitions(F.struct("kmer")), spec)
    if sort_mode != "spark_radix":
        raise ValueError(f"unknown sort_mode {sort_mode}")
    return run_length(kmers.sortWithinPartitions(*keys), spec)


def spectrum(counts: DataFrame) -> DataFrame:
    """(cnt, n_kmers): how many different k-mers occur so often."""
    return counts.groupBy("cnt").agg(F.count("*").alias("n_kmers"))


def filter_counts(counts: DataFrame, lo: int = 2, hi: int = 50) -> DataFrame:
    """Counts in an inclusive range."""
    return counts.where(F.col("cnt").between(lo, hi))


def top_k(counts: DataFrame, n: int = 20) -> DataFrame:
    """The most frequent k-mers, ties by k-mer."""
    return counts.orderBy(F.desc("cnt"), "kmer").limit(n)


def cumulative(spectrum_rows: DataFrame) -> DataFrame:
    """(cnt, n_kmers, share): share of different k-mers up to each frequency; a spectrum has few rows."""
    return spectrum_rows.selectExpr("cnt", "n_kmers", "round(sum(n_kmers) over (order by cnt) / sum(n_kmers) over (), 6) as share")


def same_counts(a: DataFrame, b: DataFrame) -> bool:
    """Whether two count tables are equal as multisets."""
    cols = a.columns
    return a.select(cols).exceptAll(b.select(cols)).isEmpty() and b.select(cols).exceptAll(a.select(cols)).isEmpty()
