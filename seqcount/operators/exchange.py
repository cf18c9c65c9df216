"""What travels: supermer blocks, pre-counted lists of heavy tasks, compressed locations; and what it costs."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqcount.functions import kernel
from seqcount.functions.scores import murmur3
from seqcount.operators.prepare import prepare_reads
from seqcount.spec import CountSpec

SUPERMERS, KMER_LIST = 0, 1
BLOCKS = "pid int, task int, kind byte, n int, payload binary"
#: A sender flushes all its blocks when they hold so many bytes, whatever their number.
SENDER_BYTES = 64 << 20
#: A sender counts the k-mers of heavy tasks anew when it holds so many pairs.
LIST_PAIRS = 1 << 20


#: How read and start of each supermer travel: 12 bytes each, or as differences.
LOCATIONS = ("plain", "pair", "per_field")


def pack_block(n_bases: np.ndarray, packed: np.ndarray, ext: tuple[np.ndarray, np.ndarray] | None = None, locations: str = "per_field") -> bytes:
    """A self-contained payload: 16-bit lengths, bases at 2 bits, and if asked read and start of each supermer."""
    body = n_bases.astype("<u2").tobytes() + np.ascontiguousarray(packed).tobytes()
    if ext is None:
        return body
    return body + (ext[0].astype("<i8").tobytes() + ext[1].astype("<i4").tobytes() if locations == "plain" else encode_locations(*ext, locations))


def unpack_block(n: int, payload: bytes, ext: bool = False, locations: str = "per_field"):
    """(lengths, packed bases, read ids, starts) of a payload; the last two None without ext."""
    data = np.frombuffer(payload, np.uint8)
    n_bases = data[: 2 * n].view("<u2").astype(np.int64)
    size = int((-(-n_bases // 4)).sum())
    packed = data[2 * n : 2 * n + size]
    if not ext:
        return n_bases, packed, None, None
    rest = data[2 * n + size :]
    if locations != "plain":
        return n_bases, packed, *decode_locations(rest.tobytes())
    return n_bases, packed, np.frombuffer(rest[: 8 * n].tobytes(), "<i8"), np.frombuffer(rest[8 * n :].tobytes(), "<i4")


def pack_list(words: list[np.ndarray], counts: np.ndarray) -> bytes:
    return b"".join([*(w.astype("<i8").tobytes() for w in words), counts.astype("<i8").tobytes()])


def unpack_list(n: int, payload: bytes, words: int) -> tuple[list[np.ndarray], np.ndarray]:
    columns = np.frombuffer(payload, "<i8").reshape(words + 1, n)
    return [columns[i] for i in range(words)], columns[words]


class Sender:
    """Blocks of one map task: buffers for each task, flushed at ``block_bytes``; lists for heavy tasks."""

    def __init__(self, spec: CountSpec, placed: np.ndarray, heavy: np.ndarray, partitions: int, ext: bool = False, heavy_target: str = "kmer", locations: str = "per_field"):
        self.spec, self.placed, self.partitions, self.ext, self.heavy_target, self.locations = spec, placed, partitions, ext, heavy_target, locations
        self.is_heavy = np.zeros(spec.s, bool)
        self.is_heavy[heavy] = True
        self.held: dict[int, list] = {}
        self.held_bytes: dict[int, int] = {}
        self.total = 0
        self.lists: list[tuple[list[np.ndarray], np.ndarray, np.ndarray]] = []
        self.pairs = 0
        self.rows: list[tuple] = []

    def add(self, codes: np.ndarray, ids: np.ndarray, starts: np.ndarray) -> None:
        """Cut codes into supermers and put them into their tasks' buffers; ids, starts: read and place of each code."""
        found = kernel.find_supermers(codes, self.spec)
        heavy = self.is_heavy[found.task]
        if heavy.any():
            self._add_heavy(codes, found.begin[heavy], found.n_bases[heavy] - self.spec.k + 1, found.task[heavy])
            found = kernel.Supermers(found.begin[~heavy], found.n_bases[~heavy], found.task[~heavy])
        if not len(found.begin):
            return
        order = np.argsort(found.task, kind="stable")
        begin, n_bases, task = found.begin[order], found.n_bases[order], found.task[order]
        packed, offsets = kernel.pack_runs(codes, begin, n_bases)
        heads = np.flatnonzero(np.r_[True, task[1:] != task[:-1]])
        for a, b in zip(heads.tolist(), [*heads[1:].tolist(), len(task)], strict=True):
            part = (n_bases[a:b], packed[offsets[a] : offsets[b]], ids[begin[a:b]] if self.ext else None, starts[begin[a:b]] if self.ext else None)
            t = int(task[a])
            size = int(offsets[b] - offsets[a]) + 2 * (b - a)
            self.held.setdefault(t, []).append(part)
            self.held_bytes[t] = self.held_bytes.get(t, 0) + size
            self.total += size
            if self.held_bytes[t] >= self.spec.block_bytes:
                self._flush(t)
        if self.total >= SENDER_BYTES:
            self.flush_blocks()

    def _flush(self, t: int) -> None:
        parts = self.held.pop(t)
        self.total -= self.held_bytes.pop(t)
        n_bases = np.concatenate([p[0] for p in parts])
        ext = (np.concatenate([p[2] for p in parts]), np.concatenate([p[3] for p in parts])) if self.ext else None
        self.rows.append((int(self.placed[t]), t, SUPERMERS, len(n_bases), pack_block(n_bases, np.concatenate([p[1] for p in parts]), ext, self.locations)))

    def flush_blocks(self) -> None:
        for t in list(self.held):
            self._flush(t)

    def _add_heavy(self, codes, begin, n, task) -> None:
        run = np.repeat(np.arange(len(begin)), n)
        at = begin[run] + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
        words, counts = kernel.count_runs([w[at] for w in kernel.kmer_words(codes, self.spec.k, self.spec.canonical)])
        target = np.zeros(0, np.int64)
        if self.heavy_target == "task":  # a k-mer lies in one task, so that of any occurrence will do
            first = {}
            for w, t in zip(zip(*(x[at].tolist() for x in kernel.kmer_words(codes, self.spec.k, self.spec.canonical)), strict=True), task[run].tolist(), strict=True):
                first.setdefault(w, t)
            target = self.placed[np.array([first[w] for w in zip(*(x.tolist() for x in words), strict=True)], np.int64)]
        self.lists.append((words, counts, target))
        self.pairs += len(counts)
        if self.pairs >= LIST_PAIRS and len(self.lists) > 1:
            self._squeeze()
            if self.pairs >= LIST_PAIRS // 2:
                self.flush_lists()

    def _squeeze(self) -> None:
        words = [np.concatenate([x[0][i] for x in self.lists]) for i in range(self.spec.words)]
        counts = np.concatenate([x[1] for x in self.lists])
        target = np.concatenate([x[2] for x in self.lists])
        if len(target):
            order = np.lexsort(words[::-1])
            fresh = np.any([np.r_[True, w[order][1:] != w[order][:-1]] for w in words], axis=0)
            target = target[order][fresh]
        words, counts = kernel.count_runs(words, counts)
        self.lists, self.pairs = [(words, counts, target)], len(counts)

    def flush_lists(self) -> None:
        """Pairs go to partitions by a hash of the k-mer, so one heavy task spreads over all of them."""
        if not self.lists:
            return
        self._squeeze()
        words, counts, target = self.lists[0]
        pid = target if len(target) else murmur3(words[-1] ^ (words[0] << 7 if len(words) == 2 else 0)) % self.partitions
        order = np.argsort(pid, kind="stable")
        cuts = np.searchsorted(pid[order], np.arange(self.partitions + 1))
        for p in np.flatnonzero(np.diff(cuts)).tolist():
            take = order[cuts[p] : cuts[p + 1]]
            self.rows.append((p, -1, KMER_LIST, len(take), pack_list([w[take] for w in words], counts[take])))
        self.lists, self.pairs = [], 0

    def drain(self):
        rows, self.rows = self.rows, []
        if rows:
            pid, task, kind, n, payload = zip(*rows, strict=True)
            yield pa.RecordBatch.from_arrays(
                [pa.array(pid, pa.int32()), pa.array(task, pa.int32()), pa.array(kind, pa.int8()), pa.array(n, pa.int32()), pa.array(payload, pa.binary())],
                names=["pid", "task", "kind", "n", "payload"],
            )


def make_blocks(reads: DataFrame, spec: CountSpec, placed: np.ndarray, heavy: np.ndarray, partitions: int, ext: bool = False, heavy_target: str = "kmer", locations: str = "per_field", places: bool = True) -> DataFrame:
    """Block rows of all reads: parse, score, cut, pack, and pre-count heavy tasks in one narrow step; without ``places`` locations name the read alone."""

    def run(batches):
        sender = Sender(spec, placed, heavy, partitions, ext, heavy_target, locations)
        for batch in batches:
            ids, offs = batch.column(0).to_numpy(zero_copy_only=False), batch.column(1).to_numpy(zero_copy_only=False)
            for first, row, place, codes in kernel.groups(batch.column(2)):
                sender.add(codes, ids[first + row] if ext else ids, offs if not ext else offs[first + row] + place if places else np.zeros_like(place))
                yield from sender.drain()
        sender.flush_blocks()
        sender.flush_lists()
        yield from sender.drain()

    return prepare_reads(reads, spec).mapInArrow(run, BLOCKS)


def exchange(blocks: DataFrame, partitions: int) -> DataFrame:
    """The one shuffle: block rows to the partition that they name, tasks of a partition one after another."""
    return blocks.repartitionById(partitions, F.col("pid")).sortWithinPartitions("task")


# --- locations of k-mers, compressed


def encode_locations(reads: np.ndarray, places: np.ndarray, mode: str = "pair") -> bytes:
    """Locations in send order: a tag byte each, then differences that fit one byte, or the values.

    pair: both fields as differences or both in full (3 or 9 bytes a location).
    per_field: each field by itself (3, 6 or 9 bytes). The first is in full, so a
    block depends on no other. Reads that don't fit 32 bits take 8 bytes in full, for
    the whole block; ``dense_ids`` avoids that.
    """
    if mode not in ("pair", "per_field"):
        raise ValueError("mode must be pair or per_field")
    n = len(reads)
    small = []
    for x in (reads, places):
        d = np.diff(x, prepend=x[:1]).astype(np.int64)
        fits = (d >= -128) & (d <= 127)
        if n:
            fits[0] = False
        small.append((d, fits))
    if mode == "pair":
        both = small[0][1] & small[1][1]
        small = [(d, both) for d, _ in small]
    tags = (small[0][1].astype(np.uint8)) | (small[1][1].astype(np.uint8) << 1)
    wide = bool(n) and (int(reads.max()) >= 1 << 31 or int(reads.min()) < -(1 << 31))
    parts = [np.array([n | wide << 31], "<u4").tobytes(), tags.tobytes()]
    for (d, fits), x, kind in zip(small, (reads, places), ("<i8" if wide else "<i4", "<i4"), strict=True):
        parts += [d[fits].astype(np.int8).tobytes(), x[~fits].astype(kind).tobytes()]
    return b"".join(parts)


def decode_locations(data: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Inverse of ``encode_locations``, for either mode."""
    n = int(np.frombuffer(data[:4], "<u4")[0])
    wide, n = n >> 31, n & 0x7FFFFFFF
    tags, at, out = np.frombuffer(data[4 : 4 + n], np.uint8), 4 + n, []
    for bit in (1, 2):
        fits = (tags & bit) > 0
        small = int(fits.sum())
        d = np.frombuffer(data[at : at + small], np.int8).astype(np.int64)
        at += small
        width = 8 if wide and bit == 1 else 4
        full = np.frombuffer(data[at : at + width * (n - small)], f"<i{width}").astype(np.int64)
        at += width * (n - small)
        step = np.zeros(n, np.int64)
        step[fits] = d
        run = np.cumsum(step)
        anchor = np.flatnonzero(~fits)
        base = np.zeros(n, np.int64)
        if len(anchor):
            since = np.searchsorted(anchor, np.arange(n), "right") - 1
            base = full[since] - run[anchor][since]
        out.append(base + run)
    return out[0], out[1]


def dense_ids(reads: DataFrame) -> DataFrame:
    """(read_id, dense): numbers from 0 without a single sorted partition, for ids that don't fit 32 bits."""
    part = reads.select("read_id").distinct().repartitionByRange("read_id").withColumn("part", F.spark_partition_id())
    counts = part.groupBy("part").agg(F.count("*").alias("c")).selectExpr("part", "sum(c) over (order by part) - c as before")
    inner = part.selectExpr("read_id", "part", "row_number() over (partition by part order by read_id) - 1 as at")
    return inner.join(F.broadcast(counts), "part").select("read_id", (F.col("at") + F.col("before")).alias("dense"))


def encode_ext(occurrences: DataFrame, mode: str = "pair") -> DataFrame:
    """(task, n, payload): compressed blocks of rows (task, read_id, pos), one for each batch and task, in row order."""

    def run(batches):
        for batch in batches:
            task = batch.column("task").to_numpy(zero_copy_only=False)
            order = np.argsort(task, kind="stable")
            heads = np.flatnonzero(np.r_[True, task[order][1:] != task[order][:-1]]) if len(task) else []
            reads, places = (batch.column(c).to_numpy(zero_copy_only=False)[order] for c in ("read_id", "pos"))
            ends = [*heads[1:], len(task)] if len(task) else []
            blocks = [encode_locations(reads[a:b], places[a:b], mode) for a, b in zip(heads, ends, strict=True)]
            yield pa.RecordBatch.from_arrays(
                [pa.array(task[order][heads] if len(task) else [], pa.int32()), pa.array([b - a for a, b in zip(heads, ends, strict=True)], pa.int32()), pa.array(blocks, pa.binary())],
                names=["task", "n", "payload"],
            )

    return occurrences.select("task", "read_id", "pos").mapInArrow(run, "task int, n int, payload binary")


def decode_ext(blocks: DataFrame) -> DataFrame:
    """(task, read_id, pos): inverse of ``encode_ext``."""

    def run(batches):
        for batch in batches:
            for task, payload in zip(batch.column("task").to_pylist(), batch.column("payload").to_pylist(), strict=True):
                reads, places = decode_locations(payload)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(reads), task, np.int32)), pa.array(reads), pa.array(places.astype(np.int32))], names=["task", "read_id", "pos"])

    return blocks.mapInArrow(run, "task int, read_id long, pos int")


def location_bytes(occurrences: DataFrame) -> DataFrame:
    """(mode, occurrences, raw_bytes, coded_bytes) of rows (task, read_id, pos), each task in order of read and place; both modes from one pass."""
    order = "over (partition by task order by read_id, pos)"
    d = occurrences.selectExpr(f"read_id - lag(read_id) {order} as dr", f"pos - lag(pos) {order} as dp")
    fit = lambda c: F.coalesce(F.col(c).between(-128, 127), F.lit(False))
    pair = F.when(fit("dr") & fit("dp"), 3).otherwise(9)
    field = F.lit(1) + F.when(fit("dr"), 1).otherwise(4) + F.when(fit("dp"), 1).otherwise(4)
    sums = d.agg(F.count("*").alias("occurrences"), F.sum(pair).cast("long").alias("pair"), F.sum(field).cast("long").alias("per_field"))
    return sums.selectExpr("stack(2, 'pair', pair, 'per_field', per_field) as (mode, coded_bytes)", "occurrences", "occurrences * 8 as raw_bytes").select("mode", "occurrences", "raw_bytes", "coded_bytes")


# --- cost models


def pair_bytes(supermers: DataFrame, senders: int, partitions: int) -> DataFrame:
    """(src, dst, bytes): supermers at 2 bits a base and 2 bytes of length, from senders by read to partitions by task."""
    size = F.ceil(F.col("n_bases") / 4) + 2
    return supermers.groupBy(F.pmod("read_id", F.lit(senders)).cast("int").alias("src"), F.pmod("task", F.lit(partitions)).cast("int").alias("dst")).agg(F.sum(size).alias("bytes"))


def round_costs(pairs: DataFrame, batch_sizes: list[int], processes: int) -> DataFrame:
    """(batch, rounds, sent, padded, waste): what rounds of a fixed batch for each pair cost, with and without padding."""
    batch = pairs.sparkSession.createDataFrame([(int(b),) for b in batch_sizes], "batch long")
    total = pairs.agg(F.sum("bytes").alias("sent"), F.max("bytes").alias("most"))
    rounds = F.ceil(F.col("most") / F.col("batch"))
    return batch.join(F.broadcast(total)).select(
        "batch",
        rounds.cast("long").alias("rounds"),
        F.col("sent").cast("long").alias("sent"),
        (rounds * F.col("batch") * processes * processes).cast("long").alias("padded"),
        F.round(rounds * F.col("batch") * processes * processes / F.col("sent") - 1, 6).alias("waste"),
    )


def plan_rounds(sizes, batch: int) -> int:
    """Rounds until the largest pair has been sent."""
    return int(-(-int(np.max(sizes, initial=0)) // batch))


def overlap_model(comm: list[float], prepare: list[float], parse: list[float]) -> tuple[float, float]:
    """(seconds with double buffers, without): round r travels while r + 1 is prepared and r - 1 is parsed."""
    n = len(comm)
    at = lambda x, i: x[i] if 0 <= i < n else 0.0
    together = at(prepare, 0) + sum(max(comm[r], at(prepare, r + 1) + at(parse, r - 1)) for r in range(n)) + at(parse, n - 1)
    return together, sum(comm) + sum(prepare) + sum(parse)


def exchange_bytes(supermers: DataFrame, spec: CountSpec) -> DataFrame:
    """(kmers, kmer_bytes, supermers, supermer_bytes, saved): words of 8 bytes against supermers with 2 bytes of length."""
    word = 8 * spec.words
    n = F.sum(F.col("n_bases") - (spec.k - 1)).cast("long")
    size = F.sum(F.ceil(F.col("n_bases") / 4) + 2).cast("long")
    return supermers.agg(n.alias("kmers"), (n * word).alias("kmer_bytes"), F.count("*").alias("supermers"), size.alias("supermer_bytes"), F.round(1 - size / (n * word), 6).alias("saved"))
