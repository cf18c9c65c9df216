"""Supermers as rows and as blocks; expansion to k-mers; the plain DataFrame twin."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from seqcount.functions import kernel
from seqcount.functions.alphabet import pack
from seqcount.functions.scores import lexical_ranks, score_column, task_column
from seqcount.operators.prepare import kmer_array, kmer_fields, prepare_reads
from seqcount.spec import CountSpec

ROWS = "task int, read_id long, start int, n_bases int, n_kmers int, packed binary"


def binary_array(data: np.ndarray, offsets: np.ndarray) -> pa.Array:
    return pa.Array.from_buffers(pa.binary(), len(offsets) - 1, [None, pa.py_buffer(offsets.astype(np.int32)), pa.py_buffer(np.ascontiguousarray(data))])


def build_supermers(reads: DataFrame, spec: CountSpec) -> DataFrame:
    """(task, read_id, start, n_bases, n_kmers, packed): one row a supermer, start from 0 in the read. Narrow."""

    def run(batches):
        for batch in batches:
            ids, offs = batch.column(0).to_numpy(zero_copy_only=False), batch.column(1).to_numpy(zero_copy_only=False)
            for first, row, place, codes in kernel.groups(batch.column(2)):
                found = kernel.find_supermers(codes, spec)
                data, offsets = kernel.pack_runs(codes, found.begin, found.n_bases)
                rows = first + row[found.begin] if len(found.begin) else np.zeros(0, np.int64)
                start = offs[rows] + place[found.begin]
                columns = [found.task.astype(np.int32), ids[rows], start.astype(np.int32), found.n_bases.astype(np.int32), (found.n_bases - spec.k + 1).astype(np.int32)]
                yield pa.RecordBatch.from_arrays([*map(pa.array, columns), binary_array(data, offsets)], names=["task", "read_id", "start", "n_bases", "n_kmers", "packed"])

    return prepare_reads(reads, spec).mapInArrow(run, ROWS)


def supermer_bases(supermers: DataFrame) -> DataFrame:
    """With ``bases``, the supermer as text, in place of ``packed``."""
    pairs = F.transform(
        F.sequence(F.lit(1), F.octet_length("packed")),
        lambda i: F.lpad(F.conv(F.hex(F.substring("packed", i, F.lit(1))), 16, 4), 4, "0"),
    )
    text = F.translate(F.array_join(pairs, ""), "0123", "ACGT")
    return supermers.withColumn("bases", F.substring(text, F.lit(1), F.col("n_bases"))).drop("packed")


def expand_supermers(supermers: DataFrame, spec: CountSpec, keep: tuple[str, ...] = ()) -> DataFrame:
    """The k-mers of supermer rows, with any of task, read_id; with 'pos' the place in the read."""
    fields = {"task": "task int", "read_id": "read_id long", "pos": "pos int"}
    schema = ", ".join([kmer_fields(spec), *(fields[c] for c in keep)])

    def run(batches):
        for batch in batches:
            n = batch.column("n_bases").to_numpy(zero_copy_only=False).astype(np.int64)
            packed = np.frombuffer(b"".join(batch.column("packed").to_pylist()), np.uint8)
            codes, begins = kernel.unpack_runs(packed, n)
            ok = kernel.window_valid(codes, spec.k)
            columns = [kmer_array([w[ok] for w in kernel.kmer_words(codes, spec.k, spec.canonical)])]
            if keep:
                counts = n - spec.k + 1
                run_of = np.repeat(np.arange(len(n)), counts)
                at = np.flatnonzero(ok)
                for c in keep:
                    if c == "pos":
                        columns.append(pa.array((batch.column("start").to_numpy(zero_copy_only=False)[run_of] + at - begins[run_of]).astype(np.int32)))
                    else:
                        columns.append(pa.array(batch.column(c).to_numpy(zero_copy_only=False)[run_of]))
            yield pa.RecordBatch.from_arrays(columns, names=["kmer", *keep])

    return supermers.mapInArrow(run, schema)


# --- the plain DataFrame form: slower, but readable and the same


def mmers(reads: DataFrame, spec: CountSpec) -> DataFrame:
    """(read_id, frag, pos, mmer, score): m-mers of the fragments between N's, pos from 0 in the read."""
    cut = F.split(F.col("seq"), "[^ACGT]")
    frags = reads.where(F.length("seq") >= spec.k).select("read_id", F.posexplode(cut).alias("frag", "seq"), cut.alias("all"))
    # each cut is one symbol, so a fragment begins after the fragments and cuts before it
    base = F.aggregate(F.slice("all", F.lit(1), F.col("frag")), F.lit(0), lambda a, x: a + F.length(x) + 1)
    body = frags.where(F.length("seq") >= spec.k).select("read_id", "frag", base.alias("base"), F.col("seq").cast("binary").alias("body"))
    at = body.select("read_id", "frag", "base", "body", F.explode(F.sequence(F.lit(1), F.octet_length("body") - spec.m + 1)).alias("at"))
    word = at.select("read_id", "frag", (F.col("base") + F.col("at") - 1).alias("pos"), pack(F.substring("body", F.col("at"), F.lit(spec.m)).cast("string"), spec.m).alias("mmer"))
    return word.withColumn("score", score_column(F.col("mmer"), spec.m, spec.score, spec.seed))


def minimizers_window(reads: DataFrame, spec: CountSpec) -> DataFrame:
    """(read_id, frag, pos, score, task) of every k-mer, by a sliding window frame."""
    along = Window.partitionBy("read_id", "frag").orderBy("pos")
    scored = mmers(reads, spec)
    ahead = along.rowsBetween(0, spec.w - 1)
    full = scored.withColumn("least", F.min("score").over(ahead)).withColumn("seen", F.count("*").over(ahead)).where(F.col("seen") == spec.w)
    return full.select("read_id", "frag", "pos", F.col("least").alias("score"), task_column(F.col("least"), spec.s).alias("task"))


def supermers_window(reads: DataFrame, spec: CountSpec) -> DataFrame:
    """(read_id, task, start, n_bases) by gaps and islands over the minimizers."""
    along = Window.partitionBy("read_id", "frag").orderBy("pos")
    mark = "task" if spec.break_on == "task" else "score"
    changed = F.coalesce((F.col(mark) != F.lag(mark).over(along)).cast("int"), F.lit(1))
    island = minimizers_window(reads, spec).withColumn("new", changed).withColumn("island", F.sum("new").over(along))
    out = island.groupBy("read_id", "frag", "island").agg(F.min("task").alias("task"), F.min("pos").alias("start"), (F.count("*") + spec.k - 1).alias("n_bases"))
    return out.select("read_id", "task", "start", F.col("n_bases").cast("int").alias("n_bases"))


def minimizers_arrow(reads: DataFrame, spec: CountSpec, method: str = "block") -> DataFrame:
    """(read_id, pos, score, mmer_pos) of every k-mer by one of the array methods; ties as ``spec.tie`` says."""
    from seqcount.functions.minimizers import METHODS

    find = METHODS[method]

    def run(batches):
        for batch in batches:
            ids, offs = batch.column(0).to_numpy(zero_copy_only=False), batch.column(1).to_numpy(zero_copy_only=False)
            for first, row, place, codes in kernel.groups(batch.column(2)):
                valid = kernel.window_valid(codes, spec.k)
                scores = np.minimum(kernel.mmer_scores(codes, spec), 0xFFFFFFFF)
                if spec.tie == "lex":
                    _, where = find(lexical_ranks(scores, kernel.mmer_words(codes, spec)), spec.w, "right")
                    least = scores[where]
                else:
                    least, where = find(scores, spec.w, spec.tie)
                at = np.flatnonzero(valid)
                rows = first + row[at]
                columns = [ids[rows], (offs[rows] + place[at]).astype(np.int32), least[at], (offs[rows] + place[where[at]]).astype(np.int32)]
                yield pa.RecordBatch.from_arrays(list(map(pa.array, columns)), names=["read_id", "pos", "score", "mmer_pos"])

    return prepare_reads(reads, spec).mapInArrow(run, "read_id long, pos int, score long, mmer_pos int")


def minimizers_naive(reads: DataFrame, spec: CountSpec) -> DataFrame:
    """(read_id, frag, pos, score): each k-mer's own m-mers by higher-order functions, nothing shared."""
    cut = F.split(F.col("seq"), "[^ACGT]")
    frags = reads.where(F.length("seq") >= spec.k).select("read_id", F.posexplode(cut).alias("frag", "seq"), cut.alias("all"))
    base = F.aggregate(F.slice("all", F.lit(1), F.col("frag")), F.lit(0), lambda a, x: a + F.length(x) + 1)
    body = frags.where(F.length("seq") >= spec.k).select("read_id", "frag", base.alias("base"), F.col("seq").cast("binary").alias("body"))
    words = lambda i: pack(F.substring("body", i, F.lit(spec.m)).cast("string"), spec.m)
    at = body.select("read_id", "frag", "base", "body", F.explode(F.sequence(F.lit(1), F.octet_length("body") - spec.k + 1)).alias("at"))
    scores = F.transform(F.sequence(F.col("at"), F.col("at") + (spec.w - 1)), lambda i: score_column(words(i), spec.m, spec.score, spec.seed))
    return at.select("read_id", "frag", (F.col("base") + F.col("at") - 1).alias("pos"), F.array_min(scores).alias("score"))
