"""Reads (read_id BIGINT, seq STRING) derived from the given tables by SQL that any engine can run."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seqcount.functions.alphabet import fold_text, text_to_bases

#: The base of each event type, for event sequences.
EVENT_BASES = {"view": "A", "click": "C", "signup": "G", "purchase": "T"}
SHORT_BASES = 150


#: Scans below this many bytes are dealt to all cores; above, files have row groups enough.
SMALL_SCAN = 256 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def spread(rows: DataFrame) -> DataFrame:
    """Rows of a small scan over all cores: a small file may be one row group, which one task reads.

    The size is that of the files, as the planner knows it, so no job runs; large
    scans stay as they are and are not shuffled.
    """
    size = int(str(rows._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return rows.repartition(rows.sparkSession.sparkContext.defaultParallelism) if size < SMALL_SCAN else rows


def reads_docs(spark, sf_dir) -> DataFrame:
    """Long reads: one base for each character of a document."""
    docs = spread(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return docs.select(F.col("doc_id").alias("read_id"), fold_text(F.col("text")).alias("seq"))


def reads_docs_exact(spark, sf_dir) -> DataFrame:
    """Documents without loss: four bases to a byte."""
    docs = spread(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return docs.select(F.col("doc_id").alias("read_id"), text_to_bases(F.col("text")).alias("seq"))


def reads_pages(spark, sf_dir) -> DataFrame:
    """Repetitive reads of markup."""
    pages = spread(table(spark, sf_dir, "pages").select("page_id", "html"))
    return pages.select(F.col("page_id").alias("read_id"), fold_text(F.col("html")).alias("seq"))


def reads_small(spark, sf_dir) -> DataFrame:
    """The smallest corpus."""
    return table(spark, sf_dir, "benchmark").select(F.col("item_id").alias("read_id"), fold_text(F.col("text")).alias("seq"))


def reads_conversations(spark, sf_dir) -> DataFrame:
    return table(spark, sf_dir, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("read_id"), fold_text(F.col("text")).alias("seq"))


def cut_reads(reads: DataFrame, size: int = SHORT_BASES) -> DataFrame:
    """Pieces of ``size`` bases that don't overlap, the last one shorter; (read_id, piece, seq)."""
    body = F.col("seq").cast("binary")
    piece = F.explode(F.sequence(F.lit(0), F.floor((F.length("seq") - 1) / size).cast("int"))).alias("piece")
    return reads.where(F.length("seq") > 0).select("read_id", piece, body.alias("b")).select("read_id", "piece", F.substring("b", F.col("piece") * size + 1, F.lit(size)).cast("string").alias("seq"))


def reads_short(spark, sf_dir) -> DataFrame:
    """Short reads of documents and conversations."""
    both = reads_docs(spark, sf_dir).unionByName(reads_conversations(spark, sf_dir))
    return cut_reads(both).select((F.col("read_id") * 4096 + F.col("piece")).alias("read_id"), "seq")


def reads_events(spark, sf_dir) -> DataFrame:
    """A user's events in order of time as one read; unknown types are N."""
    mapping = F.create_map(*[F.lit(x) for pair in EVENT_BASES.items() for x in pair])
    base = F.coalesce(F.try_element_at(mapping, F.col("event_type")), F.lit("N"))
    steps = table(spark, sf_dir, "events").groupBy("user_id").agg(F.array_sort(F.collect_list(F.struct("ts", "event_id", base.alias("base")))).alias("steps"))
    return steps.select(F.col("user_id").alias("read_id"), F.array_join(F.transform("steps", lambda s: s["base"]), "").alias("seq"))


#: A prime below 2^31 and the multipliers of the draws of ``mutated``, in numbers that SQL has too.
DRAW_PRIME, DRAW_READ, DRAW_COPY, DRAW_PLACE, DRAW_MIX = 2_147_483_629, 48_271, 1_566_083, 69_621, 16_807
#: Bases that are drawn for at once.
DRAW_BASES = 1 << 17
_ACGT = np.frombuffer(b"ACGT", np.uint8)


def mutated(reads: DataFrame, copies: int, error: float) -> DataFrame:
    """``copies`` of each read with substitutions at a rate of ``error``, fixed by a draw for each (read, copy, place)."""
    below = int(error * DRAW_PRIME)

    def run(batches):
        for batch in batches:
            data = batch.column(1).cast(pa.large_string()).cast(pa.large_binary()).fill_null(b"")
            ends = np.frombuffer(data.buffers()[1], np.int64)[data.offset : data.offset + len(data) + 1]
            body = np.frombuffer(data.buffers()[2] or b"", np.uint8)
            ids, first = batch.column(0), 0
            while first < len(data):
                last = min(len(data), max(first + 1, int(np.searchsorted(ends, ends[first] + DRAW_BASES, "right")) - 1))
                sizes = np.diff(ends[first : last + 1])
                bases, cuts = body[ends[first] : ends[last]], np.concatenate([[0], np.cumsum(sizes)])
                place = np.arange(1, len(bases) + 1) - np.repeat(cuts[:-1], sizes)
                some = ids.slice(first, last - first)
                known = np.repeat(some.is_valid().to_numpy(zero_copy_only=False), sizes)
                read = some.fill_null(0).to_numpy(zero_copy_only=False)
                for copy in range(copies):
                    start = (read % DRAW_PRIME * DRAW_READ + copy * DRAW_COPY) % DRAW_PRIME
                    mixed = _drawn(_drawn(np.repeat(start, sizes) + place * DRAW_PLACE) * DRAW_MIX)
                    draw = _drawn(mixed * mixed + mixed * DRAW_READ + place)
                    hit = np.flatnonzero((draw < below) & known)
                    out = bases.copy()
                    out[hit] = _ACGT[draw[hit] & 3]
                    text = pa.StringArray.from_buffers(last - first, pa.py_buffer(cuts.astype(np.int32)), pa.py_buffer(out))
                    yield pa.RecordBatch.from_arrays([pc.add(pc.multiply(some, copies), copy), text], names=["read_id", "seq"])
                first = last

    return reads.select(F.col("read_id").cast("long").alias("read_id"), "seq").mapInArrow(run, "read_id long, seq string")


def _drawn(x: np.ndarray) -> np.ndarray:
    """x modulo the prime, for 0 <= x < 2^62: as 2^31 leaves 19, upper bits are folded onto the lower ones."""
    for _ in range(2):
        x = (x & ((1 << 31) - 1)) + 19 * (x >> 31)
    return np.where(x >= DRAW_PRIME, x - DRAW_PRIME, x)


def reads_cov(spark, sf_dir, copies: int = 5, error: float = 0.005) -> DataFrame:
    """Coverage of ``copies`` with errors: the large repeated corpus."""
    return mutated(reads_docs(spark, sf_dir), copies, error)


def heavy_reads(spark, sf_dir, unit: str = "ACTTG", times: int = 20_000) -> DataFrame:
    """Documents and one long tandem repeat."""
    repeat = spark.range(1).select(F.lit(-1).cast("long").alias("read_id"), F.repeat(F.lit(unit), times).alias("seq"))
    return reads_docs(spark, sf_dir).unionByName(repeat)


VIEWS = {
    "reads_docs": reads_docs,
    "reads_docs_exact": reads_docs_exact,
    "reads_pages": reads_pages,
    "reads_small": reads_small,
    "reads_conversations": reads_conversations,
    "reads_short": reads_short,
    "reads_events": reads_events,
    "reads_cov": reads_cov,
    "heavy_reads": heavy_reads,
}
