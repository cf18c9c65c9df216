"""Counting of reads that arrive: running counts, merged batches, windows, state across batches."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqcount.operators.prepare import extract_kmers
from seqcount.plans.flagship import count_kmers
from seqcount.spec import CountSpec

EVENT_FIELDS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def running_counts(reads: DataFrame, spec: CountSpec) -> DataFrame:
    """(kmer, cnt) of a stream of reads; for update or complete mode."""
    return extract_kmers(reads, spec).groupBy("kmer").agg(F.count("*").alias("cnt"))


def merge_batches(reads: DataFrame, spec: CountSpec, folder: str, checkpoint: str):
    """A query writer that counts each micro-batch by the whole method and keeps its counts as one part.

    A part is named by its batch and overwritten if the batch is replayed, so a batch
    counts once however often it runs. ``merged_counts`` adds the parts up.
    """

    def merge(batch: DataFrame, batch_id: int) -> None:
        count_kmers(batch, spec).write.mode("overwrite").parquet(f"{folder}/batch={batch_id}")

    return reads.writeStream.foreachBatch(merge).option("checkpointLocation", checkpoint)


def merged_counts(spark, folder: str) -> DataFrame:
    return spark.read.parquet(folder).groupBy("kmer").agg(F.sum("cnt").alias("cnt"))


def windowed(events: DataFrame, width: str = "1 hour", slide: str | None = None, late: str = "10 minutes") -> DataFrame:
    """(start, event_type, n, total) by tumbling or sliding windows; events later than ``late`` are dropped."""
    span = F.window("ts", width, slide) if slide else F.window("ts", width)
    out = events.withWatermark("ts", late).groupBy(span.alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    return out.select(F.col("w.start").alias("start"), "event_type", "n", "total")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    """(user_id, start, end, n): a user's events without a pause of ``gap``."""
    out = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return out.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def distinct_reads(reads: DataFrame, late: str = "1 hour") -> DataFrame:
    """Reads (read_id, seq, ts), one of each sequence within the watermark."""
    return reads.withWatermark("ts", late).dropDuplicatesWithinWatermark(["seq"])


def reliable_hits(reads: DataFrame, index: DataFrame, spec: CountSpec) -> DataFrame:
    """(read_id, pos, cnt) of arriving reads' k-mers that a static table of counts has."""
    return extract_kmers(reads, spec, ext=True).join(index.select("kmer", "cnt"), "kmer").select("read_id", "pos", "cnt")


def user_kmers(symbols: DataFrame, k: int) -> DataFrame:
    """(user_id, kmer): k-mers of each user's symbols (user_id, at, base) as they arrive.

    The last k - 1 symbols are kept as state, so k-mers that span batches are found.
    Symbols must arrive in order of ``at`` from batch to batch.
    """

    def run(key, frames, state):
        tail = state.get[0] if state.exists else ""
        rows = pd.concat(list(frames)).sort_values("at")
        line = tail + "".join(rows["base"])
        state.update((line[max(0, len(line) - (k - 1)) :] if k > 1 else "",))
        found = [line[i : i + k] for i in range(len(line) - k + 1)]
        yield pd.DataFrame({"user_id": [key[0]] * len(found), "kmer": found})

    return symbols.groupBy("user_id").applyInPandasWithState(run, "user_id long, kmer string", "tail string", "append", "NoTimeout")
