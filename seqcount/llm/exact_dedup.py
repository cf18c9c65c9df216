"""Exact dedup by a tree-merge of sorted digest runs, in DataFrame operations only."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqcount.llm.common import checkpointed, join_by_weight, text_fingerprint, whole_text, without_rows

FAN_IN = 16


def digest_rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(rid, uid, leaf, digest, witness, fp) of every row, materialised: texts are read and hashed once.

    ``uid`` tells repeated rows apart, ``leaf`` is the partition whose run holds the row.
    """
    text = whole_text(text_col)
    return checkpointed(
        docs.select(
            F.col(id_col).cast("long").alias("rid"),
            F.monotonically_increasing_id().alias("uid"),
            F.spark_partition_id().alias("leaf"),
            F.unhex(F.sha2(text, 256)).alias("digest"),
            F.octet_length(text).alias("witness"),
            text_fingerprint(text_col).alias("fp"),
        )
    )


def merge_runs(rows: DataFrame, keep: str = "smallest", fan_in: int = FAN_IN) -> DataFrame:
    """(digest, witness, fp, best, n): the root run of the tree.

    A leaf is an input partition. Its run, sorted by digest with one entry for each
    different text, is what the map side of the first round makes: the entry is a
    struct, for which Spark plans sort-based aggregation. Each round sends the runs of
    ``fan_in`` neighbouring nodes to their parent, log2(fan_in) binomial steps in one
    exchange, where they're merged in digest order and only the best id is retained.
    A run entry is verified by the byte length and a second, independent fingerprint of
    the text: entries merge only if all three agree. Runs are dealt out by node and
    digest, so a parent's run is spread over the cluster, and a text with any number
    of copies brings at most ``fan_in`` entries to a merge after the first round.
    """
    if fan_in < 2 or fan_in & (fan_in - 1):
        raise ValueError("fan_in must be a power of two")
    if keep not in ("smallest", "largest"):
        raise ValueError("keep must be smallest or largest")
    best = F.min if keep == "smallest" else F.max
    known = F.col("rid").isNull() if keep == "smallest" else F.col("rid").isNotNull()  # rows without an id win last
    runs = rows.select("leaf", "digest", "witness", "fp", F.struct(known.alias("known"), "rid", "uid").alias("best"), F.lit(1).cast("long").alias("n"))
    leaves = (rows.agg(F.max("leaf")).first()[0] or 0) + 1
    step = fan_in.bit_length() - 1
    while True:
        parent = F.shiftright("leaf", step).alias("leaf")
        runs = runs.groupBy(parent, "digest", "witness", "fp").agg(best("best").alias("best"), F.sum("n").alias("n"))
        leaves = -(-leaves // fan_in)
        if leaves <= 1:
            return runs.drop("leaf")


def exact_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "smallest", fan_in: int = FAN_IN) -> DataFrame:
    """One row per input row: rid, uid, keep_id, group_size, kept, text_sha256, fp.

    Texts are equal when their bytes are; null is the empty text. Of equal texts the
    row with the smallest (or largest) id stays; a null id stays only if no row of its
    group has one; of repeats of that very row one stays. An empty table gives none.
    """
    rows = digest_rows(docs, id_col, text_col)
    root = merge_runs(rows, keep, fan_in)
    groups = checkpointed(root.where("n > 1").select("digest", "witness", "fp", F.col("best.rid").alias("keep_id"), F.col("best.uid").alias("keep_uid"), "n"))
    total = rows.count()
    out = join_by_weight(rows, groups, ["digest", "witness", "fp"], "n", total)
    alone = F.col("n").isNull()
    return out.select(
        "rid",
        "uid",
        F.when(alone, F.col("rid")).otherwise(F.col("keep_id")).alias("keep_id"),
        F.coalesce("n", F.lit(1)).cast("long").alias("group_size"),
        (alone | (F.col("uid") == F.col("keep_uid"))).alias("kept"),
        F.lower(F.hex("digest")).alias("text_sha256"),
        "fp",
    )


def drop_exact_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "smallest") -> DataFrame:
    """The rows of ``docs`` that stay, with all their columns."""
    found = exact_dedup(docs, id_col, text_col, keep)
    gone = found.where("not kept").select("rid", "fp", F.col("rid").eqNullSafe(F.col("keep_id")).alias("spare"))
    return without_rows(docs, gone, id_col, text_col)


def op1_exact_dedup(spark, sf_dir: str) -> DataFrame:
    """Every document with the row that stays for its text; see ``exact_dedup`` for null, empty and repeated rows."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    found = exact_dedup(docs, keep="largest")
    return found.select(F.col("rid").alias("doc_id"), "keep_id", "group_size", "kept", "text_sha256")


OP1_SQL = """
SELECT doc_id, max(doc_id) OVER same AS keep_id, count(*) OVER same AS group_size,
       row_number() OVER (PARTITION BY coalesce(text, '') ORDER BY doc_id DESC) = 1 AS kept,
       sha256(coalesce(text, '')) AS text_sha256
FROM documents WINDOW same AS (PARTITION BY coalesce(text, ''))
"""
