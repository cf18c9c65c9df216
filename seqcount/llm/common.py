"""Helpers shared by the training-data operators."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from seqcount.session import delete_folder, new_folder, relieve, work_folder

#: A broadcast of counted rows is used up to this many rows; beyond it the join shuffles.
BROADCAST_ROWS = 2_000_000
#: Rows of narrow tables that a task takes at least, if there are so many.
TASK_ROWS = 1 << 16


def checkpointed(df: DataFrame) -> DataFrame:
    """Cut the lineage with a reliable checkpoint in the folder the session names."""
    work_folder(df.sparkSession)
    out = df.checkpoint()
    relieve(df.sparkSession)
    return out


def few(df: DataFrame, rows: int) -> DataFrame:
    """A narrow frame of about so many rows in no more partitions than these fill, so that small tables don't become many small files."""
    return df.coalesce(max(1, -(-rows // TASK_ROWS)))


def written(df: DataFrame) -> tuple[DataFrame, str]:
    """The frame as a table in the shared folder, and its path.

    For loops: a checkpoint keeps the size estimate of the plan that it cut off, and
    these multiply from join to join; a table has the size of its files.
    """
    path = new_folder(df.sparkSession, "table")
    df.write.parquet(path)
    relieve(df.sparkSession)
    return df.sparkSession.read.schema(df.schema).parquet(path), path


discard, shared_folder = delete_folder, work_folder


def shuffle_parts(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def fresh(df: DataFrame, *bases: str) -> list[str]:
    """Column names that clash with none of the frame's."""
    taken, out = {c.lower() for c in df.columns}, []
    for base in bases:
        name, n = f"__{base}", 0
        while name.lower() in taken:
            n += 1
            name = f"__{base}{n}"
        taken.add(name.lower())
        out.append(name)
    return out


def whole_text(name: str) -> Column:
    """The text column with null as the empty text."""
    return F.coalesce(F.col(name).cast("string"), F.lit(""))


def join_by_weight(left: DataFrame, right: DataFrame, keys: list[str], weight: str, total: int) -> DataFrame:
    """Left join with a table unique in ``keys`` whose ``weight`` is each key's number of left rows.

    Keys that hold more than total / (4 x partitions) of the left rows are fewer than
    4 x partitions whatever the data, so that part of ``right`` is broadcast and their
    left rows stay where they are; all other keys are joined by a shuffle, where no key
    is heavy. ``left`` should be checkpointed: it's read once for either part.
    """
    limit = max(1, total // (4 * max(1, shuffle_parts(left.sparkSession))))
    hot, cold = right.where(F.col(weight) > limit), right.where(F.col(weight) <= limit)
    near = left.join(F.broadcast(hot), keys, "inner")
    far = left.join(F.broadcast(hot.select(*keys)), keys, "left_anti").join(cold, keys, "left")
    return near.unionByName(far)


def without_rows(docs: DataFrame, gone: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """``docs`` less the rows named by ``gone``: (id, fingerprint of the text, spare).

    ``gone`` has one row per dropped row; ``spare`` marks those that repeat the id and
    the text of a row that stays. They're broadcast if counted as few, else shuffled;
    texts move only in the second case. Of rows that repeat an id and a text, one stays,
    whichever; if their other columns differ, which of them stays isn't defined.
    """
    rid, rfp = fresh(docs, "rid", "rfp")
    kept = docs.withColumn(rid, F.col(id_col)).withColumn(rfp, text_fingerprint(text_col))
    gone = gone.toDF(rid, rfp, "spare")
    n_gone, n_spare = gone.agg(F.count("*"), F.count_if("spare")).first()
    few = (lambda d: F.broadcast(d)) if n_gone <= BROADCAST_ROWS else (lambda d: d)
    match = lambda d: [kept[rid].eqNullSafe(d[rid]), kept[rfp] == d[rfp]]
    lone = gone.where(~F.col("spare")).select(rid, rfp).distinct()
    out = kept.join(few(lone), match(lone), "left_anti")
    if n_spare:
        again = gone.where("spare").select(rid, rfp).distinct()
        match2 = [out[rid].eqNullSafe(again[rid]), out[rfp] == again[rfp]]
        once = out.join(few(again), match2, "left_semi").dropDuplicates([rid, rfp])
        out = out.join(few(again), match2, "left_anti").unionByName(once)
    return out.drop(rid, rfp)


def text_fingerprint(text_col: str) -> Column:
    return F.xxhash64(whole_text(text_col), F.octet_length(whole_text(text_col)))
