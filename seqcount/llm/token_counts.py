"""Exact token counts from one histogram of encoded lengths."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqcount.llm.bpe import VOCABULARY, token_lengths
from seqcount.llm.common import checkpointed

BLOCK = 64


def length_histogram(docs: DataFrame, text_col: str = "text", vocabulary: str = VOCABULARY) -> DataFrame:
    """(n_tokens, docs): documents of each encoded length; a null text has length 0. Materialised: texts are encoded once."""
    return checkpointed(token_lengths(docs, text_col, vocabulary).groupBy("n_tokens").agg(F.count("*").alias("docs")))


def suffix_sums(histogram: DataFrame) -> DataFrame:
    """For each length that occurs, what a context limit of that length gives.

    docs_from, tokens_from: documents at least as long, and their tokens; docs_below:
    the rest, so that a quantile is the first length whose docs_below + docs reaches it;
    truncated_tokens: tokens if each document is cut at this length. Sums run within
    blocks of lengths, and over the blocks' totals: n different lengths are n^2 / 2 tokens
    at least, so 10^14 tokens have 1.4 x 10^7 lengths at most, and one task gets a 64th of
    these, whatever the number of documents. An empty histogram gives no rows.
    """
    h = histogram.select("n_tokens", "docs", (F.col("n_tokens") * F.col("docs")).alias("tokens"), F.floor(F.col("n_tokens") / BLOCK).alias("block"))
    totals = h.groupBy("block").agg(F.sum("docs").alias("block_docs"), F.sum("tokens").alias("block_tokens"))
    totals = totals.selectExpr(
        "block",
        "sum(block_docs) over (order by block desc) - block_docs as docs_after",
        "sum(block_tokens) over (order by block desc) - block_tokens as tokens_after",
        "sum(block_docs) over () as all_docs",
        "sum(block_tokens) over () as all_tokens",
    )
    inner = h.selectExpr(
        "*",
        "sum(docs) over (partition by block order by n_tokens desc) as docs_in",
        "sum(tokens) over (partition by block order by n_tokens desc) as tokens_in",
    )
    both = inner.join(totals, "block").withColumn("docs_from", F.col("docs_in") + F.col("docs_after")).withColumn("tokens_from", F.col("tokens_in") + F.col("tokens_after"))
    return both.select(
        "n_tokens",
        "docs",
        "docs_from",
        "tokens_from",
        (F.col("all_docs") - F.col("docs_from")).alias("docs_below"),
        (F.col("all_tokens") - F.col("tokens_from") + F.col("n_tokens") * F.col("docs_from")).alias("truncated_tokens"),
    )


def limit_answers(sums: DataFrame, limits: list[int]) -> DataFrame:
    """(limit_tokens, docs_over, tokens_kept) for any limits, also those that no document has as its length.

    The limits, a stated few, are compared with every length, of which there are few (``suffix_sums``).
    """
    wanted = sums.sparkSession.createDataFrame([(int(x),) for x in limits], "limit_tokens long")
    end = sums.agg(F.max(F.col("docs_below") + F.col("docs")).alias("all_docs"), F.max("truncated_tokens").alias("all_tokens"))
    above = wanted.join(sums, F.col("n_tokens") > F.col("limit_tokens")).groupBy("limit_tokens").agg(F.min_by(F.struct("n_tokens", "docs_from", "truncated_tokens"), "n_tokens").alias("next"))
    kept = F.col("next.truncated_tokens") - (F.col("next.n_tokens") - F.col("limit_tokens")) * F.col("next.docs_from")
    return (
        wanted.join(above, "limit_tokens", "left").join(F.broadcast(end))
        .select("limit_tokens", F.coalesce("next.docs_from", F.lit(0)).alias("docs_over"), F.coalesce(kept, "all_tokens", F.lit(0)).alias("tokens_kept"))
    )


def length_at(sums: DataFrame, shares: list[float]) -> DataFrame:
    """(share, n_tokens): the least length that at least this share of the documents does not exceed."""
    wanted = sums.sparkSession.createDataFrame([(float(x),) for x in shares], "share double")
    reach = F.col("docs_below") + F.col("docs")
    total = sums.agg(F.max(reach).alias("total"))
    return wanted.join(F.broadcast(total)).join(sums, reach >= F.col("share") * F.col("total")).groupBy("share").agg(F.min("n_tokens").alias("n_tokens"))


def op8_token_counts(spark, sf_dir: str) -> DataFrame:
    """The answers for every length that a document has; null and empty texts are of length 0, repeated rows count each."""
    return suffix_sums(length_histogram(spark.read.parquet(f"{sf_dir}/documents.parquet")))
