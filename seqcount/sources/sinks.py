"""Where results go: count tables, spectra, and supermers kept between waves."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqcount.operators.exchange import exchange


def write_counts(counts: DataFrame, path: str, groups: int = 64, mode: str = "error") -> None:
    """Parquet by a hash group of the k-mer, sorted by k-mer within, so that lookups prune files and row groups."""
    keyed = counts.withColumn("part", F.pmod(F.xxhash64("kmer"), F.lit(groups)).cast("int"))
    keyed.repartition(groups, "part").sortWithinPartitions("part", "kmer").write.mode(mode).partitionBy("part").option("compression", "zstd").parquet(path)


def read_counts(spark, path: str) -> DataFrame:
    return spark.read.parquet(path).drop("part")


def lookup_counts(spark, path: str, kmer: int, groups: int = 64) -> DataFrame:
    """One k-mer's row from a written table: its own group's folder, then row groups by range."""
    part = spark.range(1).select(F.pmod(F.xxhash64(F.lit(kmer).cast("long")), F.lit(groups)).cast("int").alias("p")).first()["p"]
    return spark.read.parquet(path).where((F.col("part") == part) & (F.col("kmer") == kmer)).drop("part")


def write_blocks(blocks: DataFrame, path: str, waves: int, mode: str = "error") -> None:
    """Supermer blocks as Parquet by wave: for runs whose exchange is taken in several turns."""
    blocks.withColumn("wave", F.pmod("pid", F.lit(waves))).write.mode(mode).partitionBy("wave").parquet(path)


def read_wave(spark, path: str, wave: int, partitions: int) -> DataFrame:
    """One wave's blocks, exchanged."""
    return exchange(spark.read.parquet(path).where(F.col("wave") == wave).drop("wave"), partitions)


def write_spectrum(spectrum: DataFrame, path: str, kind: str = "csv", mode: str = "error") -> None:
    writer = spectrum.coalesce(1).write.mode(mode)
    writer.option("header", True).csv(path) if kind == "csv" else writer.json(path)


def strip_tags(html):
    """Markup without tags, as a column."""
    return F.regexp_replace(html, "<[^>]*>", " ")


