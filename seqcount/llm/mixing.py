"""Mixing sources to target weights by repetition rates and hash-seeded copies."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from seqcount.llm.common import checkpointed, whole_text

WEIGHTS = (5, 2, 1)
SHARE_PERCENT = 150
MOST = 2
SEED = 42
MAX_SOURCES = 1_000_000


def n_words(text_col: str) -> Column:
    """Runs of bytes other than space and tab to carriage return; a null text has none."""
    blank = F.translate(whole_text(text_col), "\t\n\x0b\x0c\r", "     ")
    text = F.trim(blank)
    return F.when(text == "", F.lit(0)).otherwise(F.size(F.split(text, " +"))).cast("long")


def fill_to_level(sizes: list[int], weights: list[int], total_percent: int = SHARE_PERCENT, most: int = MOST) -> list[float]:
    """Targets that share total_percent of all sizes by weight, none above ``most`` times its size.

    Taking the excess of capped sources and dealing it out again by weight until no
    source is above its cap ends at one level: target = min(cap, level x weight). The
    level follows from the sources in order of cap / weight.
    """
    order = sorted(range(len(sizes)), key=lambda i: (most * sizes[i] / weights[i], i))
    capped, open_weight, wanted = 0, sum(weights), total_percent * sum(sizes)
    level = 0.0
    for i in order:
        level = (wanted - 100 * capped) / (100 * open_weight)
        if most * sizes[i] >= level * weights[i]:
            break
        capped, open_weight = capped + most * sizes[i], open_weight - weights[i]
        level = float("inf")
    return [float(min(most * s, level * w)) for s, w in zip(sizes, weights, strict=True)]


def uniform(id_col: Column, text_hash: Column, seed: int) -> Column:
    """52 hash bits of (seed, id, text) as a number in [0, 1); the same on every run and cluster."""
    digest = F.md5(F.concat_ws(":", F.lit(str(seed)), F.coalesce(id_col.cast("string"), F.lit("")), text_hash))
    return F.conv(F.substring(digest, 1, 13), 16, 10).cast("double") / F.lit(float(1 << 52))


def source_targets(docs: DataFrame, source_col: str, size: Column, weights=WEIGHTS) -> DataFrame:
    """(source, source_size, target), one row per source, nulls last; sources, not documents, reach the driver."""
    sums = docs.select(F.col(source_col).cast("string").alias("source"), size.alias("size")).groupBy("source").agg(F.sum("size").alias("source_size"))
    got = [(r["source"], r["source_size"]) for r in sums.limit(MAX_SOURCES + 1).toLocalIterator()]
    if len(got) > MAX_SOURCES:
        raise ValueError(f"more than {MAX_SOURCES} sources: mix by a coarser column")
    got.sort(key=lambda r: (r[0] is None, r[0].encode("utf-8", "surrogatepass") if r[0] is not None else b""))
    targets = fill_to_level([s for _, s in got], [weights[i % len(weights)] for i in range(len(got))])
    rows = [(source, source is None, size, target) for (source, size), target in zip(got, targets, strict=True)]
    return docs.sparkSession.createDataFrame(rows, "m_source string, m_none boolean, source_size long, target double")


def _with_copies(rows: DataFrame, targets: DataFrame, source: Column, u: Column) -> DataFrame:
    """``rows`` with source_size, target and m_copies: floor(rate), and one more if u is below the fraction."""
    on = (F.coalesce(source, F.lit("")) == F.coalesce("m_source", F.lit(""))) & (source.isNull() == F.col("m_none"))
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    return rows.join(F.broadcast(targets), on, "left").withColumn("m_copies", (F.floor(rate) + (u < rate - F.floor(rate)).cast("long")).cast("int"))


def mix_sizes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", seed: int = SEED) -> DataFrame:
    """(rid, m_size, source_size, target, m_copies) of every row, those without a copy too.

    rate = target / source size; a row has floor(rate) copies and one more if its hash
    number is below the fraction. So no row has more than MOST copies, and each
    source's words come near its target. A source of no words has rate 0. Rows that
    repeat an id and a text share their hash number. Texts are read once; nothing is
    shuffled but the sums of the sources.
    """
    u = uniform(F.col(id_col), F.md5(whole_text(text_col)), seed)
    rows = checkpointed(docs.select(F.col(id_col).cast("long").alias("rid"), F.col(source_col).cast("string").alias("source"), n_words(text_col).alias("m_size"), u.alias("u")))
    targets = source_targets(rows, "source", F.col("m_size"))
    return _with_copies(rows, targets, F.col("source"), F.col("u")).select("rid", "m_size", "source_size", "target", "m_copies")


def mix_sources(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", seed: int = SEED) -> DataFrame:
    """The mix itself: each row of ``docs``, with its own columns, as many times as it has copies."""
    names = {c: f"c{i}" for i, c in enumerate(docs.columns)}
    plain = docs.toDF(*names.values())
    text, source = names[text_col], F.col(names[source_col]).cast("string")
    targets = source_targets(plain, names[source_col], n_words(text))
    rows = _with_copies(plain, targets, source, uniform(F.col(names[id_col]), F.md5(whole_text(text)), seed)).where("m_copies > 0")
    copies = rows.withColumn("m_copy", F.explode(F.array_repeat(F.lit(True), F.col("m_copies"))))
    return copies.select(*[F.col(n).alias(c) for c, n in names.items()])


def op10_mixing(spark, sf_dir: str) -> DataFrame:
    """Every document with the words that the mix takes of it; null texts have none, null is a source, repeats share their draw."""
    found = mix_sizes(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return found.select(
        F.col("rid").alias("doc_id"), F.col("m_size").alias("size"), "source_size", "target", (F.col("m_size") * F.col("m_copies")).alias("taken")
    )


#: The cap binds where cap / weight is least, so the level is that of the first source in this order that keeps its share.
OP10_SQL = r"""
WITH d AS (
  SELECT doc_id, source, CAST(len(list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda w: w <> '')) AS BIGINT) AS size,
         md5(concat_ws(':', '42', coalesce(CAST(doc_id AS VARCHAR), ''), md5(coalesce(text, '')))) AS h
  FROM documents),
s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source),
w AS (SELECT *, CASE (row_number() OVER (ORDER BY source COLLATE "C" NULLS LAST) - 1) % 3 WHEN 0 THEN 5 WHEN 1 THEN 2 ELSE 1 END AS weight,
             row_number() OVER (ORDER BY source COLLATE "C" NULLS LAST) AS i FROM s),
o AS (SELECT *, row_number() OVER (ORDER BY 2 * source_size / weight, i) AS turn, CAST(coalesce(sum(2 * source_size) OVER before, 0) AS BIGINT) AS capped,
             CAST(sum(weight) OVER () - coalesce(sum(weight) OVER before, 0) AS BIGINT) AS open_weight,
             CAST(150 * sum(source_size) OVER () AS BIGINT) AS wanted
      FROM w WINDOW before AS (ORDER BY 2 * source_size / weight, i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
v AS (SELECT *, CAST(wanted - 100 * capped AS DOUBLE) / CAST(100 * open_weight AS DOUBLE) AS level FROM o),
l AS (SELECT coalesce(arg_min(level, turn) FILTER (WHERE 2 * source_size >= level * weight), CAST('inf' AS DOUBLE)) AS level FROM v),
t AS (SELECT source, source_size, least(CAST(2 * source_size AS DOUBLE), l.level * weight) AS target FROM w, l),
r AS (SELECT d.doc_id, d.size, t.source_size, t.target, CASE WHEN t.source_size > 0 THEN t.target / t.source_size ELSE 0.0 END AS rate,
             CAST(CAST('0x' || substr(h, 1, 13) AS BIGINT) AS DOUBLE) / 4503599627370496.0 AS u
      FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source)
SELECT doc_id, size, source_size, target,
       CAST(size * (floor(rate) + CASE WHEN u < rate - floor(rate) THEN 1 ELSE 0 END) AS BIGINT) AS taken FROM r
"""
