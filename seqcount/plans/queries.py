"""Every registered query and its SQL; each runs over whole tables."""

from __future__ import annotations

import gc as collector
from functools import partial, reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from seqcount.functions import sqlapi
from seqcount.functions.alphabet import bases_to_text, fold_text, gc, pack, revcomp, text_to_bases, unpack
from seqcount.functions.scores import score_column
from seqcount.operators import baselines, counting, exchange, index, labelled, metrics, sketches
from seqcount.operators import supermers as sm
from seqcount.operators.prepare import extract_kmers, extract_kmers_native
from seqcount.operators.tasks import loads, task_sizes
from seqcount.plans import flagship, sql
from seqcount.session import delete_folder, new_folder, relieve
from seqcount.sources import fasta, sinks
from seqcount.sources import reads as src
from seqcount.sources.sinks import strip_tags
from seqcount.spec import SCORES, CountSpec
from seqcount.streaming import streams

K31 = CountSpec(k=31)
#: Longer than any read of the given tables, for results that show where chunks end.
WHOLE = 1 << 20
QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(name: str, text: str | None = None):
    """Register a query, with SQL for the same columns if there is some."""

    def keep(make):
        QUERIES[name] = make
        if text:
            SQL[name] = text
        return make

    return keep


def decoded(counts: DataFrame, k: int) -> DataFrame:
    return counts.withColumn("kmer", unpack(F.col("kmer"), k))


# --- the method

for _k in (17, 31, 55):

    @query(f"kmer_spectrum_k{_k}", sql.spectrum(sql.counts(_k)))
    def _(spark, d, k=_k):
        return flagship.count_kmers(src.reads_docs(spark, d), CountSpec(k=k), as_spectrum=True)


@query("kmer_counts_2_50_k31", f"SELECT * FROM ({sql.counts(31)}) WHERE cnt BETWEEN 2 AND 50")
def _(spark, d):
    return decoded(flagship.count_kmers(src.reads_docs(spark, d), K31, ranged=True), 31)


@query("kmer_counts_k55_pages", f"SELECT * FROM ({sql.counts(55, sql.reads('pages'))}) WHERE cnt BETWEEN 2 AND 50")
def _(spark, d):
    return decoded(flagship.count_kmers(src.reads_pages(spark, d), CountSpec(k=55), ranged=True), 55)


@query("kmer_top20", f"SELECT * FROM ({sql.counts(31)}) ORDER BY cnt DESC, kmer LIMIT 20")
def _(spark, d):
    return decoded(counting.top_k(flagship.count_kmers(src.reads_docs(spark, d), K31), 20), 31)


@query("kmer_native_small", sql.counts(31, sql.reads("small")))
def _(spark, d):
    return extract_kmers_native(src.reads_small(spark, d), 31).groupBy("kmer").agg(F.count("*").alias("cnt"))


@query("kmer_locations_small", f"SELECT kmer, read_id, pos FROM ({sql.kmers(31, sql.reads('small'))})")
def _(spark, d):
    return decoded(extract_kmers(src.reads_small(spark, d), K31, ext=True), 31)


@query("kmer_index", f"SELECT kmer, cnt, count(DISTINCT read_id) AS reads, min(read_id) AS first_read, CAST(sum(pos) AS BIGINT) AS places FROM ({sql.occurrences(K31)}) GROUP BY kmer, cnt")
def _(spark, d):
    found = decoded(index.kmer_index(src.reads_docs(spark, d), K31), 31)
    total = F.aggregate("occ", F.lit(0).cast("long"), lambda a, x: a + x["pos"])
    return found.select("kmer", "cnt", F.size(F.array_distinct("occ.read_id")).cast("long").alias("reads"), F.array_min("occ.read_id").alias("first_read"), total.alias("places"))


@query("pack_words_small", f"SELECT DISTINCT kmer, {sql.packed('kmer')} AS word, kmer AS back FROM ({sql.kmers(31, sql.reads('small'))})")
def _(spark, d):
    kmers = extract_kmers_native(src.reads_small(spark, d), 31).select("kmer").distinct()
    return kmers.withColumn("word", pack(F.col("kmer"), 31)).withColumn("back", unpack(F.col("word"), 31))


@query("lossless_reads", "SELECT doc_id, md5(text) AS text_md5, 4 * strlen(text) AS bases FROM documents")
def _(spark, d):
    docs = src.table(spark, d, "documents").select("doc_id", text_to_bases(F.col("text")).alias("seq"))
    return docs.select("doc_id", F.md5(bases_to_text(F.col("seq"))).alias("text_md5"), F.length("seq").cast("long").alias("bases"))


# --- scores and minimizers


@query("mmer_murmur_scores", f"SELECT score % 1024 AS part, count(*) AS mmers, CAST(sum(score) AS BIGINT) AS scores, bit_xor(code) AS words FROM (SELECT DISTINCT code, score FROM ({sql.mmer_scores(K31)})) GROUP BY part")
def _(spark, d):
    base = extract_kmers(src.reads_docs(spark, d), CountSpec(k=K31.m, m=11)).select("kmer").distinct()
    scored = base.withColumn("score", score_column(F.col("kmer"), K31.m))
    return scored.groupBy(F.pmod("score", F.lit(1024)).alias("part")).agg(F.count("*").alias("mmers"), F.sum("score").alias("scores"), F.bit_xor("kmer").alias("words"))


_BY_TASK = "SELECT task, count(*) AS n_kmers, CAST(sum(score) AS BIGINT) AS scores FROM ({}) GROUP BY task"


def _by_task(minimizers: DataFrame) -> DataFrame:
    return minimizers.groupBy(F.pmod("score", F.lit(K31.s)).alias("task")).agg(F.count("*").alias("n_kmers"), F.sum("score").alias("scores"))


for _method in ("block", "deque", "rescan", "naive"):

    @query(f"minimizer_{_method}", _BY_TASK.format(sql.minimizers(K31)))
    def _(spark, d, method=_method):
        return _by_task(sm.minimizers_arrow(src.reads_docs(spark, d), K31, method))


@query("minimizer_window", _BY_TASK.format(sql.minimizers(K31)))
def _(spark, d):
    return _by_task(sm.minimizers_window(src.reads_docs(spark, d), K31))


@query("minimizer_native_small", _BY_TASK.format(sql.minimizers(K31, sql.reads("small"))))
def _(spark, d):
    return _by_task(sm.minimizers_naive(src.reads_small(spark, d), K31))


# --- supermers, tasks, exchange

_SUPERS = f"SELECT task, count(*) AS supermers, CAST(sum(n_bases - {K31.k - 1}) AS BIGINT) AS n_kmers, CAST(sum(ceil(n_bases / 4) + 2) AS BIGINT) AS bytes FROM ({{}}) GROUP BY task"


def _supers(spark, d, spec, view=src.reads_docs):
    rows = sm.build_supermers(view(spark, d), spec.but(chunk=WHOLE))
    return task_sizes(rows).select(F.col("task").cast("long").alias("task"), F.col("n_supermers").alias("supermers"), "n_kmers", "bytes")


for _name, _spec in (("task", K31), ("minimizer", K31.but(break_on="minimizer")), ("lex", K31.but(score="lex")), ("lex_mod", K31.but(score="lex_mod"))):
    query(f"supermers_{_name}", _SUPERS.format(sql.supermers(_spec)))(partial(_supers, spec=_spec))


@query("supermer_rows_small", f"SELECT read_id, CAST(task AS INTEGER) AS task, start, n_bases, substr(seq, start + 1, n_bases) AS bases FROM ({sql.supermers(K31, sql.reads('small'))}) JOIN ({sql.reads('small')}) USING (read_id)")
def _(spark, d):
    rows = sm.supermer_bases(sm.build_supermers(src.reads_small(spark, d), K31.but(chunk=WHOLE)))
    return rows.select("read_id", "task", F.col("start").cast("long").alias("start"), F.col("n_bases").cast("long").alias("n_bases"), "bases")


@query("supermers_by_window", _SUPERS.format(sql.supermers(K31)))
def _(spark, d):
    n = F.col("n_bases")
    rows = sm.supermers_window(src.reads_docs(spark, d), K31)
    return rows.groupBy(F.col("task").cast("long").alias("task")).agg(F.count("*").alias("supermers"), F.sum(n - 30).cast("long").alias("n_kmers"), F.sum(F.ceil(n / 4) + 2).cast("long").alias("bytes"))


@query("supermers_expanded", sql.spectrum(sql.counts(31)))
def _(spark, d):
    return counting.spectrum(baselines.count_heavy_native(sm.build_supermers(src.reads_docs(spark, d), K31), K31))


_STATS = f"SELECT count(*) AS supermers, CAST(sum(n_bases - {K31.k - 1}) AS BIGINT) AS kmers, round(avg(n_bases), 6) AS mean_bases, CAST(max(n_bases) AS INTEGER) AS max_bases, CAST(sum(ceil(n_bases / 4) + 2) AS BIGINT) AS bytes FROM ({{}})"
for _m in (7, 13, 17, 21, 27):

    @query(f"supermer_stats_m{_m}", _STATS.format(sql.supermers(CountSpec(k=31, m=_m))))
    def _(spark, d, m=_m):
        return metrics.supermer_stats(sm.build_supermers(src.reads_docs(spark, d), CountSpec(k=31, m=m, chunk=WHOLE)), 31)


_SIZES = "SELECT task, count(*) AS n_kmers FROM ({}) GROUP BY task"
_BALANCE = "SELECT '{}' AS score, count(*) AS tasks, round(avg(n_kmers), 6) AS mean, round(stddev_pop(n_kmers), 6) AS stddev, round(max(n_kmers) / min(n_kmers), 6) AS max_min, round(max(n_kmers) / avg(n_kmers), 6) AS max_mean FROM ({})"


@query("task_sizes_256", f"SELECT CAST(task AS INTEGER) AS task, n_kmers FROM ({_SIZES.format(sql.minimizers(K31))})")
def _(spark, d):
    return task_sizes(sm.build_supermers(src.reads_docs(spark, d), K31)).select("task", "n_kmers")


@query("task_balance_by_score", " UNION ALL ".join(_BALANCE.format(s, _SIZES.format(sql.minimizers(K31.but(score=s)))) for s in SCORES))
def _(spark, d):
    of = lambda s: metrics.balance_of(task_sizes(sm.build_supermers(src.reads_docs(spark, d), K31.but(score=s)))).withColumn("score", F.lit(s))
    return reduce(DataFrame.unionByName, map(of, SCORES))


_BEST = {"left": "{s: score, p: pos}", "right": "{s: score, p: -pos}", "lex": "{s: score, c: code, p: -pos}"}
_TIES = f"SELECT * FROM (SELECT min({{best}}) OVER w AS best, count(*) OVER w AS seen FROM ({sql.mmer_scores(K31.but(m=3), sql.reads('small'))}) WINDOW w AS (PARTITION BY read_id ORDER BY pos RANGE BETWEEN CURRENT ROW AND {K31.but(m=3).w - 1} FOLLOWING)) WHERE seen = {K31.but(m=3).w}"


@query("minimizer_ties_small", " UNION ALL ".join(f"SELECT '{t}' AS tie, count(*) AS n_kmers, CAST(sum(best.s) AS BIGINT) AS scores, CAST(sum(abs(best.p)) AS BIGINT) AS places FROM ({_TIES.format(best=b)})" for t, b in _BEST.items()))
def _(spark, d):
    """Where minimizers lie, of equal scores the first, the last, or the least m-mer's; m = 3 makes many ties."""
    of = lambda t: sm.minimizers_arrow(src.reads_small(spark, d), K31.but(m=3, tie=t)).agg(F.count("*").alias("n_kmers"), F.sum("score").alias("scores"), F.sum("mmer_pos").alias("places")).withColumn("tie", F.lit(t))
    return reduce(DataFrame.unionByName, map(of, _BEST))


@query(
    "heavy_tasks",
    f"WITH t AS ({_SIZES.format(sql.minimizers(K31, sql.reads('heavy')))}) SELECT CAST(task AS INTEGER) AS task, n_kmers, round(n_kmers / mean, 6) AS times_mean FROM t, (SELECT avg(n_kmers) AS mean FROM t) WHERE n_kmers > 3 * mean",
)
def _(spark, d):
    return metrics.heavy_stats(task_sizes(sm.build_supermers(src.heavy_reads(spark, d), K31)), 3.0)


@query("heavy_kmerlist_count", sql.spectrum(sql.counts(31, sql.reads("heavy"))))
def _(spark, d):
    return flagship.count_kmers(src.heavy_reads(spark, d), K31, as_spectrum=True, share=1.0)


@query("heavy_default_count", sql.spectrum(sql.counts(31, sql.reads("heavy"))))
def _(spark, d):
    return flagship.count_kmers(src.heavy_reads(spark, d), K31, as_spectrum=True)


@query("heavy_default_tasks", f"WITH t AS ({_SIZES.format(sql.minimizers(K31, sql.reads('heavy')))}) SELECT CAST(task AS INTEGER) AS task FROM t WHERE n_kmers > 3 * (SELECT avg(n_kmers) FROM t)")
def _(spark, d):
    """The heavy tasks that the plan finds by itself, from its sample of pieces."""
    return spark.createDataFrame([(int(t),) for t in flagship.make_plan(src.heavy_reads(spark, d), K31).heavy], "task int")


@query("heavy_supermer_list", sql.spectrum(sql.counts(31, sql.reads("heavy"))))
def _(spark, d):
    return counting.spectrum(baselines.count_supermer_list(src.heavy_reads(spark, d), K31))


@query(
    "task_assignment",
    f"""WITH t AS ({_SIZES.format(sql.minimizers(K31, sql.reads('heavy')))}), a AS (SELECT unnest(range(0, {K31.s})) AS task), s AS (SELECT a.task, coalesce(n_kmers, 0) AS n_kmers FROM a LEFT JOIN t USING (task))
SELECT CAST(task AS INTEGER) AS task, n_kmers, n_kmers > 3 * (SELECT avg(n_kmers) FROM s) AS heavy, true AS placed, true AS within FROM s""",
)
def _(spark, d):
    """(task, n_kmers, heavy, placed, within) as the driver decides it from all reads: each has a partition, whose load is near the least level possible."""
    plan = flagship.make_plan(src.heavy_reads(spark, d), K31, partitions=16, share=1.0)
    light = plan.sizes.copy()
    light[plan.heavy] = 0
    load = loads(light, plan.placed, 16)
    level, heavy = 1.25 * max(load.mean(), light.max()), set(plan.heavy.tolist())
    rows = [(t, int(n), t in heavy, 0 <= int(p) < 16, bool(load[p] <= level)) for t, (n, p) in enumerate(zip(plan.sizes, plan.placed, strict=True))]
    return spark.createDataFrame(rows, "task int, n_kmers long, heavy boolean, placed boolean, within boolean")


_BYTES = "SELECT {k} AS k, CAST(sum(n_bases - {k1}) AS BIGINT) AS kmers, CAST(sum(n_bases - {k1}) * {word} AS BIGINT) AS kmer_bytes, count(*) AS supermers, CAST(sum(ceil(n_bases / 4) + 2) AS BIGINT) AS supermer_bytes, round(1 - sum(ceil(n_bases / 4) + 2) / (sum(n_bases - {k1}) * {word}), 6) AS saved FROM ({rows})"


@query("exchange_bytes", " UNION ALL ".join(_BYTES.format(k=k, k1=k - 1, word=8 if k <= 31 else 16, rows=sql.supermers(CountSpec(k=k))) for k in (17, 31, 55)))
def _(spark, d):
    of = lambda k: exchange.exchange_bytes(sm.build_supermers(src.reads_docs(spark, d), CountSpec(k=k, chunk=WHOLE)), CountSpec(k=k)).withColumn("k", F.lit(k))
    return reduce(DataFrame.unionByName, map(of, (17, 31, 55)))


_BATCHES = (10_000, 20_000, 40_000, 80_000, 160_000)


@query(
    "rounds_cost",
    f"""WITH p AS (SELECT read_id % 16 AS src, task % 16 AS dst, sum(ceil(n_bases / 4) + 2) AS bytes FROM ({sql.supermers(K31)}) GROUP BY ALL),
t AS (SELECT sum(bytes) AS sent, max(bytes) AS most FROM p), b AS (SELECT unnest([{', '.join(map(str, _BATCHES))}]) AS batch)
SELECT CAST(batch AS BIGINT) AS batch, CAST(ceil(most / batch) AS BIGINT) AS rounds, CAST(sent AS BIGINT) AS sent, CAST(ceil(most / batch) * batch * 256 AS BIGINT) AS padded, round(ceil(most / batch) * batch * 256 / sent - 1, 6) AS waste FROM t, b""",
)
def _(spark, d):
    pairs = exchange.pair_bytes(sm.build_supermers(src.reads_docs(spark, d), K31.but(chunk=WHOLE)), 16, 16)
    return exchange.round_costs(pairs, list(_BATCHES), 16)


_DELTA = "SELECT read_id - lag(read_id) OVER w AS dr, pos - lag(pos) OVER w AS dp FROM ({}) WINDOW w AS (PARTITION BY task ORDER BY read_id, pos)"


@query(
    "ext_delta_bytes",
    f"""WITH d AS ({_DELTA.format(sql.minimizers(K31))}), f AS (SELECT coalesce(dr BETWEEN -128 AND 127, false) AS r, coalesce(dp BETWEEN -128 AND 127, false) AS p FROM d)
SELECT 'pair' AS mode, count(*) AS occurrences, count(*) * 8 AS raw_bytes, CAST(sum(CASE WHEN r AND p THEN 3 ELSE 9 END) AS BIGINT) AS coded_bytes FROM f
UNION ALL SELECT 'per_field', count(*), count(*) * 8, CAST(sum(1 + CASE WHEN r THEN 1 ELSE 4 END + CASE WHEN p THEN 1 ELSE 4 END) AS BIGINT) FROM f""",
)
def _(spark, d):
    return exchange.location_bytes(sm.expand_supermers(sm.build_supermers(src.reads_docs(spark, d), K31), K31, ("task", "read_id", "pos")))


@query("ext_codec_roundtrip", f"SELECT task, count(*) AS n, CAST(sum(read_id) AS BIGINT) AS reads, CAST(sum(pos) AS BIGINT) AS places FROM ({sql.minimizers(K31)}) GROUP BY task")
def _(spark, d):
    rows = sm.expand_supermers(sm.build_supermers(src.reads_docs(spark, d), K31), K31, ("task", "read_id", "pos"))
    back = exchange.decode_ext(exchange.encode_ext(rows))
    return back.groupBy(F.col("task").cast("long").alias("task")).agg(F.count("*").alias("n"), F.sum("read_id").alias("reads"), F.sum(F.col("pos").cast("long")).alias("places"))


# --- baselines: all give one spectrum

_ONE = sql.spectrum(sql.counts(31))
for _name, _make in (
    ("dist_hash", baselines.count_dist_hash),
    ("dist_hash_partial", partial(baselines.count_dist_hash, partial=True)),
    ("supermer_hash", baselines.count_supermer_hash),
    ("naive_minimizer", partial(baselines.count_supermer_hash, naive=True)),
    ("range_sort", baselines.count_range_sort),
    ("hash_exchange_sort", baselines.count_hash_exchange_sort),
    ("sort_timsort", partial(baselines.count_hash_exchange_sort, sort_mode="timsort")),
    ("sort_aggregate", partial(baselines.count_hash_exchange_sort, sort_mode="sortagg")),
    ("sort_aux_radix", partial(flagship.count_kmers, method="aux_radix")),
    ("sort_inplace", partial(flagship.count_kmers, method="inplace")),
    ("sort_spilling", partial(flagship.count_kmers, method="spark_radix")),
    ("second_hash", lambda reads, spec: flagship.count_kmers(reads, spec.but(dest="second_hash"))),
    ("merge_last", baselines.count_merge_last),
    ("shared_sort", baselines.count_shared_sort),
    ("shared_sort_disk", partial(baselines.count_shared_sort, ram_only=False)),
    ("explicit_hh", baselines.count_explicit_hh),
    ("thread_owned", baselines.count_thread_owned),
    ("longest_first", partial(flagship.count_kmers, policy="longest_first")),
):

    @query(f"count_{_name}", _ONE)
    def _(spark, d, make=_make):
        return counting.spectrum(make(src.reads_docs(spark, d), K31))


for _sort in ("inplace", "aux_radix", "spark_radix"):

    @query(f"count_sort_{_sort}_k55", sql.spectrum(sql.counts(55)))
    def _(spark, d, sort=_sort):
        return flagship.count_kmers(src.reads_docs(spark, d), CountSpec(k=55), method=sort, as_spectrum=True)


@query("count_two_pass", f"SELECT * FROM ({_ONE}) WHERE cnt > 1")
def _(spark, d):
    return counting.spectrum(baselines.count_two_pass(src.reads_docs(spark, d), K31))


@query("count_drop_singletons", f"SELECT * FROM ({_ONE}) WHERE cnt > 1")
def _(spark, d):
    return counting.spectrum(flagship.count_kmers(src.reads_docs(spark, d), K31.but(lo=2, hi=1 << 40), ranged=True))


@query("count_cbf_bounds", f"SELECT count(*) AS keys, 0::BIGINT AS under, true AS few_over FROM ({sql.counts(31)})")
def _(spark, d):
    """Keys, keys counted too low (none), and whether under one in five is counted too high by a counting filter of 2^22 slots for each partition."""
    docs = src.reads_docs(spark, d)
    found = metrics.over_counts(baselines.count_cbf(docs, K31), baselines.count_dist_hash(docs, K31))
    return found.select("keys", "under", (F.col("over") < F.col("keys") / 5).alias("few_over"))


@query("hll_distinct", f"SELECT count(*) AS exact, true AS close, true AS small FROM ({sql.counts(31)})")
def _(spark, d):
    """The number of different k-mers; whether the sketch's estimate is within 5 % and the sketch under 8 kB."""
    kmers = extract_kmers(src.reads_docs(spark, d), K31)
    both = sketches.distinct_estimate(kmers).join(F.broadcast(kmers.agg(F.count_distinct("kmer").alias("exact"))))
    return both.select("exact", (F.abs(F.col("estimate") - F.col("exact")) <= 0.05 * F.col("exact")).alias("close"), (F.col("sketch_bytes") < 8192).alias("small"))


@query(
    "ablation_same_result",
    f"WITH t AS ({_SIZES.format(sql.minimizers(K31, sql.reads('heavy')))}), h AS (SELECT count(*) AS n FROM t WHERE n_kmers > 3 * (SELECT avg(n_kmers) FROM t)), s AS ({sql.spectrum(sql.counts(31, sql.reads('heavy')))}) "
    + " UNION ALL ".join(f"SELECT '{r}' AS rung, {'(SELECT n FROM h)' if r == 'heavy_tasks' else '0::BIGINT'} AS heavy, * FROM s" for r in flagship.RUNGS),
)
def _(spark, d):
    """Every rung's spectrum, and the heavy tasks that its plan counts by themselves.

    Text is folded once for all passes, and a rung is counted before the next begins, so
    the exchange of one alone is on disk.
    """
    folder = new_folder(spark, "reads")
    src.heavy_reads(spark, d).write.parquet(folder)
    reads = spark.read.schema("read_id long, seq string").parquet(folder)

    def of(name):
        spec, plan = flagship.rung_plan(reads, K31, name, 16)
        collector.collect()  # frames are in cycles and hold their exchange, and listeners the last query, now that of the sizes
        relieve(spark, 0)
        return flagship.count_kmers(reads, spec, plan=plan, as_spectrum=True).select(F.lit(name).alias("rung"), F.lit(len(plan.heavy)).cast("long").alias("heavy"), "cnt", "n_kmers").checkpoint()

    found = reduce(DataFrame.unionByName, map(of, flagship.RUNGS))
    delete_folder(spark, folder)
    return found


@query("tasks_per_worker_same_result", " UNION ALL ".join(f"SELECT {t} AS per_worker, * FROM ({_ONE})" for t in (1, 2, 3)))
def _(spark, d):
    of = lambda t: flagship.count_kmers(src.reads_docs(spark, d), K31.but(s=16 * t), 16, as_spectrum=True).withColumn("per_worker", F.lit(t))
    return reduce(DataFrame.unionByName, map(of, (1, 2, 3)))


@query("canonical_counts", f"SELECT cnt, count(*) AS n_kmers FROM (SELECT least(kmer, reverse(translate(kmer, 'ACGT', 'TGCA'))) AS c, count(*) AS cnt FROM ({sql.kmers(31)}) GROUP BY c) GROUP BY cnt")
def _(spark, d):
    return flagship.count_kmers(src.reads_docs(spark, d), K31.but(canonical=True), as_spectrum=True)


_INDEXED = f"SELECT kmer, cnt, count(DISTINCT read_id) AS reads, min(read_id) AS first_read, CAST(sum(pos) AS BIGINT) AS places FROM ({sql.occurrences(K31)}) GROUP BY kmer, cnt"


def _index_rows(found: DataFrame) -> DataFrame:
    total = F.aggregate("occ", F.lit(0).cast("long"), lambda a, x: a + x["pos"])
    return decoded(found, 31).select("kmer", "cnt", F.size(F.array_distinct("occ.read_id")).cast("long").alias("reads"), F.array_min("occ.read_id").alias("first_read"), total.alias("places"))


for _locations in ("plain", "pair"):

    @query(f"kmer_index_{_locations}", _INDEXED)
    def _(spark, d, locations=_locations):
        return _index_rows(index.kmer_index(src.reads_docs(spark, d), K31, locations=locations))


@query("kmer_index_heavy", f"SELECT kmer, cnt, count(DISTINCT read_id) AS reads, min(read_id) AS first_read, CAST(sum(pos) AS BIGINT) AS places FROM ({sql.occurrences(K31, sql.reads('heavy'))}) GROUP BY kmer, cnt")
def _(spark, d):
    """Locations where a task is heavy: its frequent k-mers are out of range, the rest are found."""
    return _index_rows(index.kmer_index(src.heavy_reads(spark, d), K31))


@query("kmer_index_two_pass", _INDEXED)
def _(spark, d):
    """Locations by the two-pass way: the second exchange carries those of repeated k-mers alone."""
    return _index_rows(baselines.index_two_pass(src.reads_docs(spark, d), K31))


# --- uses of counts and locations


@query(
    "overlap_candidates",
    f"""WITH o AS ({sql.occurrences(K31)}) SELECT a.read_id AS read_a, b.read_id AS read_b, count(*) AS shared, CAST(min(b.pos - a.pos) AS INTEGER) AS min_diff, CAST(max(b.pos - a.pos) AS INTEGER) AS max_diff
FROM o a JOIN o b ON a.kmer = b.kmer AND a.read_id < b.read_id GROUP BY ALL HAVING count(*) >= 2""",
)
def _(spark, d):
    return index.overlap_candidates(index.kmer_index(src.reads_docs(spark, d), K31), 2)


@query("overlap_candidates_banded", f"""WITH o AS ({sql.occurrences(K31)}) SELECT a.read_id AS read_a, b.read_id AS read_b, count(*) AS shared, CAST(min(b.pos - a.pos) AS INTEGER) AS min_diff, CAST(max(b.pos - a.pos) AS INTEGER) AS max_diff
FROM o a JOIN o b ON a.kmer = b.kmer AND a.read_id < b.read_id AND abs(b.pos - a.pos) <= 64 GROUP BY ALL HAVING count(*) >= 2""")  # fmt: skip
def _(spark, d):
    return index.overlap_candidates(index.kmer_index(src.reads_docs(spark, d), K31), 2, band=64)


@query("index_lookup_benchmark", f"SELECT kmer, cnt FROM ({sql.counts(31)}) WHERE cnt BETWEEN 2 AND 50 AND kmer IN (SELECT kmer FROM ({sql.kmers(31, sql.reads('small'))}))")
def _(spark, d):
    asked = extract_kmers(src.reads_small(spark, d), K31).distinct()
    return decoded(index.lookup(index.kmer_index(src.reads_docs(spark, d), K31), asked), 31).select("kmer", "cnt")


_DOC_KMERS = sql.kmers(31, f"SELECT doc_id AS read_id, lang, source, {sql.fold('text')} AS seq FROM documents", "lang, source,")


def _doc_kmers(spark, d) -> DataFrame:
    docs = src.table(spark, d, "documents").select(F.col("doc_id").alias("read_id"), "lang", "source")
    return extract_kmers(src.reads_docs(spark, d), K31, ext=True).join(docs, "read_id")


def _labelled_docs(spark, d, *columns: str) -> tuple[DataFrame, list[tuple]]:
    """Documents as reads (label, seq) and the values of ``columns`` that each label, a place in the list, stands for."""
    docs = src.table(spark, d, "documents")
    values = [tuple(r) for r in docs.select(*columns).distinct().collect()]
    if not values:
        return docs.selectExpr("0L as label", "text as seq"), values
    names = spark.createDataFrame([(i, *v) for i, v in enumerate(values)], "label long, " + ", ".join(f"v{i} string" for i in range(len(columns))))
    texts = src.spread(docs.select("text", *columns))
    match = reduce(lambda a, b: a & b, (texts[c].eqNullSafe(names[f"v{i}"]) for i, c in enumerate(columns)))
    return texts.join(F.broadcast(names), match).select("label", fold_text(F.col("text")).alias("seq")), values


def _named(spark, values: list[tuple], *columns: str) -> DataFrame:
    """(label, columns) of the values; a null value too has a label."""
    return spark.createDataFrame([(i, *v) for i, v in enumerate(values)], "label long, " + ", ".join(f"{c} string" for c in columns))


@query("contamination_semi", f"SELECT read_id, count(*) AS hits FROM ({sql.kmers(31)}) WHERE kmer IN (SELECT kmer FROM ({sql.kmers(31, sql.reads('small'))})) GROUP BY read_id")
def _(spark, d):
    known = extract_kmers(src.reads_small(spark, d), K31).distinct()
    return extract_kmers(src.reads_docs(spark, d), K31, ext=True).join(known, "kmer", "left_semi").groupBy("read_id").agg(F.count("*").alias("hits"))


@query("source_unique_anti", f"WITH s AS (SELECT DISTINCT source, kmer FROM ({_DOC_KMERS})) SELECT source, count(*) AS only_here FROM s WHERE kmer NOT IN (SELECT kmer FROM s GROUP BY kmer HAVING count(*) > 1) GROUP BY source")
def _(spark, d):
    reads, sources = _labelled_docs(spark, d, "source")

    def alone(heads, kmer, label, n):
        only = label[heads[np.diff(np.append(heads, len(n))) == 1]]
        found, times = np.unique(only, return_counts=True)
        return pa.RecordBatch.from_arrays([pa.array(found, pa.int64()), pa.array(times, pa.int64())], names=["label", "n"])

    sums = labelled.reduce_labelled(reads, K31, alone, "label long, n long").groupBy("label").agg(F.sum("n").alias("only_here"))
    return sums.join(F.broadcast(_named(spark, sources, "source")), "label").select("source", "only_here")


@query("spectrum_by_lang_rollup", f"SELECT lang, source, count(*) AS kmers, count(DISTINCT kmer) AS different FROM ({_DOC_KMERS}) GROUP BY ROLLUP (lang, source)")
def _(spark, d):
    """Sums of each task at the three levels of the rollup: a k-mer is in one task, so different ones add up."""
    reads, values = _labelled_docs(spark, d, "lang", "source")
    langs = list(dict.fromkeys(v[0] for v in values))
    lang_of = np.array([langs.index(v[0]) for v in values], np.int64)

    def levels(heads, kmer, label, n):
        each, lang = np.repeat(np.arange(len(heads)), np.diff(np.append(heads, len(n)))), lang_of[label]
        rows = [(0, i, x, y) for i, (x, y) in enumerate(zip(np.bincount(label, n, len(values)).tolist(), np.bincount(label, minlength=len(values)).tolist(), strict=True)) if y]
        both = np.unique(each * len(langs) + lang) % len(langs)
        rows += [(1, i, x, y) for i, (x, y) in enumerate(zip(np.bincount(lang, n, len(langs)).tolist(), np.bincount(both, minlength=len(langs)).tolist(), strict=True)) if y]
        rows.append((2, 0, int(n.sum()), len(heads)))
        return pa.RecordBatch.from_arrays([pa.array([int(r[i]) for r in rows], pa.int64()) for i in range(4)], names=["level", "label", "kmers", "different"])

    sums = labelled.reduce_labelled(reads, K31, levels, "level long, label long, kmers long, different long").groupBy("level", "label").agg(F.sum("kmers").alias("kmers"), F.sum("different").alias("different"))
    names = [(0, i, *v) for i, v in enumerate(values)] + [(1, i, v, None) for i, v in enumerate(langs)] + [(2, 0, None, None)]
    return sums.join(F.broadcast(spark.createDataFrame(names, "level long, label long, lang string, source string")), ["level", "label"]).select("lang", "source", "kmers", "different")


@query("kmers_by_lang_pivot", f"SELECT kmer, coalesce(sum(n) FILTER (lang = 'de'), 0)::BIGINT AS de, coalesce(sum(n) FILTER (lang = 'en'), 0)::BIGINT AS en, coalesce(sum(n) FILTER (lang = 'es'), 0)::BIGINT AS es, coalesce(sum(n) FILTER (lang = 'fr'), 0)::BIGINT AS fr FROM (SELECT kmer, lang, count(*) AS n FROM ({_DOC_KMERS}) GROUP BY ALL) GROUP BY kmer HAVING sum(n) > 50")
def _(spark, d):
    reads, values = _labelled_docs(spark, d, "lang")
    langs = ["de", "en", "es", "fr"]
    labels = [values.index((x,)) if (x,) in values else -1 for x in langs]

    def often(heads, kmer, label, n):
        many = np.add.reduceat(n, heads) > 50
        by = [np.add.reduceat(np.where(label == x, n, 0), heads)[many] for x in labels]
        return pa.RecordBatch.from_arrays([pa.array(kmer[heads[many]]), *map(pa.array, by)], names=["kmer", *langs])

    return decoded(labelled.reduce_labelled(reads, K31, often, "kmer long, de long, en long, es long, fr long"), 31)


@query("top_kmers_per_lang", f"SELECT lang, kmer, cnt, rank FROM (SELECT lang, kmer, cnt, CAST(row_number() OVER (PARTITION BY lang ORDER BY cnt DESC, kmer) AS INTEGER) AS rank FROM (SELECT lang, kmer, count(*) AS cnt FROM ({_DOC_KMERS}) GROUP BY ALL)) WHERE rank <= 5")
def _(spark, d):
    counts = _doc_kmers(spark, d).groupBy("lang", "kmer").agg(F.count("*").alias("cnt"))
    best = Window.partitionBy("lang").orderBy(F.desc("cnt"), "kmer")
    return decoded(counts.withColumn("rank", F.row_number().over(best)).where("rank <= 5"), 31)


@query("cumulative_share", f"SELECT cnt, n_kmers, round(sum(n_kmers) OVER (ORDER BY cnt) / sum(n_kmers) OVER (), 6) AS share FROM ({_ONE})")
def _(spark, d):
    return counting.cumulative(flagship.count_kmers(src.reads_docs(spark, d), K31, as_spectrum=True))


@query("kmer_set_ops", f"""WITH a AS (SELECT DISTINCT kmer FROM ({sql.kmers(31)})), b AS (SELECT DISTINCT kmer FROM ({sql.kmers(31, sql.reads('pages'))}))
SELECT 'both' AS op, count(*) AS n FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT 'docs_only', count(*) FROM (SELECT * FROM a EXCEPT SELECT * FROM b)
UNION ALL SELECT 'either', count(*) FROM (SELECT * FROM a UNION SELECT * FROM b)""")  # fmt: skip
def _(spark, d):
    """Sizes of the sets, from one exchange of both tables' supermers with the table's number."""
    docs, pages = (view(spark, d).select(F.lit(i).alias("label"), "seq") for i, view in enumerate((src.reads_docs, src.reads_pages)))

    def sizes(heads, kmer, label, n):
        tables = np.diff(np.append(heads, len(n)))
        found = (int((tables == 2).sum()), int(((tables == 1) & (label[heads] == 0)).sum()), len(heads))
        return pa.RecordBatch.from_arrays([pa.array([x], pa.int64()) for x in found], names=["both", "docs_only", "either"])

    names = ("both", "docs_only", "either")
    sums = labelled.reduce_labelled(docs.unionByName(pages), K31, sizes, "both long, docs_only long, either long").agg(*[F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in names])
    return sums.selectExpr("stack(3, 'both', both, 'docs_only', docs_only, 'either', either) as (op, n)").select("n", "op")


@query("compare_spectra", f"""WITH a AS ({sql.counts(31)}), b AS ({sql.counts(31, sql.reads('pages'))})
SELECT coalesce(a.cnt, 0) AS in_docs, coalesce(b.cnt, 0) AS in_pages, count(*) AS n_kmers FROM a FULL JOIN b USING (kmer) GROUP BY ALL""")
def _(spark, d):
    a = flagship.count_kmers(src.reads_docs(spark, d), K31).withColumnRenamed("cnt", "in_docs")
    b = flagship.count_kmers(src.reads_pages(spark, d), K31).withColumnRenamed("cnt", "in_pages")
    return a.join(b, "kmer", "full_outer").na.fill(0, ["in_docs", "in_pages"]).groupBy("in_docs", "in_pages").agg(F.count("*").alias("n_kmers"))


@query("debruijn_degrees", f"WITH c AS ({sql.counts(31)}), o AS (SELECT left(kmer, 30) AS node, count(*) AS n FROM c GROUP BY node), i AS (SELECT right(kmer, 30) AS node, count(*) AS n FROM c GROUP BY node) SELECT coalesce(i.n, 0) AS in_degree, coalesce(o.n, 0) AS out_degree, count(*) AS nodes FROM o FULL JOIN i USING (node) GROUP BY ALL")
def _(spark, d):
    counts = flagship.count_kmers(src.reads_docs(spark, d), K31)
    out = counts.groupBy(F.shiftright("kmer", 2).alias("node")).agg(F.count("*").alias("out_degree"))
    inn = counts.groupBy(F.col("kmer").bitwiseAND(F.lit((1 << 60) - 1)).alias("node")).agg(F.count("*").alias("in_degree"))
    return out.join(inn, "node", "full_outer").na.fill(0, ["in_degree", "out_degree"]).groupBy("in_degree", "out_degree").agg(F.count("*").alias("nodes"))


@query("labelled_spectrum", f"SELECT quality, cnt, count(*) AS n_kmers FROM (SELECT quality, kmer, count(*) AS cnt FROM ({sql.kmers(31)}) JOIN labels ON read_id = doc_id GROUP BY ALL) GROUP BY ALL")
def _(spark, d):
    labels = src.table(spark, d, "labels").select(F.col("doc_id").alias("read_id"), "quality")
    reads = src.reads_docs(spark, d).join(labels, "read_id", "left_semi")  # before any k-mer is made
    rows = extract_kmers(reads, K31, ext=True).join(labels, "read_id").groupBy("quality", "kmer").agg(F.count("*").alias("cnt"))
    return rows.groupBy("quality", "cnt").agg(F.count("*").alias("n_kmers"))


@query("read_composition", f"SELECT read_id, length(seq) AS n, round(length(regexp_replace(seq, '[^GC]', '', 'g')) / nullif(length(regexp_replace(seq, '[^ACGT]', '', 'g')), 0), 6) AS gc, md5(reverse(translate(seq, 'ACGT', 'TGCA'))) AS other FROM ({sql.reads()})")
def _(spark, d):
    return src.reads_docs(spark, d).select("read_id", F.length("seq").cast("long").alias("n"), F.round(gc(F.col("seq")), 6).alias("gc"), F.md5(revcomp(F.col("seq"))).alias("other"))


@query("short_read_spectrum", f"""WITH r AS ({sql.reads()} UNION ALL SELECT conv_id * 1000 + turn, {sql.fold('text')} FROM conversations), p AS (SELECT read_id, seq, unnest(range(0, length(seq), 150)) AS off FROM r WHERE length(seq) > 0)
{sql.spectrum(sql.counts(31, 'SELECT read_id * 4096 + off // 150 AS read_id, substr(seq, off + 1, 150) AS seq FROM p'))}""")  # fmt: skip
def _(spark, d):
    return flagship.count_kmers(src.reads_short(spark, d), K31, as_spectrum=True)


@query("coverage_spectrum", sql.spectrum(sql.counts(31, sql.reads("cov"))))
def _(spark, d):
    """Spectrum of five erroneous copies of every document."""
    return flagship.count_kmers(src.reads_cov(spark, d, 5, 0.005), K31, as_spectrum=True)


@query("page_text_lengths", "SELECT page_id, length(regexp_replace(html, '<[^>]*>', ' ', 'g')) AS n FROM pages")
def _(spark, d):
    return src.table(spark, d, "pages").select("page_id", F.length(strip_tags(F.col("html"))).cast("long").alias("n"))


# --- events and relational tables

_EVENTS = sql.reads("events")


@query("event_kmers", f"SELECT kmer, count(*) AS cnt FROM ({sql.kmers(5, _EVENTS)}) GROUP BY kmer")
def _(spark, d):
    return decoded(flagship.count_kmers(src.reads_events(spark, d), CountSpec(k=5, m=3, s=64)), 5)


@query("event_windows", "SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL")
def _(spark, d):
    rows = src.table(spark, d, "events").groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total"))
    return rows.select(F.col("w.start").alias("start"), "event_type", "n", "total")


@query("event_sessions", """WITH m AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS i FROM m)
SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS end, count(*) AS n FROM s GROUP BY user_id, i""")  # fmt: skip
def _(spark, d):
    rows = src.table(spark, d, "events").groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count("*").alias("n"))
    return rows.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


@query("event_trailing", "SELECT event_id, count(*) OVER w AS n, CAST(lead(event_id) OVER (PARTITION BY user_id ORDER BY ts) AS BIGINT) AS next_event, first_value(event_type) OVER w AS first_type FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW)")
def _(spark, d):
    day = "over (partition by user_id order by ts range between interval 1 day preceding and current row)"
    return src.table(spark, d, "events").selectExpr("event_id", f"count(*) {day} as n", "lead(event_id) over (partition by user_id order by ts) as next_event", f"first_value(event_type) {day} as first_type")


@query("asof_events", "SELECT p.event_id, v.event_id AS view_id, v.ts AS view_ts FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'view') v ON p.user_id = v.user_id AND p.ts >= v.ts")
def _(spark, d):
    """The last view before each purchase, by one window over both instead of a range join."""
    events = src.table(spark, d, "events").where(F.col("event_type").isin("purchase", "view"))
    view = F.when(F.col("event_type") == "view", F.struct("event_id", "ts"))
    so_far = Window.partitionBy("user_id").orderBy("ts").rowsBetween(Window.unboundedPreceding, 0)
    last = events.withColumn("v", F.last(view, ignorenulls=True).over(so_far)).where("event_type = 'purchase'")
    return last.select("event_id", F.col("v.event_id").alias("view_id"), F.col("v.ts").alias("view_ts"))


@query("json_props", "SELECT CAST(props->>'$.k' AS BIGINT) AS k, count(*) AS n, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS cents FROM events GROUP BY k")
def _(spark, d):
    k = F.get_json_object("props", "$.k").cast("long").alias("k")
    return src.table(spark, d, "events").groupBy(k).agg(F.count("*").alias("n"), F.sum(F.round(F.col("value") * 100).cast("long")).alias("cents"))


for _how in ("sort", "range", "hash", "precount"):

    @query(f"partkey_{_how}_count", "SELECT l_partkey AS kmer, count(*) AS cnt FROM lineitem GROUP BY l_partkey")
    def _(spark, d, how=_how):
        return baselines.count_keys(src.table(spark, d, "lineitem"), "l_partkey", how)


@query("user_sort_count", "SELECT user_id AS kmer, count(*) AS cnt FROM events GROUP BY user_id")
def _(spark, d):
    return baselines.count_keys(src.table(spark, d, "events"), "user_id")


@query("star_join", """SELECT r_name, n_name, p_brand, count(*) AS items, CAST(sum(l_quantity) AS BIGINT) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey
JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey JOIN part ON l_partkey = p_partkey GROUP BY ALL""")  # fmt: skip
def _(spark, d):
    t = partial(src.table, spark, d)
    joined = (
        t("lineitem").join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(t("customer"), F.col("o_custkey") == F.col("c_custkey"))
        .join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey"))
        .join(t("part"), F.col("l_partkey") == F.col("p_partkey"))
    )
    return joined.groupBy("r_name", "n_name", "p_brand").agg(F.count("*").alias("items"), F.sum("l_quantity").cast("long").alias("quantity"))


@query("span_hits", f"""WITH h AS (SELECT read_id, pos, pos // 4096 AS span FROM ({sql.kmers(31)}) WHERE kmer IN (SELECT kmer FROM ({sql.kmers(31, sql.reads('small'))})))
SELECT read_id, CAST(span AS BIGINT) AS span, count(*) AS hits, CAST(min(pos) AS INTEGER) AS first FROM h GROUP BY ALL""")  # fmt: skip
def _(spark, d):
    """Hits of benchmark k-mers by spans of 4096 bases: an interval join as an equi join on the span's number."""
    known = extract_kmers(src.reads_small(spark, d), K31).distinct()
    hits = extract_kmers(src.reads_docs(spark, d), K31, ext=True).join(known, "kmer", "left_semi").withColumn("span", F.floor(F.col("pos") / 4096))
    spans = src.reads_docs(spark, d).select("read_id", F.explode(F.sequence(F.lit(0).cast("long"), F.floor(F.length("seq") / 4096))).alias("span"))
    return hits.join(spans, ["read_id", "span"]).groupBy("read_id", "span").agg(F.count("*").alias("hits"), F.min("pos").alias("first"))


# --- further aggregates, windows and uses


@query("supermer_length_percentiles", f"SELECT round(quantile_cont(n_bases, 0.5), 6) AS p50, round(quantile_cont(n_bases, 0.9), 6) AS p90, round(quantile_cont(n_bases, 0.99), 6) AS p99 FROM ({sql.supermers(K31)})")
def _(spark, d):
    rows = sm.build_supermers(src.reads_docs(spark, d), K31.but(chunk=WHOLE))
    return rows.agg(*[F.round(F.percentile("n_bases", F.lit(q)), 6).alias(n) for n, q in (("p50", 0.5), ("p90", 0.9), ("p99", 0.99))])


@query("bases_by_cube", f"SELECT lang, source, count(*) AS reads, CAST(sum(length(seq)) AS BIGINT) AS bases FROM (SELECT lang, source, {sql.fold('text')} AS seq FROM documents) GROUP BY CUBE (lang, source)")
def _(spark, d):
    docs = src.table(spark, d, "documents").select(F.col("doc_id").alias("read_id"), "lang", "source")
    return src.reads_docs(spark, d).join(docs, "read_id").cube("lang", "source").agg(F.count("*").alias("reads"), F.sum(F.length("seq")).cast("long").alias("bases"))


@query("spectrum_ranks", f"""WITH s AS ({_ONE}) SELECT cnt, n_kmers, CAST(rank() OVER (ORDER BY n_kmers DESC) AS INTEGER) AS place, CAST(dense_rank() OVER (ORDER BY n_kmers DESC) AS INTEGER) AS dense,
CAST(ntile(4) OVER (ORDER BY cnt) AS INTEGER) AS quarter, round(percent_rank() OVER (ORDER BY cnt), 6) AS below, round(cume_dist() OVER (ORDER BY cnt), 6) AS upto FROM s""")  # fmt: skip
def _(spark, d):
    many, few = Window.orderBy(F.desc("n_kmers")), Window.orderBy("cnt")  # a spectrum has few rows
    rows = flagship.count_kmers(src.reads_docs(spark, d), K31, as_spectrum=True)
    return rows.select("cnt", "n_kmers", F.rank().over(many).alias("place"), F.dense_rank().over(many).alias("dense"), F.ntile(4).over(few).alias("quarter"), F.round(F.percent_rank().over(few), 6).alias("below"), F.round(F.cume_dist().over(few), 6).alias("upto"))


@query("kmer_neighbours_small", f"""WITH k AS (SELECT DISTINCT kmer FROM ({sql.kmers(15, sql.reads('small'))})), n AS (SELECT kmer, substr(kmer, 1, CAST(i - 1 AS BIGINT)) || b || substr(kmer, CAST(i + 1 AS BIGINT)) AS near
FROM k, unnest(range(1, 16)) AS p(i), unnest(['A', 'C', 'G', 'T']) AS l(b) WHERE substr(kmer, CAST(i AS BIGINT), 1) <> b) SELECT kmer, count(*) AS neighbours FROM n WHERE near IN (SELECT kmer FROM k) GROUP BY kmer""")  # fmt: skip
def _(spark, d):
    """K-mers that occur with one base changed: 45 flips of the packed word and a join, not a comparison of all pairs."""
    kmers = extract_kmers(src.reads_small(spark, d), CountSpec(k=15, m=7)).distinct()
    flips = F.explode(F.array(*[F.lit(x << 2 * i) for i in range(15) for x in (1, 2, 3)])).alias("flip")
    near = kmers.select("kmer", flips).select("kmer", F.col("kmer").bitwiseXOR(F.col("flip")).alias("near"))
    found = near.join(kmers.withColumnRenamed("kmer", "near"), "near", "left_semi").groupBy("kmer").agg(F.count("*").alias("neighbours"))
    return decoded(found, 15)


@query("read_profiles_small", f"SELECT read_id, kmer, count(*) AS n FROM ({sql.kmers(3, sql.reads('small'))}) GROUP BY ALL")
def _(spark, d):
    """Each read's k-mers as a map, opened again."""
    rows = extract_kmers_native(src.reads_small(spark, d), 3).groupBy("read_id", "kmer").agg(F.count("*").alias("n"))
    maps = rows.groupBy("read_id").agg(F.map_from_entries(F.collect_list(F.struct("kmer", "n"))).alias("profile"))
    return maps.select("read_id", F.explode("profile").alias("kmer", "n"))


@query("read_jaccard", f"""WITH m AS (SELECT DISTINCT read_id, score FROM ({sql.minimizers(K31)})), k AS (SELECT read_id, score FROM m JOIN (SELECT score FROM m GROUP BY score HAVING count(*) <= {K31.hi}) USING (score)),
c AS (SELECT read_id, count(*) AS n FROM k GROUP BY read_id), p AS (SELECT a.read_id AS read_a, b.read_id AS read_b, count(*) AS common FROM k a JOIN k b ON a.score = b.score AND a.read_id < b.read_id GROUP BY ALL)
SELECT read_a, read_b, common, round(common / (x.n + y.n - common), 6) AS jaccard FROM p JOIN c x ON x.read_id = read_a JOIN c y ON y.read_id = read_b""")  # fmt: skip
def _(spark, d):
    """Similarity of reads by their sets of minimizers, of which those in more than spec.hi reads say nothing, as in the index: so no key pairs more."""
    sets = sm.minimizers_arrow(src.reads_docs(spark, d), K31).select("read_id", "score").distinct()
    rare = sets.groupBy("score").agg(F.count("*").alias("reads")).where(F.col("reads") <= K31.hi).select("score")
    kept = sets.join(rare, "score")
    sizes = kept.groupBy("read_id").agg(F.count("*").alias("n"))
    lists = kept.groupBy("score").agg(F.array_sort(F.collect_list("read_id")).alias("reads")).where(F.size("reads") > 1)
    pairs = lists.select(F.explode(F.flatten(F.transform("reads", lambda a: F.transform(F.filter("reads", lambda b: b > a), lambda b: F.struct(a.alias("read_a"), b.alias("read_b")))))).alias("p"))
    common = pairs.groupBy("p.read_a", "p.read_b").agg(F.count("*").alias("common"))
    named = common.join(sizes.toDF("read_a", "x"), "read_a").join(sizes.toDF("read_b", "y"), "read_b")
    return named.select("read_a", "read_b", "common", F.round(F.col("common") / (F.col("x") + F.col("y") - F.col("common")), 6).alias("jaccard"))


@query("kmers_by_prefix", f"SELECT left(kmer, 4) AS prefix, count(*) AS kmers, CAST(sum(cnt) AS BIGINT) AS occurrences FROM ({sql.counts(31)}) GROUP BY prefix")
def _(spark, d):
    counts = flagship.count_kmers(src.reads_docs(spark, d), K31)
    by = counts.groupBy(F.shiftright("kmer", 54).alias("prefix")).agg(F.count("*").alias("kmers"), F.sum("cnt").alias("occurrences"))
    return by.withColumn("prefix", unpack(F.col("prefix"), 4))


@query("sketch_bounds", f"WITH c AS ({sql.counts(31)}) SELECT count(*) AS keys, true AS theta_close, true AS quantile_close, true AS frequent_first FROM c")
def _(spark, d):
    """Further sketches against exact counts: distinct keys by a theta sketch, the median count by a quantile sketch, the top key by frequent items."""
    counts = flagship.count_kmers(src.reads_docs(spark, d), K31).withColumn("key", F.xxhash64("kmer"))
    exact = counts.agg(F.count("*").alias("keys"), F.expr("theta_sketch_estimate(theta_sketch_agg(key))").alias("theta"), F.expr("kll_sketch_get_quantile_bigint(kll_sketch_agg_bigint(cnt), 0.5)").alias("mid"),
                        F.expr("percentile_disc(0.5) within group (order by cnt)").alias("median"), F.expr("approx_top_k(least(cnt, 3), 1)[0].item").alias("often"), F.expr("mode(least(cnt, 3))").alias("mode"))
    return exact.select("keys", (F.abs(F.col("theta") - F.col("keys")) <= 0.05 * F.col("keys")).alias("theta_close"), (F.abs(F.col("mid") - F.col("median")) <= 1).alias("quantile_close"), (F.col("often") == F.col("mode")).alias("frequent_first"))


# --- files, SQL functions and streams, each against the batch result


def _kept(spark, name: str, write) -> DataFrame:
    """What ``write`` leaves in a new folder of the work folder."""
    return write(new_folder(spark, name))


@query("fasta_roundtrip", f"SELECT read_id, length(seq) AS n, md5(seq) AS seq_md5 FROM ({sql.reads('small')}) WHERE length(seq) > 0")
def _(spark, d):
    def through(path):
        fasta.write_fasta(src.reads_small(spark, d), path)
        return fasta.read_fasta(spark, path)

    return _kept(spark, "fasta", through).where("length(seq) > 0").select("read_id", F.length("seq").cast("long").alias("n"), F.md5("seq").alias("seq_md5"))


@query("seqfile_source", f"SELECT CAST(read_id AS VARCHAR) AS name, length(seq) AS n, md5(seq) AS seq_md5 FROM ({sql.reads('small')}) WHERE length(seq) > 0")
def _(spark, d):
    def through(path):
        fasta.write_fasta(src.reads_small(spark, d), path)
        fasta.register(spark)
        return spark.read.format("seqfile").option("kind", "fasta").option("splitBytes", 4096).load(path.removeprefix("file:"))

    return _kept(spark, "seqfile", through).where("length(seq) > 0").select("name", F.length("seq").cast("long").alias("n"), F.md5("seq").alias("seq_md5"))


@query("counts_sink", f"SELECT kmer, cnt FROM ({sql.counts(31, sql.reads('small'))})")
def _(spark, d):
    def through(path):
        sinks.write_counts(flagship.count_kmers(src.reads_small(spark, d), K31), path, groups=8)
        return sinks.read_counts(spark, path)

    return decoded(_kept(spark, "counts", through), 31)


@query("spectrum_sink", _ONE)
def _(spark, d):
    def through(path):
        sinks.write_spectrum(flagship.count_kmers(src.reads_docs(spark, d), K31, as_spectrum=True), path)
        return spark.read.option("header", True).schema("cnt long, n_kmers long").csv(path)

    return _kept(spark, "spectrum", through)


@query("count_in_waves", _ONE)
def _(spark, d):
    """Blocks kept by wave and exchanged a wave at a time: what an exchange too wide for one go does."""
    reads = src.reads_docs(spark, d)
    plan = flagship.make_plan(reads, K31)

    def through(path):
        sinks.write_blocks(exchange.make_blocks(reads, K31, plan.placed, plan.heavy, plan.partitions), path, 3)
        waves = [counting.count_blocks(sinks.read_wave(spark, path, w, plan.partitions), K31, plan.method, as_spectrum=True) for w in range(3)]
        return reduce(DataFrame.unionByName, waves).groupBy("cnt").agg(F.sum("n_kmers").alias("n_kmers"))

    return _kept(spark, "blocks", through)


@query("sql_table_function", f"SELECT kmer, count(*) AS cnt FROM ({sql.kmers(31, sql.reads('small'))}) GROUP BY kmer")
def _(spark, d):
    sqlapi.register_all(spark, d)
    return decoded(spark.sql("SELECT k.kmer, count(*) AS cnt FROM reads_small, LATERAL kmers(seq, 31) k GROUP BY k.kmer"), 31)


@query("sql_supermer_function", f"SELECT CAST(task AS INTEGER) AS task, count(*) AS supermers, CAST(sum(n_bases) AS BIGINT) AS bases FROM ({sql.supermers(K31, sql.reads('small'))}) GROUP BY task")
def _(spark, d):
    sqlapi.register_all(spark, d)
    return spark.sql(f"SELECT s.task, count(*) AS supermers, sum(length(s.bases)) AS bases FROM reads_small, LATERAL supermers(seq, {K31.k}, {K31.m}, {K31.s}, 'murmur3') s GROUP BY s.task")


@query("sql_scalar_functions", f"SELECT read_id, count(*) AS n, CAST(sum(score) AS BIGINT) AS scores, CAST(sum(code % 1000003) AS BIGINT) AS words FROM ({sql.mmer_scores(K31, sql.reads('small'))}) GROUP BY read_id")
def _(spark, d):
    sqlapi.register_all(spark, d)
    rows = spark.sql(f"SELECT read_id, mmer_scores(seq, {K31.m}) AS s, pack_kmers(seq, {K31.m}) AS w FROM reads_small").where("size(s) > 0")
    total = lambda c, f: F.aggregate(c, F.lit(0).cast("long"), lambda a, x: a + f(x))
    return rows.select("read_id", F.size("s").cast("long").alias("n"), total("s", lambda x: x).alias("scores"), total("w", lambda x: x % 1000003).alias("words"))


@query("sql_spectrum_aggregate", f"SELECT read_id, cnt, count(*) AS n_kmers FROM (SELECT read_id, kmer, count(*) AS cnt FROM ({sql.kmers(5, sql.reads('small'))}) GROUP BY ALL) GROUP BY ALL")
def _(spark, d):
    sqlapi.register_all(spark, d)
    return spark.sql("SELECT read_id, inline(spectrum_of(k.kmer)) FROM reads_small, LATERAL kmers(seq, 5) k GROUP BY read_id")


def _streamed(spark, d, name: str) -> DataFrame:
    """A table as a stream of files; event time has to be an instant."""
    rows = spark.readStream.schema(src.table(spark, d, name).schema).option("pathGlobFilter", f"{name}.parquet").parquet(d)
    return rows.withColumn("ts", F.col("ts").cast("timestamp")) if "ts" in rows.columns else rows


def _drained(spark, stream: DataFrame, mode: str) -> DataFrame:
    """What a stream has given once all that is there has been read."""
    path = new_folder(spark, "stream")

    def keep(batch, number):
        batch.write.mode("overwrite").parquet(f"{path}/out" if mode == "complete" else f"{path}/out/batch={number}")

    stream.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start().awaitTermination()
    out = spark.read.parquet(f"{path}/out")
    return out if mode == "complete" else out.drop("batch")


def _streamed_small(spark, d) -> DataFrame:
    return _streamed(spark, d, "benchmark").select(F.col("item_id").alias("read_id"), fold_text(F.col("text")).alias("seq"))


@query("stream_running_counts", f"SELECT kmer, cnt FROM ({sql.counts(31, sql.reads('small'))})")
def _(spark, d):
    return decoded(_drained(spark, streams.running_counts(_streamed_small(spark, d), K31), "complete"), 31)


@query("stream_merged_counts", f"SELECT kmer, cnt FROM ({sql.counts(31, sql.reads('small'))})")
def _(spark, d):
    path = new_folder(spark, "merged")
    streams.merge_batches(_streamed_small(spark, d), K31, f"{path}/parts", f"{path}/state").trigger(availableNow=True).start().awaitTermination()
    return decoded(streams.merged_counts(spark, f"{path}/parts"), 31)


@query("stream_windows", "SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL")
def _(spark, d):
    found = _drained(spark, streams.windowed(_streamed(spark, d, "events")), "complete")
    return found.withColumn("total", F.round("total", 4)).withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("stream_sessions", SQL["event_sessions"])
def _(spark, d):
    found = _drained(spark, streams.sessions(_streamed(spark, d, "events")), "complete")
    return found.withColumn("start", F.col("start").cast("timestamp_ntz")).withColumn("end", F.col("end").cast("timestamp_ntz"))


@query("stream_distinct", "SELECT DISTINCT event_type || ':' || user_id AS seq FROM events")
def _(spark, d):
    rows = _streamed(spark, d, "events").select(F.concat_ws(":", "event_type", "user_id").alias("seq"), "ts")
    return _drained(spark, streams.distinct_reads(rows, "3650 days").select("seq"), "append")


@query("stream_reliable_hits", f"WITH c AS (SELECT kmer, cnt FROM ({sql.counts(31)}) WHERE cnt BETWEEN 2 AND 50) SELECT read_id, count(*) AS hits, CAST(sum(cnt) AS BIGINT) AS seen FROM ({sql.kmers(31, sql.reads('small'))}) JOIN c USING (kmer) GROUP BY read_id")
def _(spark, d):
    known = flagship.count_kmers(src.reads_docs(spark, d), K31, ranged=True)
    return _drained(spark, streams.reliable_hits(_streamed_small(spark, d), known, K31), "append").groupBy("read_id").agg(F.count("*").alias("hits"), F.sum("cnt").alias("seen"))


@query("stream_user_kmers", f"SELECT kmer, count(*) AS cnt FROM ({sql.kmers(5, _EVENTS)}) GROUP BY kmer")
def _(spark, d):
    base = reduce(lambda c, kv: c.when(F.col("event_type") == kv[0], kv[1]), src.EVENT_BASES.items(), F.when(F.lit(False), "N")).otherwise("N")
    symbols = _streamed(spark, d, "events").select("user_id", F.struct("ts", "event_id").alias("at"), base.alias("base"))
    flat = symbols.select("user_id", (F.unix_micros("at.ts") * 1000 + F.pmod("at.event_id", F.lit(1000))).alias("at"), "base")
    return _drained(spark, streams.user_kmers(flat, 5), "append").where("kmer not like '%N%'").groupBy("kmer").agg(F.count("*").alias("cnt"))


def flagship_entry(spark, d) -> DataFrame:
    """The spectrum of all documents at k = 31 by the whole method."""
    return QUERIES["kmer_spectrum_k31"](spark, d)
