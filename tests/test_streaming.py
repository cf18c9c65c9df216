"""Streams give what a batch over the same rows gives."""

import shutil

import pytest
from pyspark.sql import Window
from pyspark.sql import functions as F

from seqcount.operators import baselines, counting
from seqcount.sources.reads import EVENT_BASES, reads_small, table
from seqcount.spec import CountSpec
from seqcount.streaming import streams

SF = "/root/testdata/sf0.001"
SPEC = CountSpec(k=31, s=16)


@pytest.fixture
def arriving(spark, tmp_path):
    """Files of reads that a stream takes one at a time."""
    rows = reads_small(spark, SF)
    rows.repartition(4, "read_id").write.parquet(str(tmp_path / "in"))
    return rows, spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))


def drain(frame, name, mode, tmp_path):
    q = frame.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", str(tmp_path / name)).trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert q.exception() is None
    return frame.sparkSession.table(name)


def test_running_counts_equal_a_batch(arriving, tmp_path):
    rows, stream = arriving
    got = drain(streams.running_counts(stream, SPEC), "running", "complete", tmp_path)
    assert counting.same_counts(got, baselines.count_dist_hash(rows, SPEC))


def test_merged_batches_equal_a_batch_also_when_replayed(spark, arriving, tmp_path):
    rows, stream = arriving
    out = str(tmp_path / "parts")
    for _ in range(2):  # the second run forgets its progress and takes every batch again
        q = streams.merge_batches(stream, SPEC, out, str(tmp_path / "progress")).trigger(availableNow=True).start()
        q.awaitTermination(120)
        shutil.rmtree(tmp_path / "progress")
    assert counting.same_counts(streams.merged_counts(spark, out), baselines.count_dist_hash(rows, SPEC))


def event_stream(spark, tmp_path, rows):
    rows.coalesce(1).write.parquet(str(tmp_path / "events"))
    return spark.readStream.schema(streams.EVENT_FIELDS).parquet(str(tmp_path / "events"))


def test_windows_and_sessions_equal_a_batch(spark, tmp_path):
    rows = table(spark, SF, "events")
    stream = event_stream(spark, tmp_path, rows)
    got = drain(streams.windowed(stream), "tumbling", "complete", tmp_path)
    want = rows.groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n"))
    assert sorted(got.select("start", "event_type", "n").collect()) == sorted(want.select("w.start", "event_type", "n").collect())
    slid = drain(streams.windowed(stream, "1 hour", "30 minutes"), "sliding", "complete", tmp_path)
    assert slid.agg(F.sum("n")).first()[0] == 2 * rows.count()
    found = drain(streams.sessions(stream), "sessions", "complete", tmp_path)
    assert found.agg(F.sum("n")).first()[0] == rows.count()


def test_late_events_are_dropped(spark, tmp_path):
    fields = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
    for i, stamps in enumerate((["2024-01-01 00:00:00", "2024-01-01 05:00:00"], ["2024-01-01 06:00:00"], ["2024-01-01 00:30:00", "2024-01-01 09:00:00"], ["2024-01-01 12:00:00"])):
        frame = spark.createDataFrame([(10 * i + j, t) for j, t in enumerate(stamps)], "event_id long, t string")
        frame.selectExpr("event_id", "cast(t as timestamp) as ts", "1L as user_id", "'view' as event_type", "1.0D as value", "'{}' as props").coalesce(1).write.mode("append").parquet(str(tmp_path / "late"))
    stream = spark.readStream.schema(fields).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "late"))
    got = drain(streams.windowed(stream), "late_windows", "append", tmp_path)
    assert got.where("start = '2024-01-01 00:00:00'").first()["n"] == 1


def test_kmers_that_span_batches(spark, tmp_path):
    rows = table(spark, SF, "events")
    base = F.create_map(*[F.lit(x) for p in EVENT_BASES.items() for x in p])
    symbols = rows.select("user_id", F.col("ts").alias("at"), F.coalesce(F.try_element_at(base, F.col("event_type")), F.lit("N")).alias("base"))
    for part in range(3):  # in order of time, so that state carries over
        at = symbols.withColumn("p", F.ntile(3).over(Window.orderBy("at"))).where(F.col("p") == part + 1).drop("p")
        at.coalesce(1).write.mode("append").parquet(str(tmp_path / "symbols"))
    stream = spark.readStream.schema(symbols.schema).option("maxFilesPerTrigger", 1).option("latestFirst", False).parquet(str(tmp_path / "symbols"))
    got = drain(streams.user_kmers(stream, 4), "spanning", "append", tmp_path)
    want = {}
    for r in symbols.orderBy("user_id", "at").collect():
        want.setdefault(r["user_id"], []).append(r["base"])
    lines = {u: "".join(x) for u, x in want.items()}
    pairs = sorted((u, s[i : i + 4]) for u, s in lines.items() for i in range(len(s) - 3))
    assert sorted((r["user_id"], r["kmer"]) for r in got.collect()) == pairs


def test_distinct_reads_and_static_join(spark, arriving, tmp_path):
    rows, stream = arriving
    counts = baselines.count_dist_hash(rows, SPEC)
    hits = drain(streams.reliable_hits(stream, counts, SPEC), "hits", "append", tmp_path)
    assert hits.count() == counts.agg(F.sum("cnt")).first()[0]
    twice = rows.unionAll(rows).withColumn("ts", F.lit("2024-01-01 00:00:00").cast("timestamp"))
    twice.coalesce(1).write.parquet(str(tmp_path / "twice"))
    once = drain(streams.distinct_reads(spark.readStream.schema(twice.schema).parquet(str(tmp_path / "twice"))), "once", "append", tmp_path)
    assert once.count() == rows.select("seq").distinct().count()
