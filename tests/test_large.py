"""What keeps tasks small on large tables: packed exchanges, counts by ranges, labels, draws by arrays, the driver's memory."""

import os
from collections import Counter as Tally

import numpy as np
import pytest
from pyspark.sql import functions as F

from seqcount import session
from seqcount.functions import kernel
from seqcount.llm import common
from seqcount.operators import baselines, counting, exchange, labelled
from seqcount.plans import queries
from seqcount.sources import reads as src
from seqcount.spec import CountSpec

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("k", [1, 4, 31, 32, 55, 62])
def test_kmers_of_packed_runs_are_those_of_their_bases(k):
    codes = np.random.default_rng(k).integers(0, 4, 5000).astype(np.uint8)
    spec = CountSpec(k=k)
    found = kernel.find_supermers(codes, spec)
    packed, offsets = kernel.pack_runs(codes, found.begin, found.n_bases)
    for begin, n, a in zip(found.begin[:20], found.n_bases, offsets, strict=False):
        word = "".join(f"{b:08b}" for b in packed[a : a - (-n // 4)])
        assert word == "".join(f"{c:02b}" for c in codes[begin : begin + n]).ljust(len(word), "0")
    want = kernel.valid_kmers(codes, k)
    for x, y in zip(want, kernel.run_kmers(packed, found.n_bases, k), strict=True):
        assert (np.sort(x) == np.sort(y)).all()


@pytest.mark.parametrize(("k", "method"), [(5, "aux_radix"), (15, "aux_radix"), (15, "hash"), (15, "inplace"), (40, "aux_radix")])
def test_a_task_is_counted_by_ranges(monkeypatch, k, method):
    monkeypatch.setattr(counting, "EXPAND_KMERS", 300)
    monkeypatch.setattr(counting, "HELD_PAIRS", 1000)
    spec, rng = CountSpec(k=k, m=3), np.random.default_rng(7)
    counter, want = counting.Counter(spec, method), Tally()
    for _ in range(60):
        codes = rng.integers(0, 4, 200).astype(np.uint8)
        codes[100:150] = codes[0:50]
        packed, _ = kernel.pack_runs(codes, np.array([0]), np.array([200]))
        counter.add_packed(np.array([200]), packed)
        want.update(zip(*(w.tolist() for w in kernel.valid_kmers(codes, k)), strict=True))
    pieces = list(counter.pieces())
    got = Tally()
    for words, n in pieces:
        assert len(n) <= 1300  # the range, and the part that was expanded last
        for key, times in zip(zip(*(w.tolist() for w in words), strict=True), n.tolist(), strict=True):
            assert key not in got
            got[key] = times
    assert got == want and (k == 5 or len(pieces) > 3)


@pytest.mark.parametrize("method", ["aux_radix", "inplace", "hash"])
@pytest.mark.parametrize("repeats", [0, 1, 60])
def test_lists_are_merged_range_by_range(monkeypatch, method, repeats):
    monkeypatch.setattr(counting, "EXPAND_KMERS", 300)
    monkeypatch.setattr(counting, "HELD_PAIRS", 4000)
    spec, rng = CountSpec(k=31, m=3), np.random.default_rng(11)
    counter, want = counting.Counter(spec, method), Tally()
    same = rng.integers(0, 4, 200).astype(np.uint8)
    for i in range(60):
        codes = same if i < repeats else rng.integers(0, 4, 200).astype(np.uint8)
        packed, _ = kernel.pack_runs(codes, np.array([0]), np.array([200]))
        words, n = kernel.count_runs(kernel.valid_kmers(codes, 31))
        counter.add_list(len(n), exchange.pack_list(words, n)) if i % 10 == 9 else counter.add_block(1, exchange.pack_block(np.array([200]), packed))
        want.update(words[0].tolist())
    got = [(key, times) for words, n in counter.pieces() for key, times in zip(words[0].tolist(), n.tolist(), strict=True)]
    assert dict(got) == want and len(got) == len(want)
    if method != "hash":  # lists out of order can't be sliced
        assert max(len(n) for _, n in counter.pieces()) < 900


def test_rungs_are_counted_one_after_another(spark):
    found = queries.QUERIES["ablation_same_result"](spark, SF)
    assert "Exchange" not in found._jdf.queryExecution().executedPlan().toString()
    where = session.work_folder(spark).removeprefix("file:")
    assert not [name for name in os.listdir(where) if name.startswith("reads-")]


@pytest.mark.parametrize("make", [baselines.count_two_pass, baselines.index_two_pass])
def test_two_passes_exchange_blocks(spark, make):
    plan = make(src.reads_docs(spark, SF), CountSpec(k=31), 4)._jdf.queryExecution().optimizedPlan().toString()
    exchanges = [x for x in plan.splitlines() if "RepartitionById" in x or "RepartitionByExpression" in x]
    assert len(exchanges) == 2 and "kmer#" not in plan.split("MapInArrow keep", 1)[-1].split("\n", 1)[-1]


@pytest.mark.parametrize("heavy_factor", [3.0, 0.5])
def test_labels_are_counted_together(spark, heavy_factor):
    rows = [(i % 3, "".join("ACGT"[(j * j + i // 2 * j) % 4] for j in range(120)) + "N" + "ACGTTGCA" * 5) for i in range(12)] + [(1, None), (2, ""), (0, "ACG")]
    want = Tally()
    for label, seq in rows:
        for i in range(len(seq or "") - 10):
            word = seq[i : i + 11]
            if "N" not in word:
                want[(sum("ACGT".index(c) << 2 * (10 - j) for j, c in enumerate(word)), label)] += 1

    def listed(heads, kmer, label, n):
        assert (np.diff(kmer[heads]) > 0).all()
        return labelled.pa.RecordBatch.from_arrays([labelled.pa.array(x) for x in (kmer, label, n)], names=["kmer", "label", "n"])

    reads = spark.createDataFrame(rows, "label long, seq string")
    found = labelled.reduce_labelled(reads, CountSpec(k=11, m=5, s=16, heavy_factor=heavy_factor), listed, "kmer long, label long, n long", 3).collect()
    assert {(r.kmer, r.label): r.n for r in found} == want and len(found) == len(want)


@pytest.mark.parametrize("name", ["kmer_set_ops", "kmers_by_lang_pivot", "source_unique_anti", "spectrum_by_lang_rollup"])
def test_uses_of_labels_exchange_no_rows_of_kmers(spark, name):
    plan = queries.QUERIES[name](spark, SF)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("RepartitionById") + plan.count("RepartitionByExpression") >= 1 and "payload" in plan and "extract_kmers" not in plan and "Join LeftAnti" not in plan


def test_labels_of_null_values(spark, tmp_path):
    text = "the same words are in a text without a source and in one with it, more than once"
    rows = [(1, text, None, None), (2, text + " or twice, some say in another place", "de", None), (3, "quite another text that nothing else is like at all", None, "web")]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string").write.parquet(f"{tmp_path}/documents.parquet")
    docs = spark.read.parquet(f"{tmp_path}/documents.parquet")
    kmers = queries.extract_kmers(docs.select(F.col("doc_id").alias("read_id"), queries.fold_text(F.col("text")).alias("seq")), queries.K31, ext=True).join(docs.withColumnRenamed("doc_id", "read_id"), "read_id")
    want = kmers.rollup("lang", "source").agg(F.count("*").alias("kmers"), F.count_distinct("kmer").alias("different")).collect()
    got = queries.QUERIES["spectrum_by_lang_rollup"](spark, str(tmp_path)).collect()
    assert sorted(map(str, got)) == sorted(map(str, want))
    alone = {r["source"]: r["only_here"] for r in queries.QUERIES["source_unique_anti"](spark, str(tmp_path)).collect()}
    assert alone.keys() == {None, "web"} and alone["web"] == len(rows[2][1]) - 30


def test_draws_by_arrays_are_those_of_whole_numbers(spark):
    x = np.array([0, 1, src.DRAW_PRIME - 1, src.DRAW_PRIME, src.DRAW_PRIME + 18, (1 << 62) - 1, 1 << 61], np.int64)
    assert src._drawn(x).tolist() == [int(v) % src.DRAW_PRIME for v in x]
    base = spark.createDataFrame([(-7, "ACGTN" * 300), (1 << 40, "A" * 700), (3, ""), (4, None), (None, "CCC")], "read_id long, seq string")
    got = sorted(((r["read_id"], r["seq"]) for r in src.mutated(base, 2, 0.02).collect()), key=str)
    p, want = src.DRAW_PRIME, []
    for i, seq in ((-7, "ACGTN" * 300), (1 << 40, "A" * 700), (3, ""), (4, "")):
        for copy in range(2):
            start, out = (i % p * src.DRAW_READ + copy * src.DRAW_COPY) % p, list(seq)
            for j in range(1, len(seq) + 1):
                mixed = (start + j * src.DRAW_PLACE) % p * src.DRAW_MIX % p
                draw = (mixed * mixed + mixed * src.DRAW_READ + j) % p
                if draw < int(0.02 * p):
                    out[j - 1] = "ACGT"[draw % 4]
            want.append((i * 2 + copy, "".join(out)))
    assert got == sorted([*want, (None, "CCC"), (None, "CCC")], key=str)


def test_shared_sort_has_as_many_places_as_partitions(spark, monkeypatch):
    seen = []
    kept = exchange.exchange
    monkeypatch.setattr(exchange, "exchange", lambda blocks, p: seen.append(p) or kept(blocks, p))
    monkeypatch.setattr(baselines, "_parts", lambda df, p: p or 50)
    baselines.count_shared_sort(src.reads_small(spark, SF), CountSpec(k=31))
    assert seen == [50]


def test_the_driver_gives_back_what_plans_leave(spark, monkeypatch):
    held = spark._jvm.java.lang.ref.WeakReference(spark._jvm.java.util.ArrayList())
    monkeypatch.setattr(session, "RELIEVE_SECONDS", 0.0)
    session._relieved[0] = 0.0
    common.checkpointed(spark.range(3))
    assert held.get() is None or session.relieve(spark, 0.0)
    session._relieved[0] = 1e12
    assert not session.relieve(spark)
    session._relieved[0] = 0.0
