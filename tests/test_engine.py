"""Plans against brute force and against each other, with odd inputs."""

import itertools
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from seqcount.functions import alphabet, kernel, scores
from seqcount.operators import baselines, counting, exchange, index, metrics, prepare, sketches
from seqcount.operators import supermers as sm
from seqcount.operators.tasks import assign_tasks
from seqcount.plans import flagship
from seqcount.spec import CountSpec

SMALL = CountSpec(k=9, m=4, s=13, lo=1, hi=1 << 40, chunk=64, block_bytes=64)


def make_reads(spark, seqs):
    return spark.createDataFrame(list(enumerate(seqs)), "read_id long, seq string").repartition(3)


def random_reads(seed=0, n=60):
    rng = random.Random(seed)
    base = "".join(rng.choice("ACGT") for _ in range(400))
    out = []
    for _ in range(n):
        a = rng.randrange(300)
        s = list(base[a : a + rng.randint(5, 180)])
        for i in range(len(s)):
            if rng.random() < 0.02:
                s[i] = rng.choice("ACGTN")
        out.append("".join(s))
    return [*out, None, "", "ACGT", "N" * 40, "acgtacgtacgt", "NACGTACGTAN", "A" * 300, "ACTTG" * 80]


def brute(seqs, k):
    counts = {}
    for s in seqs:
        for i in range(len(s or "") - k + 1):
            x = s[i : i + k]
            if set(x) <= set("ACGT"):
                counts[x] = counts.get(x, 0) + 1
    return counts


def as_dict(counts, k):
    rows = counts.select(alphabet.unpack(F.col("kmer"), k).alias("kmer"), "cnt").collect()
    assert len({r["kmer"] for r in rows}) == len(rows)
    return {r["kmer"]: r["cnt"] for r in rows}


@pytest.fixture(scope="module")
def reads(spark):
    return make_reads(spark, random_reads()).cache()


@pytest.mark.parametrize("k", [1, 9, 31, 32, 40])
@pytest.mark.parametrize("factor", [0.01, 3.0, 1e9])
def test_flagship_is_exact_for_any_decision(spark, reads, k, factor):
    spec = CountSpec(k=k, s=13, heavy_factor=factor, chunk=4 * 64, block_bytes=200)
    want = brute(random_reads(), k)
    for target in ("kmer", "task"):
        assert as_dict(flagship.count_kmers(reads, spec, 3, share=1.0, heavy_target=target), k) == want
    got = {r["cnt"]: r["n_kmers"] for r in flagship.count_kmers(reads, spec, 3, as_spectrum=True).collect()}
    assert got == {c: list(want.values()).count(c) for c in set(want.values())}


@pytest.mark.parametrize("change", [{"s": 1}, {"s": 5000}, {"m": 1}, {"m": 8}, {"m": 9}, {"score": "lex"}, {"score": "lex_mod"}, {"score": "arith"}, {"score": "universal", "seed": 7}, {"break_on": "minimizer"}, {"chunk": 40}, {"block_bytes": 1}, {"dest": "second_hash"}, {"dest": "second_hash", "break_on": "minimizer", "m": 1}, {"tie": "lex"}, {"worker_bytes": 1}, {"worker_bytes": 900}])
def test_result_does_not_depend_on_parameters(spark, reads, change):
    assert as_dict(flagship.count_kmers(reads, SMALL.but(**change), 5), 9) == brute(random_reads(), 9)


@pytest.mark.parametrize("policy", ["greedy", "longest_first", "round_robin", "modulo"])
@pytest.mark.parametrize("partitions", [1, 64])
def test_policies_and_partitions(reads, policy, partitions):
    assert as_dict(flagship.count_kmers(reads, SMALL, partitions, policy=policy, method="aux_radix"), 9) == brute(random_reads(), 9)


@pytest.mark.parametrize("method", ["inplace", "aux_radix", "spark_radix", "hash"])
@pytest.mark.parametrize("k", [9, 40])
def test_sorts_agree(reads, method, k):
    spec = CountSpec(k=k, s=7, heavy_factor=1.5, chunk=256)
    assert as_dict(flagship.count_kmers(reads, spec, 3, method=method, share=1.0), k) == brute(random_reads(), k)


def test_plan_chooses_the_sort_by_the_largest_task(reads):
    largest = int(max(flagship.make_plan(reads, SMALL, 4, heavy=False, share=1.0).sizes)) * 8
    for room, method in ((4 * largest, "aux_radix"), (2 * largest, "inplace"), (largest, "spark_radix")):
        assert flagship.make_plan(reads, SMALL.but(worker_bytes=room), 4, heavy=False, share=1.0).method == method


def test_a_repeat_within_one_read_is_found_by_the_sample(spark):
    rng = random.Random(1)
    seqs = ["".join(rng.choice("ACGT") for _ in range(1500)) for _ in range(300)] + ["ACTTG" * 20_000]
    plan = flagship.make_plan(make_reads(spark, seqs), CountSpec(k=31))
    full = flagship.make_plan(make_reads(spark, seqs), CountSpec(k=31), share=1.0)
    assert len(full.heavy) and plan.heavy.tolist() == full.heavy.tolist()
    assert 0.7 < plan.sizes.sum() / full.sizes.sum() < 1.4


def test_sampled_pieces_hold_each_window_once(spark, monkeypatch):
    monkeypatch.setattr(flagship, "SIZE_PIECE", 16)
    seqs = random_reads()
    pieces = flagship.sampled_pieces(make_reads(spark, seqs), SMALL, 1.0)
    assert brute([r["seq"] for r in pieces.collect()], 9) == brute(seqs, 9)


def test_first_fit_is_the_plain_one():
    rng = random.Random(3)
    for _ in range(60):
        partitions, sizes = rng.randint(1, 9), np.array([rng.randint(0, 30) for _ in range(rng.randint(0, 40))], np.int64)
        order = np.lexsort((np.arange(len(sizes)), -sizes))
        level = max(sizes.sum() / partitions, sizes.max(initial=0))
        while True:
            load, want = [0.0] * partitions, {}
            for t in order.tolist():
                fits = [p for p in range(partitions) if load[p] + sizes[t] <= level]
                if not fits:
                    break
                want[t] = fits[0]
                load[fits[0]] += sizes[t]
            if len(want) == len(sizes):
                break
            level *= 1.05
        got = assign_tasks(sizes, partitions)
        assert [want[t] for t in range(len(sizes))] == got.tolist()


def test_lexical_ties_and_second_hash_agree_on_equal_kmers():
    spec = CountSpec(k=9, m=3, s=11, dest="second_hash")
    rng = random.Random(2)
    tasks = {}
    for _ in range(40):
        seq = "".join(rng.choice("ACG") for _ in range(60))
        codes = np.array([kernel._CODE[ord(c)] for c in seq], np.uint8)
        found = kernel.find_supermers(codes, spec)
        for b, n, t in zip(found.begin.tolist(), found.n_bases.tolist(), found.task.tolist()):
            for i in range(b, b + n - 8):
                assert tasks.setdefault(seq[i : i + 9], t) == t
    assert len(set(tasks.values())) > 5


BASELINES = {
    "dist_hash": baselines.count_dist_hash,
    "partial": lambda r, s: baselines.count_dist_hash(r, s, partial=True),
    "supermer_hash": baselines.count_supermer_hash,
    "naive": lambda r, s: baselines.count_supermer_hash(r, s, naive=True),
    "range": baselines.count_range_sort,
    "spark_sort": baselines.count_hash_exchange_sort,
    "timsort": lambda r, s: baselines.count_hash_exchange_sort(r, s, sort_mode="timsort"),
    "sortagg": lambda r, s: baselines.count_hash_exchange_sort(r, s, sort_mode="sortagg"),
    "merge": baselines.count_merge_last,
    "shared": baselines.count_shared_sort,
    "explicit": lambda r, s: baselines.count_explicit_hh(r, s, share=0.02),
    "owned": baselines.count_thread_owned,
    "list": baselines.count_supermer_list,
    "native": lambda r, s: baselines.count_heavy_native(sm.build_supermers(r, s), s),
}


@pytest.mark.parametrize("name", BASELINES)
@pytest.mark.parametrize("k", [9, 40])
def test_baselines_are_exact(reads, name, k):
    spec = CountSpec(k=k, s=13, chunk=256)
    assert as_dict(BASELINES[name](reads, spec), k) == brute(random_reads(), k)


@pytest.mark.parametrize("k", [9, 40])
def test_two_passes_lose_singletons_only(reads, k):
    want = {x: n for x, n in brute(random_reads(), k).items() if n > 1}
    assert as_dict(baselines.count_two_pass(reads, CountSpec(k=k), fpp=0.3), k) == want


def test_rungs_agree(reads):
    want = sorted(map(tuple, flagship.count_kmers(reads, SMALL, as_spectrum=True).collect()))
    for name in flagship.RUNGS:
        assert sorted(map(tuple, flagship.rung(reads, SMALL, name, 4).collect())) == want


def test_canonical_counts(reads):
    def low(x):
        return min(x, x[::-1].translate(str.maketrans("ACGT", "TGCA")))

    for k in (9, 40):
        want = {}
        for x, n in brute(random_reads(), k).items():
            want[low(x)] = want.get(low(x), 0) + n
        assert as_dict(flagship.count_kmers(reads, CountSpec(k=k, canonical=True, s=13, heavy_factor=0.5, chunk=256)), k) == want


def test_empty_and_odd_tables(spark):
    for seqs in ([], [None], [""], ["ACGT"], ["N" * 100]):
        r = spark.createDataFrame(list(enumerate(seqs)), "read_id long, seq string")
        assert flagship.count_kmers(r, SMALL).count() == 0
        assert sm.build_supermers(r, SMALL).count() == 0
        assert index.kmer_index(r, SMALL).count() == 0
        for name in ("dist_hash", "range", "merge", "explicit", "list"):
            assert BASELINES[name](r, SMALL).count() == 0
    twice = spark.createDataFrame([(1, "ACGTACGTAC"), (1, "ACGTACGTAC")], "read_id long, seq string")
    assert set(as_dict(flagship.count_kmers(twice, SMALL), 9).values()) == {2}


def test_chunks_hold_every_window_once(spark):
    seq = "".join(random.Random(3).choice("ACGTN") for _ in range(1000))
    r = make_reads(spark, [seq])
    rows = prepare.extract_kmers(r, SMALL.but(chunk=50), ext=True).select(alphabet.unpack(F.col("kmer"), 9).alias("kmer"), "pos").collect()
    assert sorted((x["pos"], x["kmer"]) for x in rows) == [(i, seq[i : i + 9]) for i in range(992) if "N" not in seq[i : i + 9]]
    native = prepare.extract_kmers_native(r, 9).select("pos", "kmer").collect()
    assert sorted(map(tuple, native)) == sorted((x["pos"], x["kmer"]) for x in rows)
    frags = prepare.fragments(r, SMALL.but(chunk=1 << 16)).collect()
    assert sorted(f["seq"] for f in frags) == sorted(p for p in seq.split("N") if len(p) >= 9)


def test_reads_are_dealt_evenly(spark):
    r = make_reads(spark, ["A" * (10 * i) for i in range(200)])
    sizes = [x["n"] for x in prepare.balance_reads(r, 4).groupBy(F.spark_partition_id().alias("p")).agg(F.sum(F.length("seq")).alias("n")).collect()]
    assert len(sizes) == 4 and max(sizes) < 1.15 * sum(sizes) / 4


@pytest.mark.parametrize("score", ["murmur3", "lex", "lex_mod", "arith", "universal"])
def test_columns_and_arrays_score_alike(spark, score):
    import numpy as np

    values = [int(x) for x in np.random.default_rng(2).integers(0, 4**11, 300)] + [0, 4**11 - 1]
    got = spark.createDataFrame([(v,) for v in values], "mmer long").select("mmer", scores.score_column(F.col("mmer"), 11, score).alias("s")).collect()
    want = scores.score_array(np.array(values), 11, score)
    assert {r["mmer"]: r["s"] for r in got} == dict(zip(values, want.tolist())) and want.min() >= 0
    if score == "murmur3":
        assert scores.murmur3(np.array([1]))[0] == 2582647965


@pytest.mark.parametrize("break_on", ["task", "minimizer"])
def test_supermers_equal_the_window_form(reads, break_on):
    spec = SMALL.but(break_on=break_on, chunk=1 << 12)
    rows = sm.supermer_bases(sm.build_supermers(reads, spec))
    plain = sm.supermers_window(reads, spec)
    assert sorted(map(tuple, rows.select("read_id", "task", "start", "n_bases").collect())) == sorted(map(tuple, plain.select("read_id", "task", "start", "n_bases").collect()))
    texts = {i: s for i, s in enumerate(random_reads())}
    assert all(texts[r["read_id"]][r["start"] : r["start"] + r["n_bases"]] == r["bases"] for r in rows.collect())


def test_minimizers_by_all_plans(reads):
    spec = SMALL.but(chunk=1 << 12)
    want = sorted(map(tuple, sm.minimizers_window(reads, spec).select("read_id", "pos", "score").collect()))
    for method in ("block", "deque", "rescan", "naive"):
        assert sorted(map(tuple, sm.minimizers_arrow(reads, spec, method).select("read_id", "pos", "score").collect())) == want
    assert sorted(map(tuple, sm.minimizers_naive(reads, spec).select("read_id", "pos", "score").collect())) == want


@pytest.mark.parametrize("k", [9, 40])
@pytest.mark.parametrize("factor", [0.5, 1e9])
def test_index_and_overlaps(spark, reads, k, factor):
    spec = CountSpec(k=k, s=13, lo=2, hi=30, heavy_factor=factor, chunk=256)
    a, b = index.kmer_index(reads, spec), index.kmer_index_native(reads, spec)
    assert counting.same_counts(a, b) and a.count() > 0
    occ = {}
    for i, s in enumerate(random_reads()):
        for p in range(len(s or "") - k + 1):
            if set(s[p : p + k]) <= set("ACGT"):
                occ.setdefault(s[p : p + k], []).append((i, p))
    pairs = {}
    for places in occ.values():
        if 2 <= len(places) <= 30:
            for (r1, p1), (r2, p2) in itertools.combinations(sorted(places), 2):
                if r1 < r2:
                    pairs.setdefault((r1, r2), []).append(p2 - p1)
    want = {(*rs, len(d), min(d), max(d)) for rs, d in pairs.items() if len(d) >= 2}
    found = index.overlap_candidates(a, 2)
    assert {tuple(r) for r in found.collect()} == want
    assert index.prune_transitive(found).count() <= len(want)
    asked = a.select("kmer").limit(3)
    assert index.lookup(a, asked).count() == 3


def test_locations_survive_the_codec(reads):
    rows = sm.expand_supermers(sm.build_supermers(reads, SMALL), SMALL, ("task", "read_id", "pos"))
    for mode in ("pair", "per_field"):
        assert counting.same_counts(exchange.decode_ext(exchange.encode_ext(rows, mode)), rows.select("task", "read_id", "pos"))
    sizes = exchange.location_bytes(rows).first()
    assert sizes["coded_bytes"] < 9 * sizes["occurrences"]
    ids = exchange.dense_ids(reads.select((F.col("read_id") * 10**12).alias("read_id"))).collect()
    assert sorted(r["dense"] for r in ids) == list(range(len(ids))) and len({r["read_id"] for r in ids}) == len(ids)


def test_sketches(spark, reads):
    kmers = prepare.extract_kmers(reads, SMALL).cache()
    true = brute(random_reads(), 9)
    got = sketches.distinct_estimate(kmers).first()
    assert abs(got["estimate"] - len(true)) < 0.1 * len(true)
    more = sketches.distinct_estimate(kmers.unionAll(kmers)).first()
    assert more["sketch_bytes"] < 2 * got["sketch_bytes"] + 64
    exact = baselines.count_dist_hash(reads, SMALL)
    for slots in (1 << 6, 1 << 16):
        errors = metrics.over_counts(baselines.count_cbf(reads, SMALL, slots=slots), exact).first()
        assert errors["under"] == 0 and errors["keys"] == len(true)
    assert errors["over"] == 0
    import numpy as np

    bloom = sketches.Bloom(2000, 0.02)
    keys = np.random.default_rng(0).integers(0, 2**62, 4000)
    bloom.add([keys[:2000]])
    assert bloom.has([keys[:2000]]).all() and bloom.has([keys[2000:]]).mean() <= 0.04
    model = sketches.hash_memory_model(1000)
    assert model["hash_table"] > 2 * model["sorted_inplace"]


def test_hash_order_balances_better_than_lexical(spark):
    rng = random.Random(1)
    r = make_reads(spark, ["".join(rng.choice("AAACGT") for _ in range(3000)) for _ in range(20)])
    spread = {s: metrics.balance(flagship.kmers_per_task(r, CountSpec(k=31, s=64, score=s)))["stddev"] for s in ("murmur3", "lex")}
    assert spread["murmur3"] < spread["lex"]


def test_shorter_minimizers_skew_and_longer_ones_cost_bytes(spark):
    rng = random.Random(2)
    r = make_reads(spark, ["".join(rng.choice("ACGT") for _ in range(2000)) for _ in range(20)])
    got = {m: exchange.exchange_bytes(sm.build_supermers(r, CountSpec(k=31, m=m)), CountSpec(k=31)).first()["saved"] for m in (7, 17, 27)}
    assert got[7] > got[17] > got[27] and got[17] > 0.75


def test_measures():
    assert metrics.speedup(26.5, 15.4) == pytest.approx(1.72, abs=0.005)
    assert metrics.strong_efficiency(10, 1, 2, 4) == 1.25 and metrics.weak_efficiency(8, 10) == 0.8
    assert metrics.balance([2, 4])["max_min"] == 2
    assert counting.choose_sort(10, 100) == "aux_radix" and counting.choose_sort(40, 100) == "inplace" and counting.choose_sort(70, 100) == "spark_radix"


def test_stage_times_and_memory(reads):
    times = metrics.stage_times(reads, SMALL, 3)
    assert set(times) == {"preparation", "exchange", "counting"} and all(t >= 0 for t in times.values())
    assert metrics.peak_memory(lambda: flagship.count_kmers(reads, SMALL, 3)) > 50 << 20


def test_plan_has_one_exchange_by_place(spark):
    from seqcount.functions.alphabet import fold_text

    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").where("lang = 'en'")
    reads = docs.select(F.col("doc_id").alias("read_id"), fold_text(F.col("text")).alias("seq"))
    text = lambda df: df._jdf.queryExecution().executedPlan().toString()
    plan = text(flagship.count_kmers(reads, SMALL, 4, plan=flagship.make_plan(reads, SMALL, 4)))
    assert plan.count("Exchange ") == 1 and "REPARTITION_BY_NUM" in plan and plan.count("MapInArrow") == 2
    assert text(baselines.count_thread_owned(reads, SMALL)).count("Exchange ") == 1
    scan = text(prepare.extract_kmers(reads, SMALL))
    assert "PushedFilters: [" in scan and "EqualTo(lang,en)" in scan and "n_chars" not in scan


def test_key_counts_need_no_alphabet(spark):
    rows = spark.createDataFrame([(x,) for x in [5, 5, -3, None, 7, 5]], "key long")
    for how in ("sort", "range", "hash", "precount"):
        assert {tuple(r) for r in baselines.count_keys(rows, "key", how).collect()} == {(5, 3), (-3, 1), (7, 1)}
