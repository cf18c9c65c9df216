"""Hand examples, and properties of the array kernels on random sequences."""

import random

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from seqcount.functions import kernel, minimizers, scores
from seqcount.operators import exchange
from seqcount.operators.tasks import assign_tasks, heavy_tasks, loads
from seqcount.spec import CountSpec, default_m, tasks_from


def codes_of(seq):
    return np.array(["ACGT".find(c) if c in "ACGT" else 4 for c in seq], np.uint8)


def word(seq):
    return int("".join(str("ACGT".index(c)) for c in seq), 4)


def brute_kmers(seq, k):
    return [seq[i : i + k] for i in range(len(seq) - k + 1) if set(seq[i : i + k]) <= set("ACGT")]


def decode(words, k):
    n = [(int(a) << 62 | int(b)) if len(words) == 2 else int(a) for a, *rest in zip(*words) for b in (rest or [0])]
    return ["".join("ACGT"[(x >> 2 * (k - 1 - i)) & 3] for i in range(k)) for x in n]


def revcomp(s):
    return s[::-1].translate(str.maketrans("ACGT", "TGCA"))


def test_example_counts_and_supermers():
    seq = "ACGTACGTAC"
    spec = CountSpec(k=5, m=3, s=1 << 20, score="lex", break_on="minimizer", chunk=64)
    words, n = kernel.count_runs(kernel.valid_kmers(codes_of(seq), 5))
    assert dict(zip(decode(words, 5), n.tolist())) == {"ACGTA": 2, "CGTAC": 2, "GTACG": 1, "TACGT": 1}
    found = kernel.find_supermers(codes_of(seq), spec)
    pieces = [seq[b : b + m] for b, m in zip(found.begin.tolist(), found.n_bases.tolist())]
    assert pieces == ["ACGTA", "CGTAC", "GTACGTA", "CGTAC"] and sum(map(len, pieces)) == 22
    least, where = minimizers.window_block(kernel.mmer_scores(codes_of(seq), spec), spec.w, "left")
    assert [seq[i : i + 3] for i in where.tolist()] == ["ACG", "CGT", "ACG", "ACG", "ACG", "CGT"] and where.tolist() == [0, 1, 4, 4, 4, 5]


def test_example_packing_of_tasks():
    placed = assign_tasks([9, 7, 6, 5, 4, 3], 2, growth=0.10)
    assert sorted(loads([9, 7, 6, 5, 4, 3], placed, 2)) == [16, 18]
    assert heavy_tasks(np.array([100, 10, 10, 10, 10]), 3).tolist() == [0]
    assert heavy_tasks(np.zeros(0)).tolist() == []


def test_example_locations():
    reads, places = np.array([7, 7, 7, 8]), np.array([100, 104, 300, 5])
    data = exchange.encode_locations(reads, places)
    assert len(data) == 4 + 9 + 3 + 9 + 9
    back = exchange.decode_locations(data)
    assert back[0].tolist() == reads.tolist() and back[1].tolist() == places.tolist()
    assert len(exchange.encode_locations(reads, places, "per_field")) == 4 + 9 + 3 + 6 + 6


def test_example_rounds_and_words():
    assert exchange.plan_rounds([170_000, 3], 80_000) == 3
    assert int(kernel.rolling_pack(codes_of("ACGT"), 4)[0]) == 27
    assert decode([kernel.reverse_complement(kernel.rolling_pack(codes_of("AACG"), 4), 4)], 4) == ["CGTT"]
    assert exchange.overlap_model([2, 2], [1, 1], [1, 1]) == (6.0, 8)


def test_default_lengths():
    assert [default_m(k) for k in (17, 31, 55)] == [11, 17, 23]
    assert all(1 <= default_m(k) <= max(1, k - 1) for k in range(1, 63)) and tasks_from(16, 2, 3) == 96
    for bad in ({"k": 0}, {"k": 63}, {"k": 5, "m": 6}, {"s": 0}, {"score": "x"}, {"lo": 3, "hi": 2}, {"chunk": 8}):
        with pytest.raises(ValueError):
            CountSpec(**bad)


@pytest.mark.parametrize("k", [1, 2, 5, 30, 31, 32, 33, 55, 61, 62])
@pytest.mark.parametrize("canonical", [False, True])
def test_words_of_all_lengths(k, canonical):
    rng = random.Random(k)
    for n in (0, k - 1, k, k + 1, 300):
        seq = "".join(rng.choice("ACGTACGTACGTN") for _ in range(n))
        want = brute_kmers(seq, k)
        if canonical:
            want = [min(x, revcomp(x)) for x in want]
        codes = codes_of(seq)
        ok = kernel.window_valid(codes, k)
        hi_lo = [w[ok] for w in kernel.kmer_words(codes, k, canonical)]
        if len(hi_lo) == 2:
            assert [(int(a), int(b)) for a, b in zip(*hi_lo)] == [(word(x[: k - 31]), word(x[k - 31 :])) for x in want]
        else:
            assert hi_lo[0].tolist() == [word(x) for x in want]


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 12), max_size=200), st.integers(1, 30), st.sampled_from(["left", "right"]))
def test_minimizer_methods_agree(values, w, tie):
    x = np.array(values, np.int64)
    want = minimizers.window_naive(x, w, tie)
    for name, find in minimizers.METHODS.items():
        got = find(x, w, tie)
        assert got[0].tolist() == want[0].tolist(), name
        assert got[1].tolist() == want[1].tolist(), name
    assert minimizers.block_minimum(x, w).tolist() == want[0].tolist()


def test_work_of_minimizer_methods():
    x = np.arange(5000, dtype=np.int64)  # a rising sequence: the current minimizer expires at each step
    work = {}
    for name, find in minimizers.METHODS.items():
        work[name] = minimizers.Work()
        find(x, 40, "right", work[name])
    assert work["deque"].comparisons <= 2 * len(x) < work["rescan"].comparisons
    assert work["naive"].comparisons == (len(x) - 39) * 40


@settings(max_examples=40, deadline=None)
@given(st.text("ACGTN", max_size=400), st.sampled_from(scores.__dict__.get("SCORES", ("murmur3", "lex", "lex_mod", "arith", "universal"))), st.sampled_from([1, 7, 256]), st.booleans(), st.booleans())
def test_supermers_hold_each_kmer_once_and_part_by_value(seq, score, s, canonical, by_minimizer):
    spec = CountSpec(k=9, m=4, s=s, score=score, canonical=canonical, break_on="minimizer" if by_minimizer else "task", chunk=64)
    codes = codes_of(seq)
    found = kernel.find_supermers(codes, spec)
    pieces = [seq[b : b + n] for b, n in zip(found.begin.tolist(), found.n_bases.tolist())]
    assert all(len(p) >= 9 and "N" not in p for p in pieces)
    assert [x for p in pieces for x in brute_kmers(p, 9)] == brute_kmers(seq, 9)
    home = {}
    for p, t in zip(pieces, found.task.tolist()):
        for x in brute_kmers(p, 9):
            key = min(x, revcomp(x)) if canonical else x
            assert home.setdefault(key, t) == t and 0 <= t < s
    packed, offsets = kernel.pack_runs(codes, found.begin, found.n_bases)
    back, begins = kernel.unpack_runs(packed, found.n_bases)
    assert ["".join("ACGT"[c] for c in back[b : b + n]) for b, n in zip(begins.tolist(), found.n_bases.tolist())] == pieces
    n, packed2, ids, starts = exchange.unpack_block(len(pieces), exchange.pack_block(found.n_bases, packed, (found.begin, found.begin)), ext=True)
    assert n.tolist() == found.n_bases.tolist() and packed2.tolist() == packed.tolist() and ids.tolist() == starts.tolist() == found.begin.tolist()


def test_long_runs_are_cut_to_sixteen_bits():
    codes = np.zeros(200_000, np.uint8)
    found = kernel.find_supermers(codes, CountSpec(k=31))
    assert found.n_bases.max() <= kernel.MAX_BASES and (found.n_bases - 30).sum() == 200_000 - 30


@pytest.mark.parametrize("method", ["inplace", "aux_radix"])
@pytest.mark.parametrize("bucket, moved", [(1 << 17, 1 << 14), (64, 16), (5, 3)])
def test_radix_sorts_of_any_width_and_weight(monkeypatch, method, bucket, moved):
    monkeypatch.setattr(kernel, "BUCKET", bucket)
    monkeypatch.setattr(kernel, "MOVED", moved)
    rng = np.random.default_rng(bucket)
    for n in (0, 1, 2, 7, 100, 2500):
        for words in (1, 2):
            for weighted in (False, True):
                for high in (1, 5, 1 << 20, 1 << 62):
                    keys = [rng.integers(0, min(high, 1 << 48) if words == 2 and not i else high, n) for i in range(words)]
                    weights = rng.integers(1, 9, n) if weighted else None
                    want = {}
                    for i, key in enumerate(zip(*(x.tolist() for x in keys))):
                        want[key] = want.get(key, 0) + (int(weights[i]) if weighted else 1)
                    got, counts = kernel.count_runs([x.copy() for x in keys], weights, method)
                    assert list(zip(zip(*(x.tolist() for x in got)), counts.tolist())) == sorted(want.items())


@pytest.mark.parametrize("method", ["inplace", "aux_radix"])
@pytest.mark.parametrize("words", [1, 2])
def test_counts_of_runs(method, words):
    rng = np.random.default_rng(1)
    keys = [rng.integers(0, 2**61 if i else 5, 4000) % (7 if i else 2**62) for i in range(words)]
    got, n = kernel.count_runs(keys, method=method)
    want = {}
    for key in zip(*(x.tolist() for x in keys)):
        want[key] = want.get(key, 0) + 1
    assert dict(zip(zip(*(x.tolist() for x in got)), n.tolist())) == want
    assert list(zip(*(x.tolist() for x in got))) == sorted(want)
    twice, m = kernel.count_runs([np.r_[x, x] for x in got], np.r_[n, n])
    assert m.tolist() == (2 * n).tolist() and all((a == b).all() for a, b in zip(twice, got))
    big = rng.integers(0, 2**62, 3000)
    assert kernel.aux_radix([big])[0][0].tolist() == sorted(big.tolist())


@settings(max_examples=60, deadline=None)
@given(st.lists(st.tuples(st.integers(-3, 2**31 - 1), st.integers(-400, 400)), max_size=60), st.sampled_from(["pair", "per_field"]))
def test_locations_round_trip(rows, mode):
    reads, places = np.array([r for r, _ in rows], np.int64), np.cumsum(np.array([p for _, p in rows], np.int64))
    back = exchange.decode_locations(exchange.encode_locations(reads, places, mode))
    assert back[0].tolist() == reads.tolist() and back[1].tolist() == places.tolist()


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 1000), max_size=60), st.integers(1, 9), st.sampled_from(["greedy", "longest_first", "round_robin", "modulo"]))
def test_every_task_has_a_place(sizes, partitions, policy):
    placed = assign_tasks(sizes, partitions, 0.05, policy)
    assert len(placed) == len(sizes) and all(0 <= p < partitions for p in placed)
    if policy == "greedy" and sizes:
        level = max(sum(sizes) / partitions, max(sizes))
        assert loads(sizes, placed, partitions).max() <= 2 * level + 1


def test_groups_keep_places_over_odd_batches():
    seqs = pa.array(["ACGT", None, "", "N", "acgt", "TT" * 50, "é"])[1:]
    parts = [(first, row.tolist(), place.tolist(), codes.tolist()) for first, row, place, codes in kernel.groups(seqs, 8)]
    out = {}
    for first, row, place, codes in parts:
        for r, p, c in zip(row, place, codes):
            out.setdefault(first + r, {})[p] = c
    assert {r: len(x) for r, x in out.items()} == {0: 1, 1: 1, 2: 2, 3: 5, 4: 101, 5: 3}
    assert set(out[3].values()) == {4} and set(list(out[4].values())[:-1]) == {3}
