import math
import random

import numpy as np
import pytest

from seqcount.llm import topk_nra


def brute(rows, k, scale=64):
    sound = [(i, [math.floor(scale * x) for x in v]) for i, v in rows if i is not None and v and all(x is not None and math.isfinite(x) for x in v)]
    out = []
    for a, (i, q) in enumerate(sound):
        if i % 20 == 0:
            near = sorted((-sum(x * y for x, y in zip(q, v)), j) for b, (j, v) in enumerate(sound) if b != a and len(v) == len(q))[:k]
            out += [(i, r + 1, j, -s) for r, (s, j) in enumerate(near)]
    return sorted(out)


@pytest.mark.parametrize("kind", ["spread", "clustered", "ties"])
def test_equals_brute_force(spark, monkeypatch, kind):
    monkeypatch.setattr(topk_nra, "LANE_ROWS", 150)
    monkeypatch.setattr(topk_nra, "CHUNK_ROWS", 9)
    rng = random.Random(kind)
    centres = [[rng.gauss(0, 1) for _ in range(8)] for _ in range(5)]
    rows = []
    for i in range(600):
        c = rng.choice(centres)
        v = {"spread": lambda: [rng.uniform(-1, 1) for _ in range(8)], "clustered": lambda: [x + rng.gauss(0, 0.05) for x in c], "ties": lambda: [float(rng.choice([-1, 0, 1])) for _ in range(8)]}[kind]()
        rows.append((i, v))
    rows += [(620, None), (640, []), (660, [1.0] * 7 + [None]), (680, [float("nan")] * 8), (700, [float("inf")] * 8), (720, [0.5] * 3), (721, [0.25] * 3), (None, [0.1] * 8)]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<double>").selectExpr("vec_id", "embedding", "1 as dim", "2 as lane")
    got = topk_nra.top_k(frame, "vec_id", "embedding", lambda i: i % 20 == 0, 20)
    assert sorted(map(tuple, got.collect())) == brute(rows, 20)


def test_few_or_no_rows(spark):
    frame = spark.createDataFrame([(0, [0.5, -0.5]), (1, [1.0, 1.0])], "vec_id long, embedding array<float>")
    assert [tuple(r) for r in topk_nra.top_k(frame, "vec_id", "embedding", lambda i: i % 20 == 0).collect()] == [(0, 1, 1, 0)]
    assert topk_nra.top_k(frame.limit(0), "vec_id", "embedding", lambda i: i % 20 == 0).count() == 0


def read_share(v, q, k=20):
    query, row, score, reads = topk_nra.cell_top(q, np.arange(len(q)) + len(v), v, topk_nra.Lists.sort(v), np.arange(len(v)), k)
    want = np.sort(q @ v.T, axis=1)[:, ::-1][:, :k]
    assert np.array_equal(score.reshape(len(q), k), want) and np.array_equal((q[query] * v[row]).sum(1), score)
    return reads / (len(q) * v.size)


def test_lists_stop_before_their_ends_when_outsiders_cannot_qualify():
    rng = np.random.default_rng(0)
    v = rng.normal(0, 3, (4000, 4)).round()
    v[:40] += 60
    assert read_share(v, np.abs(rng.normal(0, 40, (50, 4))).round()) < 0.1


@pytest.mark.parametrize("name", ["given", "normal", "skewed"])
def test_reads_of_64_components_end_with_the_lists_at_most(name):
    """Vectors of 64 even components need most of their lists; a few strong components end the reading sooner."""
    import pyarrow.parquet as pq

    rng = np.random.default_rng(1)
    v = rng.normal(0, 1, (1500, 64))
    if name == "given":
        v = np.array(pq.read_table("/root/testdata/sf0.1/embeddings.parquet")["embedding"].to_pylist())[:1500]
    if name == "skewed":
        v = v / np.arange(1, 65) ** 2
    v = np.floor(64 * v.astype(float))
    share = read_share(v, v[::20])
    assert share <= 1 and (name != "skewed" or share < 0.8)


def test_large_components_are_exact(spark):
    rng = random.Random(5)
    rows = [(i, [rng.choice([1e9, -1e9, 3e8, 0.5, 1e-3]) * rng.random() for _ in range(6)]) for i in range(80)] + [(100, [1e30] * 6), (101, [-1e30] * 6), (120, [1e30] * 5 + [2e30]), (121, [1e308] * 6)]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = [tuple(r) for r in topk_nra.top_k(frame, "vec_id", "embedding", lambda i: i % 20 == 0, 20).collect()]
    limit = (1 << 63) - 1
    want = [(q, r, c, max(-limit - 1, min(limit, s))) for q, r, c, s in brute([x for x in rows if x[0] != 121], 20)]
    assert sorted(got) == sorted(want)
