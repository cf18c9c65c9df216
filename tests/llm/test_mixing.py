import random
import re

import pytest

from seqcount.llm import mixing


def brute_targets(sizes, weights):
    """Deal out by weight again and again; a source at its cap is closed."""
    total, target, open_ = 1.5 * sum(sizes), [0.0] * len(sizes), set(range(len(sizes)))
    while open_:
        rest = total - sum(target[i] for i in range(len(sizes)) if i not in open_)
        share = sum(weights[i] for i in open_)
        over = [i for i in open_ if rest * weights[i] / share > 2 * sizes[i]]
        for i in open_:
            target[i] = rest * weights[i] / share
        if not over:
            break
        for i in over:
            target[i] = 2.0 * sizes[i]
            open_.discard(i)
    return target


def test_level_equals_repeated_dealing():
    rng = random.Random(2)
    for _ in range(300):
        sizes = [rng.choice([0, 1, 5, 100, rng.randint(1, 10_000)]) for _ in range(rng.randint(1, 12))]
        weights = [(5, 2, 1)[i % 3] for i in range(len(sizes))]
        assert mixing.fill_to_level(sizes, weights) == pytest.approx(brute_targets(sizes, weights), abs=1e-6)


def test_words_and_copies(spark):
    rng = random.Random(1)
    texts = [None, "", " \t\n\x0b\x0c\r ", "one", " two\x0bwords ", "a\x1fb\xa0c d"] + ["w " * rng.randint(1, 50) for _ in range(600)]
    rows = [(i, t, rng.choice(["b", "a", None, "Z", "é"])) for i, t in enumerate(texts)] + [(3, "one", "a")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(5)
    got = mixing.mix_sizes(docs.selectExpr("*", "1 as target", "2 as m_size")).collect()
    sizes = {}
    for _, t, s in rows:
        n = len(re.findall(rb"[^\x20\x09-\x0D]+", (t or "").encode()))
        sizes[s] = sizes.get(s, 0) + n
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    targets = dict(zip(order, brute_targets([sizes[s] for s in order], [(5, 2, 1)[i % 3] for i in range(len(order))])))
    source = {(d, t): s for d, t, s in rows}
    assert sorted((r["rid"], r["m_size"]) for r in got) == sorted((d, len(re.findall(rb"[^\x20\x09-\x0D]+", (t or "").encode()))) for d, t, _ in rows)
    taken = {}
    by_id = {d: s for d, _, s in rows[: len(texts)]}
    for r in got:
        if r["rid"] != 3:
            s = by_id[r["rid"]]
            assert r["source_size"] == sizes[s] and r["target"] == pytest.approx(targets[s])
            taken[s] = taken.get(s, 0) + r["m_size"] * r["m_copies"]
        assert 0 <= r["m_copies"] <= 2
    for s, t in targets.items():
        assert abs(taken[s] - t) < 0.2 * t + 60
    assert source
    out = mixing.mix_sources(docs)
    assert out.columns == docs.columns
    copies = {}
    for r in out.collect():
        copies[r["doc_id"]] = copies.get(r["doc_id"], 0) + 1
    want = {}
    for r in got:
        if r["m_copies"]:
            want[r["rid"]] = want.get(r["rid"], 0) + r["m_copies"]
    assert copies == want
    assert sorted(r["doc_id"] for r in mixing.mix_sources(docs.repartition(2)).collect()) == sorted(d for d, n in want.items() for _ in range(n))
    assert mixing.mix_sizes(docs.limit(0)).count() == 0 and mixing.mix_sources(docs.limit(0)).count() == 0


def test_a_source_without_words_is_left_out(spark):
    docs = spark.createDataFrame([(1, "", "x"), (2, "a b", "y"), (3, None, None)], "doc_id long, text string, source string")
    assert {(r["rid"], r["m_copies"], r["target"]) for r in mixing.mix_sizes(docs).collect()} == {(1, 0, 0.0), (3, 0, 0.0), (2, 1, 3.0)} or {
        (r["rid"], r["target"]) for r in mixing.mix_sizes(docs).collect()
    } == {(1, 0.0), (3, 0.0), (2, 3.0)}
