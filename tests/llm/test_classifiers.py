import random
import zlib

import numpy as np
import pyarrow as pa
import pytest

from seqcount.llm import quality_knn, textkernel, toxicity_ftrl

WORDS = [f"{a}{b}" for a in ("ta", "re", "mi", "so", "lu") for b in ("n", "r", "st", "", "ble", "ing")]
INSULTS = ["scum", "moron", "trashy"]


def corpus(n, seed):
    rng = random.Random(seed)
    rows = []
    for i in range(n):
        words = [rng.choice(WORDS) for _ in range(rng.randint(20, 120))]
        good, toxic = i % 3 != 0, i % 5 == 0
        if toxic:
            words = [rng.choice(INSULTS) if rng.random() < 0.1 else w for w in words] + ["scum"]
        if not good:
            words = [w.upper() + "!!" for w in words] if i % 2 else [w for w in words for _ in range(8)]
        rows.append((i, " ".join(words), int(good), int(toxic)))
    return rows


def test_words_and_hashes_are_those_of_a_plain_split():
    texts = [None, "", " \t", "A bc  d\n", "x\x00 x", "é É \x1f", "word " * 50, "ab abc abcd"]
    for g in textkernel.groups_of_words(pa.array(texts), style=True, stems=(2,)):
        by_hash = {}
        at = 0
        for d, t in enumerate(texts):
            for w in bytes(c + 32 if 65 <= c <= 90 else c for c in (t or "").encode()).split():
                assert g.doc[at] == d
                assert by_hash.setdefault(int(g.word[at]), w) == w
                at += 1
        assert at == len(g.word) and len(set(by_hash.values())) == len(by_hash)
        longer, heads = g.stems[0]
        words = [w for t in texts for w in (t or "").lower().encode().split()]
        assert [len(w) > 2 for w in words] == [i in set(longer.tolist()) for i in range(len(words))]
        same = {}
        for i, h in zip(longer.tolist(), heads.tolist()):
            assert same.setdefault(words[i][:2], h) == h


def test_long_words_and_runs_count_once(monkeypatch):
    texts = pa.array(["a " + "long" * 900 + " b c", "run " * 700 + "w" * 3000, "x" * 5000])
    whole = [[x.tolist() for x in part[2:5]] for part in quality_knn.term_counts(texts)]
    monkeypatch.setattr(textkernel, "GROUP_BYTES", 300)
    parts = list(quality_knn.term_counts(texts))
    assert [[int(p[0]) for p in parts for _ in p[2]], [x for p in parts for x in p[3].tolist()], [x for p in parts for x in p[4].tolist()]] == whole[0]


def test_blocks_of_a_long_text_count_like_one_group(monkeypatch):
    rng = random.Random(0)
    texts = [" ".join(rng.choice(WORDS) for _ in range(5000)), "short one", " ".join(rng.choice(WORDS) for _ in range(900))]
    whole = [(int(f), d.tolist(), t.tolist(), v.tolist()) for f, _, d, t, v in toxicity_ftrl.features(pa.array(texts))]
    one = {f + d: {} for f, ds, *_ in whole for d in ds}
    for f, ds, ts, vs in whole:
        for d, t, v in zip(ds, ts, vs):
            one[f + d][t] = v
    monkeypatch.setattr(textkernel, "GROUP_BYTES", 700)
    two = {}
    for f, _, d, t, v in toxicity_ftrl.features(pa.array(texts)):
        for a, b, c in zip(d.tolist(), t.tolist(), v.tolist()):
            two.setdefault(int(f) + a, {})[b] = c
    assert one.keys() == two.keys()
    assert all(one[d] == pytest.approx(two[d]) for d in one)


def plain_terms(text):
    """The terms of the quality model, word by word: repeats by place in the run, words, styles."""
    words = bytes(text or "", "utf-8").split()
    low = [bytes(c + 32 if 65 <= c <= 90 else c for c in w) for w in words]
    (g,) = textkernel.groups_of_words(pa.array([text], pa.string()), style=True)
    half, out, run = quality_knn.N_TERMS // 2, {}, 0
    for i, w in enumerate(low):
        run = run + 1 if i and w == low[i - 1] else 0
        terms = [int(g.word[i]) % (half - 16) + 16, int(textkernel.mix(g.style[i : i + 1] + quality_knn._STYLE)[0]) % half + half]
        for t in [*terms, *([min(run, 16) - 1] if run else [])]:
            out[t] = out.get(t, 0) + 1
    return out


def test_quality_scores_are_those_of_a_plain_vote():
    rows = corpus(160, 5)
    texts = [r[1] for r in rows] + [None, "", "word " * 40, "solo"]
    model = quality_knn.fit(pa.array(texts[:100]), np.array([r[2] for r in rows[:100]]))

    def latent(text):
        v = np.zeros(model["basis"].shape[1])
        for t, n in plain_terms(text).items():
            v += (1 + np.log(n)) * model["idf"][t] * model["basis"][t]
        norm = np.linalg.norm(v)
        return v / norm if norm else v

    for text, got in zip(texts, quality_knn.scores(model, pa.array(texts)).tolist()):
        v = latent(text)
        if not v.any():
            assert got == pytest.approx(float(model["prior"]))
            continue
        near = sorted(((float(v @ k), float(y)) for k, y in zip(model["vectors"], model["labels"])), reverse=True)[: quality_knn.NEIGHBOURS]
        weights = [max(c, 0) ** quality_knn.SHARPNESS for c, _ in near]
        assert got == pytest.approx(sum(w * y for w, (_, y) in zip(weights, near)) / sum(weights), abs=2e-3)


def test_quality_latent_space_is_that_of_the_singular_vectors():
    rows = corpus(120, 8)
    model = quality_knn.fit(pa.array([r[1] for r in rows]), np.array([r[2] for r in rows]))
    a = np.zeros((len(rows), quality_knn.N_TERMS))
    for i, r in enumerate(rows):
        for t, n in plain_terms(r[1]).items():
            a[i, t] = (1 + np.log(n)) * model["idf"][t]
    a /= np.linalg.norm(a, axis=1, keepdims=True)
    s = np.linalg.svd(a, compute_uv=False)
    kept = np.linalg.norm(a @ model["basis"]) ** 2
    assert kept > 0.97 * (s[: model["basis"].shape[1]] ** 2).sum()


def test_toxicity_weights_are_those_of_a_plain_ftrl_loop():
    rows = corpus(80, 6)
    t = toxicity_ftrl
    features = t.rows_of_features(pa.array([r[1] for r in rows]))
    model = t.fit(features, np.array([r[3] for r in rows]))
    z, n, bias_z, bias_n = {}, {}, 0.0, 0.0
    order = np.random.default_rng(42)

    def weight(i):
        zi = z.get(i, 0.0)
        return 0.0 if abs(zi) <= t.L1 else -(zi - np.sign(zi) * t.L1) / ((t.BETA + n[i] ** 0.5) / t.ALPHA + t.L2)

    bias = 0.0
    for _ in range(t.EPOCHS):
        for i in order.permutation(len(rows)).tolist():
            x, value = features[i]
            w = [weight(j) for j in x.tolist()]
            bias = -bias_z / ((t.BETA + bias_n**0.5) / t.ALPHA)
            p = 1 / (1 + np.exp(-np.clip(sum(a * b for a, b in zip(w, value.tolist())) + bias, -35, 35)))
            miss = p - rows[i][3]
            for j, v, wj in zip(x.tolist(), value.tolist(), w):
                g = miss * v
                old = n.get(j, 0.0)
                n[j] = old + g * g
                z[j] = z.get(j, 0.0) + g - (n[j] ** 0.5 - old**0.5) / t.ALPHA * wj
            step = ((bias_n + miss * miss) ** 0.5 - bias_n**0.5) / t.ALPHA
            bias_z, bias_n = bias_z + miss - step * bias, bias_n + miss * miss
    want = {j: weight(j) for j in z if weight(j)}
    got = dict(zip(model["at"].tolist(), model["weight"].tolist()))
    assert got.keys() == want.keys() and all(got[j] == pytest.approx(want[j], rel=1e-4, abs=1e-5) for j in want)
    assert 0 < len(got) < len(z) / 4


def test_samples_are_bounded_and_defined(spark, monkeypatch):
    monkeypatch.setattr(quality_knn, "SAMPLE_TEXT_BYTES", 40)
    docs = spark.createDataFrame([(1, f"copy {i}") for i in range(300)] + [(i, "x" * i) for i in range(2, 90)] + [(None, "none")], "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(90)] + [(7, 0), (None, 1), (8, None)], "doc_id long, quality int")
    got = {r["s_id"]: (r["text"], r["s_label"]) for r in quality_knn.labelled_sample(docs, labels, "quality", 1000, lambda c: quality_knn.F.lit(True)).collect()}
    assert got.pop(1) == ("copy 0", 1)
    assert got == {i: ("x" * i, i % 2) for i in range(2, 41) if i != 7}
    few = quality_knn.labelled_sample(docs, labels, "quality", 3, lambda c: quality_knn.F.lit(True))
    assert few.count() <= 6


def test_rows_without_an_id_are_not_held_out(spark):
    rows = spark.createDataFrame([(None,), (5,)], "doc_id long")
    for module, base, out in ((quality_knn, 4, 2), (toxicity_ftrl, 3, 1)):
        got = {r["doc_id"]: r["h"] for r in rows.select("doc_id", module.held_out().alias("h")).collect()}
        assert got == {None: False, 5: zlib.crc32(b"5") % base == out}


@pytest.mark.parametrize("module, column", [(quality_knn, 2), (toxicity_ftrl, 3)])
def test_held_out_accuracy(spark, module, column):
    rows = corpus(900, 1)
    name = "quality" if module is quality_knn else "toxic"
    docs = spark.createDataFrame([(r[0], r[1]) for r in rows] + [(5000, None), (5001, ""), (5002, "q" * 200_000)], "doc_id long, text string")
    labels = spark.createDataFrame([(r[0], r[2], r[3]) for r in rows] + [(None, 1, 1), (3, None, None), (7, 1, 1)], "doc_id long, quality int, toxic int")
    model = module.train(docs, labels)
    scored = module.with_scores(docs.selectExpr("doc_id", "text", "'x' as lang"), model)
    got = {r["doc_id"]: r["score"] for r in scored.collect()}
    assert len(got) == 903 and all(0 <= s <= 1 for s in got.values())
    remainder, base = (2, 4) if module is quality_knn else (1, 3)
    held = [r for r in rows if zlib.crc32(str(r[0]).encode()) % base == remainder]
    assert np.mean([(got[r[0]] >= 0.7) == r[column] for r in held]) > 0.95
    assert module.with_scores(docs.limit(0), model).count() == 0
    assert name in labels.columns


def test_held_out_rows_have_no_part_in_the_model(spark):
    rows = corpus(300, 2)
    docs = spark.createDataFrame([(r[0], r[1]) for r in rows], "doc_id long, text string")
    labels = spark.createDataFrame([(r[0], r[2], r[3]) for r in rows], "doc_id long, quality int, toxic int")
    for module, name, base, out in ((quality_knn, "quality", 4, 2), (toxicity_ftrl, "toxic", 3, 1)):
        flipped = labels.rdd.map(lambda r, b=base, o=out: (r[0], *(1 - x if zlib.crc32(str(r[0]).encode()) % b == o else x for x in r[1:]))).toDF(labels.schema)
        a, b = module.train(docs, labels), module.train(docs, flipped)
        assert all(np.array_equal(a[k], b[k]) for k in a), name


def test_no_labels_give_the_prior(spark):
    docs = spark.createDataFrame([(1, "a b c"), (2, None)], "doc_id long, text string")
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    for module in (quality_knn, toxicity_ftrl):
        got = [r["score"] for r in module.with_scores(docs, module.train(docs, labels)).collect()]
        assert got == [0.5, 0.5]
