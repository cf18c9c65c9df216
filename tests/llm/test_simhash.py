import random

import numpy as np
import pyarrow as pa
import pytest
import xxhash

from seqcount.llm import shingles, simhash


def brute_fingerprint(text, words=3):
    toks = "".join(c.lower() if "A" <= c <= "Z" else c for c in (text or "")).encode().split()
    if not toks:
        return 0
    shingles = [b" ".join(toks[i : i + words]) for i in range(max(1, len(toks) - words + 1))]
    hashes = [xxhash.xxh64_intdigest(s, 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


@pytest.mark.parametrize("text", [None, "", " \t", "One", "a b", "A b C", "É x\x0by z " * 50, "word " * 40000])
def test_fingerprint_is_the_majority_of_shingles(text):
    assert simhash.fingerprint(text) % (1 << 64) == brute_fingerprint(text)


def brute_shingles(text, words):
    toks = bytes(c + 32 if 65 <= c <= 90 else c for c in (text or "").encode()).split()
    return [xxhash.xxh64_intdigest(b" ".join(toks[i : i + words]), 42) for i in range(max(1, len(toks) - words + 1))] if toks else []


@pytest.mark.parametrize("group_bytes", [1 << 20, 500, 40, 7])
def test_array_hashes_and_bits_are_those_of_single_shingles(group_bytes):
    rng = random.Random(3)
    bits = ["a", "bc", "DEF", "é", "日本", " ", "  ", "\n", "\t", "longerword", " ", " "]
    texts = [None, "", " \t\n", "One", "a b", "É x\x0by z " * 20, "w" * 1000 + " x " + "v" * 40, "x " * 700]
    texts += ["".join(rng.choice([*bits, "x" * rng.randint(1, 60)]) for _ in range(rng.randint(0, 200))) for _ in range(120)]
    for words, carried in ((1, 1), (1, 5), (3, 3), (3, 5), (5, 5)):
        got, ones = {i: [] for i in range(len(texts))}, {i: 0 for i in range(len(texts))}
        for part in shingles.parts_of(pa.array(texts), carried, group_bytes):
            h, before = part.shingles(words)
            counts = shingles.bit_counts(h, before)
            for d in range(part.texts):
                got[part.first + d] += h[before[d] : before[d + 1]].tolist()
                ones[part.first + d] = ones[part.first + d] + counts[d]
        for i, t in enumerate(texts):
            assert got[i] == brute_shingles(t, words)
            assert np.broadcast_to(ones[i], 64).tolist() == [sum(x >> b & 1 for x in got[i]) for b in range(64)]


def test_long_texts_in_blocks_have_the_same_prints_and_keys(monkeypatch):
    rng = random.Random(6)
    texts = pa.array([" ".join(rng.choice("ab cd efg hi".split()) for _ in range(n)) for n in (0, 3, 4, 90, 400, 2, 700)])
    whole = simhash._prints_and_keys(texts, 5)
    lists = simhash.shingle_lists(texts, 5)
    monkeypatch.setattr(shingles, "GROUP_BYTES", 100)
    cut = simhash._prints_and_keys(texts, 5)
    assert whole[0].tolist() == cut[0].tolist() == [simhash.fingerprint(t.as_py()) for t in texts] and whole[1].equals(cut[1])
    assert [x.tolist() for x in lists] == [x.tolist() for x in simhash.shingle_lists(texts, 5)]


def pairs_within(fps, radius):
    return {(min(a, b), max(a, b)) for i, a in enumerate(fps) for b in fps[:i] if a != b and bin((a ^ b) % (1 << 64)).count("1") <= radius}


@pytest.mark.parametrize("radius, segments, key_rows", [(0, 2, 64), (1, 2, 3), (2, 2, 64), (2, 2, 3), (2, 4, 5), (2, 1, 2), (3, 2, 4), (3, 5, 8), (4, 2, 10), (4, 4, 3)])
def test_links_are_all_pairs_within_the_radius(spark, monkeypatch, radius, segments, key_rows):
    monkeypatch.setattr(simhash, "KEY_ROWS", key_rows)
    rng = random.Random(radius * 10 + segments)
    fps = [0, 1, 3, 7, 15, (1 << 64) - 1, 1 << 63]
    for _ in range(6):
        centre = rng.getrandbits(64)
        for _ in range(25):
            x = centre
            for _ in range(rng.randint(0, 4)):
                x ^= 1 << rng.randrange(64)
            fps.append(x)
        low = centre >> 32 << 32  # many that share a half
        fps += [low | rng.getrandbits(8) for _ in range(20)] + [(centre & 0xFFFFFFFF) | rng.getrandbits(32) << 32 for _ in range(10)]
    signed = sorted({f - (1 << 64) if f >> 63 else f for f in fps})
    frame = spark.createDataFrame([(f,) for f in signed] + [(None,)], "fp long")
    assert {tuple(r) for r in simhash.links(frame, radius, segments).collect()} == pairs_within(signed, radius)
    assert simhash.links(frame.limit(0), radius, segments).count() == 0


def brute_components(ids, fps):
    parent = list(range(len(ids)))

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(ids)):
        for j in range(i):
            if bin(fps[i] ^ fps[j]).count("1") <= 2:
                parent[root(i)] = root(j)
    least = {}
    for i, d in enumerate(ids):
        if d is not None:
            least[root(i)] = min(d, least.get(root(i), d))
    return [least.get(root(i)) for i in range(len(ids))]


def test_components_equal_all_pairs_on_chains_clusters_and_strangers(spark):
    rng = random.Random(7)
    fps, x = [], rng.getrandbits(64)
    for _ in range(60):  # a chain: neighbours differ in two bits, far ones in many
        fps.append(x)
        x ^= (1 << rng.randrange(64)) ^ (1 << rng.randrange(64))
    centre = rng.getrandbits(64)
    fps += [centre ^ (1 << rng.randrange(64)) for _ in range(80)] + [centre] * 40
    fps += [rng.getrandbits(64) for _ in range(60)] + [0, 0, 1, 3, 7]
    ids = list(range(1000, 1000 + len(fps)))
    rng.shuffle(ids)
    signed = [f - (1 << 64) if f >> 63 else f for f in fps]
    nodes = spark.createDataFrame(list(zip(ids, signed)), "rid long, fp long").selectExpr("rid", "fp").groupBy("fp").agg({"rid": "min"}).withColumnRenamed("min(rid)", "least")
    got = {r["fp"]: r["least"] for r in simhash.components(simhash.links(nodes.select("fp")), nodes).collect()}
    want = dict(zip(signed, brute_components(ids, fps)))
    alone = {r["fp"]: r["least"] for r in nodes.collect()}
    assert {f: got.get(f, alone[f]) for f in want} == want


def test_odd_rows(spark):
    rows = [(1, "a b c d"), (2, "A B c d"), (3, None), (4, ""), (None, "a b c d"), (5, "x"), (5, "x"), (6, "z y x w v")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("doc_id", "text", "1 as fp", "2 as least")
    got = sorted((repr(r["rid"]), r["least"]) for r in simhash.near_duplicates(docs).collect())
    assert got == [("1", 1), ("2", 1), ("3", 3), ("4", 3), ("5", 5), ("5", 5), ("6", 6), ("None", 1)]
    kept = simhash.drop_near_copies(docs)
    assert kept.columns == docs.columns
    assert sorted(r["doc_id"] for r in kept.collect()) == [1, 3, 5, 6]
    assert simhash.near_duplicates(docs.limit(0)).count() == 0


def test_given_table_against_all_pairs(spark):
    sf = "/root/testdata/sf0.001"
    rows = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()
    fps = [brute_fingerprint(r["text"]) for r in rows]
    want = {(r["doc_id"], f"{f:016x}", c) for r, f, c in zip(rows, fps, brute_components([r["doc_id"] for r in rows], fps))}
    assert {tuple(r) for r in simhash.op9_simhash(spark, sf).collect()} == want


def jaccard(a, b, words=5):
    def shingles(t):
        w = t.lower().split()
        return {tuple(w[i : i + words]) for i in range(max(1, len(w) - words + 1))}

    x, y = shingles(a), shingles(b)
    return len(x & y) / len(x | y)


def test_stage_finds_similar_texts_and_spares_others(spark):
    rng = random.Random(12)
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(rng.randint(2, 7)))
    texts, sources = [], []
    for g in range(60):
        base = [word() for _ in range(rng.randint(60, 400))]
        for c in range(rng.randint(1, 4)):
            copy = list(base)
            for _ in range(0 if c == 0 else max(1, int(rng.uniform(0.002, 0.03) * len(copy)))):
                copy[rng.randrange(len(copy))] = word()
            texts.append(" ".join(copy))
            sources.append(g)
    hub = [word() for _ in range(120)]
    for _ in range(150):  # a large group
        copy = list(hub)
        copy[rng.randrange(120)] = word()
        texts.append(" ".join(copy))
        sources.append(-1)
    ids = list(range(100, 100 + len(texts)))
    rng.shuffle(ids)
    docs = spark.createDataFrame(list(zip(ids, texts)), "doc_id long, text string").repartition(7)
    kept = {r["doc_id"] for r in simhash.drop_near_copies(docs).collect()}
    for g in set(sources):
        group = [(i, t) for i, t, s in zip(ids, texts, sources) if s == g]
        stay = [x for x in group if x[0] in kept]
        assert stay and min(group)[0] in kept
        for a in range(len(stay)):
            for b in range(a):
                assert jaccard(stay[a][1], stay[b][1]) < 0.8


def test_sketches_of_equal_sets_agree():
    h = simhash.shingle_hashes("a b c d e f g h i j k l m n o p", 5)
    twice = simhash.sketches(np.concatenate([h, h, h[:1]]), np.repeat([0, 1, 1], [12, 12, 1]))
    assert len(h) == 12 and twice[0].tolist() == [0] * (len(twice[0]) // 2) + [1] * (len(twice[0]) // 2)
    assert twice[1][: len(twice[0]) // 2].tolist() == twice[1][len(twice[0]) // 2 :].tolist() and len(simhash.sketches(h[:0], np.zeros(0, np.int64))[1]) == 0
    assert len(simhash.shingle_hashes("only three words", 5)) == 1 and len(simhash.shingle_hashes(None, 5)) == 0


def similar_components(texts, ids):
    """Least ids of the components of all pairs within 2 bits, or with a similarity of 0.8 or more."""
    fps = [simhash.fingerprint(t) % (1 << 64) for t in texts]
    sets = [set(simhash.shingle_hashes(t, 5).tolist()) for t in texts]
    parent = list(range(len(texts)))

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(texts)):
        for j in range(i):
            common = len(sets[i] & sets[j])
            if bin(fps[i] ^ fps[j]).count("1") <= 2 or common >= 0.8 * (len(sets[i]) + len(sets[j]) - common):
                parent[root(i)] = root(j)
    least = {}
    for i, d in enumerate(ids):
        least[root(i)] = min(d, least.get(root(i), d))
    return sorted(least.values())


def template_texts(rng):
    """Forms that share most of a passage, pairs of near copies among them, and a group that drifts."""
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(rng.randint(3, 8)))
    passage, texts = [word() for _ in range(340)], []
    for pair in range(90):
        own = [word() for _ in range(60)]
        texts.append(passage + own)
        if pair < 45:  # similarity 0.82, but 0.74 to the other forms
            texts.append(passage + own[:20] + [word() for _ in range(40)])
    drift = [word() for _ in range(150)]
    for _ in range(60):
        texts.append(drift[:])
        for _ in range(2):
            drift[rng.randrange(150)] = word()
    return [" ".join(t) for t in texts]


@pytest.mark.parametrize("cell", [1 << 16, 2000])
def test_near_copies_in_a_passage_that_many_share(spark, monkeypatch, cell):
    monkeypatch.setattr(simhash, "CELL_SHINGLES", cell)
    rng = random.Random(31)
    texts = template_texts(rng)
    rng.shuffle(texts)
    ids = list(range(500, 500 + len(texts)))
    docs = spark.createDataFrame(list(zip(ids, texts)), "doc_id long, text string").repartition(5)
    want = similar_components(texts, ids)
    assert len(want) < 110
    assert sorted(r["doc_id"] for r in simhash.drop_near_copies(docs).collect()) == want


def test_cells_link_what_all_pairs_link():
    rng = random.Random(8)
    for _ in range(20):
        sets = []
        for _ in range(rng.randint(1, 12)):
            base = [rng.randrange(-(1 << 63), 1 << 63) for _ in range(rng.randint(1, 60))] + list(range(30)) * rng.randint(0, 1)
            for _ in range(3):
                sets.append(sorted({x for x in base if rng.random() > 0.1} | {rng.randrange(1 << 60)}))
        label = np.array([rng.choice([i, i, 0, 1]) for i in range(len(sets))])
        uid = np.arange(len(sets)) + 1000
        want = [(i, j) for j in range(len(sets)) for i in range(j) if len({*sets[i]} & {*sets[j]}) >= 0.8 * len({*sets[i]} | {*sets[j]})]
        got = simhash.cell_links(uid, label, np.cumsum([0, *map(len, sets)]), np.concatenate([np.array(x, np.int64) for x in sets]), 0.8)
        assert {(min(a, b) - 1000, max(a, b) - 1000) for a, b in got} <= set(want)

        def classes(links):
            group = {i: int(x) for i, x in enumerate(label)}
            for i, j in links:
                a, b = group[i], group[j]
                group = {k: a if g == b else g for k, g in group.items()}
            return {frozenset(k for k in group if group[k] == g) for g in group.values()}

        assert classes([(a - 1000, b - 1000) for a, b in got]) == classes(want) and len(got) < len(set(label.tolist()))


def test_large_group_keeps_one_row_of_each_component(spark):
    rng = random.Random(12)
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(rng.randint(2, 7)))
    hub, texts = [word() for _ in range(120)], []
    for _ in range(150):
        copy = list(hub)
        copy[rng.randrange(120)] = word()
        texts.append(" ".join(copy))
    ids = list(range(100, 250))
    rng.shuffle(ids)
    docs = spark.createDataFrame(list(zip(ids, texts)), "doc_id long, text string").repartition(7)
    assert sorted(r["doc_id"] for r in simhash.drop_near_copies(docs).collect()) == similar_components(texts, ids)
