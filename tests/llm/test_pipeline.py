import corpus_pipeline

from seqcount.llm import bpe, exact_dedup, mixing, quality_knn, simhash

SF = "/root/testdata/sf0.001"


def brute_near(rows):
    """Least ids of the components of all pairs within 2 bits, or with a similarity of 0.8 or more of five-word shingles."""
    fps = [simhash.fingerprint(t) % (1 << 64) for _, t in rows]
    sets = [set(simhash.shingle_hashes(t, 5).tolist()) for _, t in rows]
    parent = list(range(len(rows)))

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            common = len(sets[i] & sets[j])
            if bin(fps[i] ^ fps[j]).count("1") <= 2 or (common and common >= 0.8 * (len(sets[i]) + len(sets[j]) - common)):
                parent[root(i)] = root(j)
    least = {}
    for i, (d, _) in enumerate(rows):
        least[root(i)] = min(d, least.get(root(i), d))
    return sorted(least.values())


def test_stages_hand_on_whole_rows(spark, tmp_path):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    first = docs
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["quality", "exact_dedup", "near_dedup", "mixing", "bpe"]
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, SF)
        out.write.parquet(f"{tmp_path}/{name}")
        got = spark.read.parquet(f"{tmp_path}/{name}")
        if name == "quality":
            model = quality_knn.train(docs, spark.read.parquet(f"{SF}/labels.parquet"))
            want = {r["doc_id"] for r in quality_knn.with_scores(docs, model).collect() if r["score"] >= corpus_pipeline.REJECT_BELOW}
            assert {r["doc_id"] for r in got.collect()} == want and 0 < len(want) < docs.count()
        elif name == "exact_dedup":
            best = {}
            for r in docs.collect():
                best[r["text"]] = max(r["doc_id"], best.get(r["text"], -1))
            assert sorted(r["doc_id"] for r in got.collect()) == sorted(best.values())
        elif name == "near_dedup":
            assert sorted(r["doc_id"] for r in got.collect()) == brute_near([(r["doc_id"], r["text"]) for r in docs.collect()])
        elif name == "mixing":
            want = sorted(r["rid"] for r in mixing.mix_sizes(docs).collect() for _ in range(r["m_copies"]))
            assert sorted(r["doc_id"] for r in got.collect()) == want
        else:
            plain = bpe.coder().encoding
            counts = sorted((r["doc_id"], len(plain.encode_ordinary(r["text"]))) for r in docs.collect())
            assert sorted((r["doc_id"], r["n_tokens"]) for r in got.collect()) == counts
        if name != "bpe":
            assert got.columns == first.columns
        docs = got
    assert sorted(map(tuple, corpus_pipeline.run(spark, SF).collect())) == sorted(map(tuple, docs.collect()))
    assert exact_dedup


def test_odd_tables(spark, tmp_path):
    rows = [(1, None, "en", None, 0), (1, None, "en", None, 0), (2, "", None, "s", None), (None, "a b c", "en", "s", 5), (3, "w " * 50_000, "en", "s", 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    docs = docs.selectExpr("*", "1 as score", "2 as n_tokens", "3 as __score", "4 as fp")
    for frame in (docs, docs.limit(0)):
        some = bool(frame.count())
        got = {name: stage(spark, frame, SF) for name, stage in corpus_pipeline.STAGES}
        for name, out in got.items():
            assert out.columns == (["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"] if name == "bpe" else docs.columns)
        kept = {name: sorted(map(repr, (r["doc_id"] for r in out.collect()))) for name, out in got.items()}
        assert set(kept["quality"]) <= {"1", "2", "None", "3"} if some else not kept["quality"]
        # the texts are empty (1 twice, 2), three words, and one word repeated
        assert kept["exact_dedup"] == kept["exact_dedup"] and len(kept["exact_dedup"]) == (3 if some else 0)
        assert kept["exact_dedup"] == (["2", "3", "None"] if some else []) and kept["near_dedup"] == (["1", "3", "None"] if some else [])
        assert all(kept["mixing"].count(i) <= 2 * len([1 for r in rows if repr(r[0]) == i]) for i in kept["mixing"])
        assert kept["bpe"] == (sorted(repr(r[0]) for r in rows) if some else [])
