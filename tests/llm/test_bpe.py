import hashlib
import random

import numpy as np
import public_tokenizers
import pytest

from seqcount.llm import bpe, token_counts

PIECES = ["a", "the ", "éç", " ", "\n", "  ", "1", "42", "!", "日本語", "　", "'s", "'re", "ab", " x", "\t", "ing", "🙂", "A", "\x00", "\x1c", "\x85", "'", "''", "²", "ª", "\u0301", "\u200b", "--"]


@pytest.fixture(scope="module")
def small():
    return bpe.Coder(public_tokenizers.path(bpe.VOCABULARY), leaf_chars=64, leaf_bytes=16)


@pytest.mark.parametrize("leaf", [1, 2, 7, 64])
def test_tree_equals_the_library_on_random_texts(leaf):
    coder = bpe.Coder(public_tokenizers.path(bpe.VOCABULARY), leaf_chars=leaf, leaf_bytes=16)
    rng = random.Random(9)
    for i in range(700):
        text = "".join(rng.choice(PIECES if i % 3 else ["a", "b", " ", "'", "s", "1", "\x1c", "!", "é"]) for _ in range(rng.randint(0, 150)))
        ids = coder.encode(text)
        assert ids == coder.encoding.encode_ordinary(text), repr(text)
        assert coder.decode(ids) == text.encode()


def test_every_text_above_a_leaf_is_joined():
    coder = bpe.Coder(public_tokenizers.path(bpe.VOCABULARY))
    for n in (0, 1, 95, 96, 97, 192, 193, 5000, 40_000):
        text, before = ("some words, and more " * (n // 20 + 1))[:n], coder.joins
        assert coder.encode(text) == coder.encoding.encode_ordinary(text)
        leaves, spans = 0, [n]
        while spans:
            x = spans.pop()
            if x <= bpe.LEAF_CHARS:
                leaves += 1
            else:
                spans += [x // 2, x - x // 2]
        assert coder.joins - before == leaves - 1


@pytest.mark.parametrize("text", ["", "a" * 5000, " " * 5000, "ab" * 3000, "\n" * 700 + "x", "日本" * 2000, "=-" * 3000, "x" + " " * 3000 + "y", ("word " * 30 + "b" * 900) * 5])
def test_long_runs(small, text):
    assert list(small.encode(text)) == small.encoding.encode_ordinary(text)


def test_production_leaves_on_a_long_text():
    text = " ".join(f"word{i} é" for i in range(60_000)) + "z" * 50_000
    coder = bpe.coder()
    assert list(coder.encode(text)) == coder.encoding.encode_ordinary(text)


def test_rows(spark):
    docs = spark.createDataFrame([(1, None), (2, ""), (3, "Hello, wörld"), (3, "Hello, wörld"), (None, "x")], "doc_id long, text string").selectExpr("doc_id", "text", "1 as n_tokens", "2 as IDS")
    plain = bpe.coder().encoding
    want = []
    for d, t in [(1, ""), (2, ""), (3, "Hello, wörld"), (3, "Hello, wörld"), (None, "x")]:
        ids = plain.encode_ordinary(t)
        want.append((d, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(t.encode()).hexdigest()))
    assert sorted(map(tuple, bpe.token_digests(docs).collect()), key=repr) == sorted(want, key=repr)
    encoded = bpe.encoded_frame(docs)
    assert encoded.columns == [*docs.columns, "__n_tokens", "__ids"]
    ids = {r["doc_id"]: r["__ids"] for r in encoded.collect()}
    assert ids[3] == plain.encode_ordinary("Hello, wörld") and ids[1] == []
    assert bpe.encoded_frame(docs.select("text")).columns == ["text", "n_tokens", "ids"] and bpe.encoded_frame(docs.limit(0)).count() == 0
    assert bpe.token_digests(docs.limit(0)).count() == 0


def test_histogram_answers_every_limit(spark):
    rng = random.Random(4)
    texts = [None, ""] + ["tok " * rng.choice([0, 1, 1, 5, 1100, 2500, rng.randint(0, 3000)]) for _ in range(120)]
    docs = spark.createDataFrame([(t,) for t in texts], "text string")
    lengths = sorted(len(bpe.coder().encode(t or "")) for t in texts)
    sums = token_counts.suffix_sums(token_counts.length_histogram(docs))
    for r in sums.collect():
        x = r["n_tokens"]
        assert r["docs"] == lengths.count(x) and r["docs_from"] == sum(n >= x for n in lengths) and r["docs_below"] == sum(n < x for n in lengths)
        assert r["tokens_from"] == sum(n for n in lengths if n >= x) and r["truncated_tokens"] == sum(min(n, x) for n in lengths)
    limits = [0, 1, 2, 7, 1024, 2048, 10**6]
    got = {r["limit_tokens"]: (r["docs_over"], r["tokens_kept"]) for r in token_counts.limit_answers(sums, limits).collect()}
    assert got == {x: (sum(n > x for n in lengths), sum(min(n, x) for n in lengths)) for x in limits}
    shares = {r["share"]: r["n_tokens"] for r in token_counts.length_at(sums, [0.1, 0.5, 0.99, 1.0]).collect()}
    assert shares == {q: next(x for x in lengths if sum(n <= x for n in lengths) >= q * len(lengths)) for q in (0.1, 0.5, 0.99, 1.0)}
    none = token_counts.suffix_sums(token_counts.length_histogram(docs.limit(0)))
    assert none.count() == 0 and [tuple(r) for r in token_counts.limit_answers(none, [5]).collect()] == [(5, 0, 0)]
