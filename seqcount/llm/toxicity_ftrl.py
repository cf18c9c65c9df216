"""Toxicity by FTRL-proximal logistic regression over hashed word n-grams and skip-grams."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StructField, StructType

from seqcount.llm.quality_knn import fitted, labelled_sample
from seqcount.llm.textkernel import Words, groups_of_words, mix, whole_counts

#: Labelled rows of each label that the model is fitted on, at most; taken by a hash of the id.
SAMPLE_PER_LABEL = 4000
BITS, EPOCHS, THRESHOLD = 20, 6, 0.7
ALPHA, BETA, L1, L2 = 1.0, 1.0, 3.0, 0.1
_PAIR, _SKIP = np.uint64(0x9FB21C651E98DF25), np.uint64(0xD6E8FEB86659FD93)
_MASK = np.uint64((1 << BITS) - 1)
#: Inflected and compound words also count by their first bytes.
STEMS = (5, 6, 7)
#: A feature's value is log(1 + its occurrences for each so many words).
PER_WORDS = 100


def _features_of(g: Words) -> tuple[np.ndarray, np.ndarray]:
    """(text, feature) of words, stems, pairs of neighbours and pairs with one word between."""
    w, doc, lead = g.word, g.doc, g.lead
    one, two = doc[1:] == doc[:-1], doc[2:] == doc[:-2]
    one[: max(0, lead - 1)] = False
    two[: max(0, lead - 2)] = False
    pair = mix(w[:-1] * _PAIR + w[1:])[one]
    skip = mix(w[:-2] * _SKIP + (w[2:] ^ _PAIR))[two]
    stems = [(at[at >= lead], h[at >= lead]) for at, h in g.stems]
    where = np.concatenate([doc[lead:], doc[:-1][one], doc[:-2][two], *(doc[at] for at, _ in stems)])
    return where, np.concatenate([w[lead:], pair, skip, *(h for _, h in stems)]) & _MASK


def features(texts: pa.Array):
    """(first text, texts, text, feature, value) of groups of texts."""
    for first, n_docs, at, feature, n, words in whole_counts(groups_of_words(texts, stems=STEMS), _features_of, 1 << BITS):
        yield first, n_docs, at, feature, np.log1p(n * (PER_WORDS / words[at]))


def rows_of_features(texts: pa.Array) -> list[tuple[np.ndarray, np.ndarray]]:
    """(features, values) of each text."""
    out = []
    for _, n_docs, doc, feature, value in features(texts):
        cuts = np.searchsorted(doc, np.arange(1, n_docs))
        out += zip(np.split(feature.astype(np.int32), cuts), np.split(value.astype(np.float32), cuts), strict=True) if n_docs else []
    return out


def fit(rows: list[tuple[np.ndarray, np.ndarray]], labels: np.ndarray) -> dict[str, np.ndarray]:
    """Sparse weights from a few passes: each coordinate has its own rate, and L1 keeps most at zero."""
    z, n = np.zeros(1 << BITS), np.zeros(1 << BITS)
    bias = bias_z = bias_n = 0.0
    order = np.random.default_rng(42)

    def weight(z, n):
        return np.where(np.abs(z) <= L1, 0.0, -(z - np.sign(z) * L1) / ((BETA + np.sqrt(n)) / ALPHA + L2))

    for _ in range(EPOCHS):
        for i in order.permutation(len(rows)):
            x, value = rows[i]
            zx, nx = z[x], n[x]
            w = weight(zx, nx)
            bias = -bias_z / ((BETA + np.sqrt(bias_n)) / ALPHA)
            miss = 1.0 / (1.0 + np.exp(-np.clip(w @ value + bias, -35, 35))) - labels[i]
            g = miss * value
            more = nx + g * g
            z[x] = zx + g - (np.sqrt(more) - np.sqrt(nx)) / ALPHA * w
            n[x] = more
            bias_z += miss - (np.sqrt(bias_n + miss * miss) - np.sqrt(bias_n)) / ALPHA * bias
            bias_n += miss * miss
    w = weight(z, n)
    at = np.flatnonzero(w)
    return {"at": at.astype(np.int32), "weight": w[at], "bias": np.float64(bias)}


def scores(model: dict[str, np.ndarray], texts: pa.Array) -> np.ndarray:
    """Probability of label 1; a text without words has the bias alone."""
    dense = np.zeros(1 << BITS)
    dense[model["at"]] = model["weight"]
    out = np.full(len(texts), float(model["bias"]))
    for first, n_docs, doc, feature, value in features(texts):
        out[first : first + n_docs] += np.bincount(doc, dense[feature] * value, minlength=n_docs)
    return 1.0 / (1.0 + np.exp(-np.clip(out, -35, 35)))


def held_out(id_col: str = "doc_id"):
    """Whether a row is kept from the fit; a row without an id isn't."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % 3 == 1, F.lit(False))


def train(docs: DataFrame, labels: DataFrame, per_label: int = SAMPLE_PER_LABEL, usable=lambda c: ~held_out(c), id_col: str = "doc_id", text_col: str = "text") -> dict:
    """The model of a bounded sample; without usable labels, one that gives every text 0.5."""
    return fitted(labelled_sample(docs, labels, "toxic", per_label, usable, id_col, text_col), lambda texts, y: fit(rows_of_features(texts), y))


def with_scores(docs: DataFrame, model: dict, text_col: str = "text", name: str = "score") -> DataFrame:
    """``docs`` with a score column; the sparse weights are broadcast and texts don't move.

    Null and empty texts have no words and get the bias alone; equal texts get equal
    scores; repeated rows stay; an empty table gives no rows.
    """
    schema = StructType([*docs.schema.fields, StructField(name, DoubleType())])
    shared = docs.sparkSession.sparkContext.broadcast(model)
    at = docs.columns.index(text_col)

    def run(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(scores(shared.value, batch.column(at)))], names=[*batch.schema.names, name])

    return docs.mapInArrow(run, schema)


def op5_toxicity(spark, sf_dir: str) -> DataFrame:
    """Score, held_out and predicted of every document, null, empty and repeated ones too; see ``with_scores``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    model = train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    scored = with_scores(docs, model)
    return scored.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
