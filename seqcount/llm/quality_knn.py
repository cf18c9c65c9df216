"""Quality by nearest-neighbour voting among labelled latent-semantic vectors."""

from __future__ import annotations

import io

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StructField, StructType

from seqcount.llm.textkernel import Words, groups_of_words, mix, whole_counts

#: Labelled rows of each label that the model is fitted on, at most, taken by a hash of the id; and bytes of a text
#: above which it isn't taken. Every text is scored whole, however long.
SAMPLE_PER_LABEL, SAMPLE_TEXT_BYTES = 1200, 1 << 15
N_TERMS, RANK, NEIGHBOURS, SHARPNESS, THRESHOLD = 8192, 48, 15, 8, 0.7
SEED = 42
_STYLE = np.uint64(0xA11CE)
_RUN_TERMS = 16  # the first terms count words that repeat the word before, by their place in the run


def _terms(g: Words) -> tuple[np.ndarray, np.ndarray]:
    """(text, term) of hashed words, word styles and word repeats."""
    again = np.zeros(len(g.doc), bool)
    again[1:] = (g.word[1:] == g.word[:-1]) & (g.doc[1:] == g.doc[:-1])
    since = np.arange(len(again))
    place = since - np.maximum.accumulate(np.where(again, 0, since)) if len(again) else since
    again[: g.lead] = False
    runs = np.minimum(place[again], _RUN_TERMS).astype(np.uint64) - np.uint64(1)
    word = g.word[g.lead :] % np.uint64(N_TERMS // 2 - _RUN_TERMS) + np.uint64(_RUN_TERMS)
    style = mix(g.style[g.lead :] + _STYLE) % np.uint64(N_TERMS // 2) + np.uint64(N_TERMS // 2)
    doc = g.doc[g.lead :]
    return np.concatenate([doc, doc, g.doc[again]]), np.concatenate([word, style, runs])


def term_counts(texts: pa.Array):
    """(first text, texts, text, term, count, words) of groups of texts."""
    return whole_counts(groups_of_words(texts, style=True), _terms, N_TERMS)


def _weighted(doc, term, n, idf):
    return (1.0 + np.log(n)) * idf[term]


def _unit(v: np.ndarray) -> np.ndarray:
    norm = np.linalg.norm(v, axis=1, keepdims=True)
    return (v / np.where(norm > 0, norm, 1)).astype(np.float32)


def fit(texts: pa.Array, labels: np.ndarray) -> dict[str, np.ndarray]:
    """Idf weights, the projection to RANK latent dimensions, and the labelled unit vectors."""
    parts = list(term_counts(texts))
    doc = np.concatenate([p[0] + p[2] for p in parts] or [np.zeros(0, np.int64)])
    term = np.concatenate([p[3] for p in parts] or [np.zeros(0, np.int64)])
    n = np.concatenate([p[4] for p in parts] or [np.zeros(0, np.int64)])
    idf = np.log((1.0 + len(labels)) / (1.0 + np.bincount(term, minlength=N_TERMS))) + 0.1
    a = np.zeros((len(labels), N_TERMS), np.float32)
    a[doc, term] = _weighted(doc, term, n, idf)
    norm = np.linalg.norm(a, axis=1, keepdims=True)
    a /= np.where(norm > 0, norm, 1).astype(np.float32)  # in place: the matrix is the driver's largest
    rank = min(RANK, *a.shape) if len(labels) else 0
    rng = np.random.default_rng(SEED)
    y = a @ rng.standard_normal((N_TERMS, min(rank + 16, max(1, len(labels))))).astype(np.float32) if rank else np.zeros((0, 0), np.float32)
    for _ in range(3 if rank else 0):  # subspace iteration: the leading right singular vectors
        q, _ = np.linalg.qr(y)
        q, _ = np.linalg.qr(a.T @ q)
        y = a @ q
    if not rank:
        return {"idf": idf, "basis": np.zeros((N_TERMS, 1), np.float32), "vectors": np.zeros((0, 1), np.float32), "labels": np.zeros(0, np.float32), "prior": np.float32(0.5)}
    q, _ = np.linalg.qr(y)
    _, _, vt = np.linalg.svd(q.T @ a, full_matrices=False)
    basis = np.ascontiguousarray(vt[:rank].T, np.float32)
    return {"idf": idf, "basis": basis, "vectors": _unit(a @ basis), "labels": labels.astype(np.float32), "prior": np.float32(labels.mean())}


def scores(model: dict[str, np.ndarray], texts: pa.Array) -> np.ndarray:
    """Similarity-weighted share of label 1 among the nearest labelled vectors, by exact cosines in blocks.

    A text without words is the zero vector: it has no neighbours and gets the prior.
    """
    out = np.full(len(texts), float(model["prior"]))
    known, k = model["vectors"], min(NEIGHBOURS, len(model["vectors"]))
    if not k:
        return out
    for first, _, doc, term, n, _ in term_counts(texts):
        if not len(doc):
            continue
        w = _weighted(doc, term, n, model["idf"]).astype(np.float32)
        heads = np.flatnonzero(np.r_[True, doc[1:] != doc[:-1]])
        latent = np.add.reduceat(model["basis"][term] * w[:, None], heads, axis=0)
        full = doc[heads]
        cosine = _unit(latent) @ known.T
        near = np.argpartition(cosine, len(known) - k, axis=1)[:, -k:]
        weight = np.maximum(np.take_along_axis(cosine, near, 1), 0.0) ** SHARPNESS
        total = weight.sum(1)
        voted = (weight * model["labels"][near]).sum(1) / np.where(total > 0, total, 1)
        out[first + full] = np.where(total > 0, np.clip(voted, 0, 1), out[first + full])
    return out


def held_out(id_col: str = "doc_id"):
    """Whether a row is kept from the fit; a row without an id isn't."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % 4 == 2, F.lit(False))


def labelled_sample(docs: DataFrame, labels: DataFrame, label_col: str, per_label: int, usable, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(s_turn, s_id, s_label, text) of at most ``per_label`` labelled ids of either label, those of least id hash.

    An id whose labels disagree, or a null id or label, isn't taken. An id has one row: of several texts
    the least. Texts over SAMPLE_TEXT_BYTES are left out, so rows and bytes are bounded.
    """
    flags = labels.select(F.col(id_col).alias("s_id"), F.col(label_col).cast("int").alias("s_label")).where(F.col("s_label").isin(0, 1) & F.col("s_id").isNotNull())
    flags = flags.groupBy("s_id").agg(F.min("s_label").alias("s_label"), F.max("s_label").alias("s_most")).where("s_label = s_most").drop("s_most")
    flags = flags.where(usable("s_id")).withColumn("s_turn", F.xxhash64("s_id", F.lit(SEED)))
    chosen = [flags.where(F.col("s_label") == y).orderBy("s_turn", "s_id").limit(per_label) for y in (0, 1)]
    few = F.broadcast(chosen[0].unionByName(chosen[1]))
    texts = docs.select(F.col(id_col).alias("d_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text")).where(F.octet_length("text") <= SAMPLE_TEXT_BYTES)
    return texts.join(few, F.col("d_id") == F.col("s_id")).groupBy("s_turn", "s_id", "s_label").agg(F.min("text").alias("text"))


def fitted(sample: DataFrame, fit) -> dict[str, np.ndarray]:
    """``fit`` (texts, labels) of a bounded sample, in one task, so that the driver has the model alone in memory."""

    def run(batches):
        rows = pa.Table.from_batches(batches).sort_by([("s_turn", "ascending"), ("s_id", "ascending")])
        with io.BytesIO() as out:
            np.savez(out, **fit(rows["text"].combine_chunks(), rows["s_label"].to_numpy()))
            yield pa.RecordBatch.from_arrays([pa.array([out.getvalue()], pa.binary())], names=["model"])

    got = sample.repartition(1).mapInArrow(run, "model binary").first()
    if got is None:
        return fit(pa.array([], pa.string()), np.zeros(0))
    with np.load(io.BytesIO(got["model"])) as model:
        return dict(model)


def train(docs: DataFrame, labels: DataFrame, per_label: int = SAMPLE_PER_LABEL, usable=lambda c: ~held_out(c), id_col: str = "doc_id", text_col: str = "text") -> dict:
    """The model of a bounded sample; without usable labels, one that gives every text 0.5."""
    return fitted(labelled_sample(docs, labels, "quality", per_label, usable, id_col, text_col), fit)


def with_scores(docs: DataFrame, model: dict, text_col: str = "text", name: str = "score") -> DataFrame:
    """``docs`` with a score column; the model, of a bounded size, is broadcast and texts don't move.

    Null and empty texts have no words and get the prior; equal texts get equal scores;
    repeated rows stay; an empty table gives no rows.
    """
    schema = StructType([*docs.schema.fields, StructField(name, DoubleType())])
    shared = docs.sparkSession.sparkContext.broadcast(model)
    at = docs.columns.index(text_col)

    def run(batches):
        for batch in batches:
            score = scores(shared.value, batch.column(at))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(score)], names=[*batch.schema.names, name])

    return docs.mapInArrow(run, schema)


def op2_quality(spark, sf_dir: str) -> DataFrame:
    """Score, held_out and predicted of every document, null, empty and repeated ones too; see ``with_scores``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    model = train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    scored = with_scores(docs, model)
    return scored.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
