"""Exact top-k inner products by no-random-access aggregation of sorted lists."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqcount.llm.common import checkpointed

SCALE, TOP = 64, 20
#: Candidates of a lane, and queries of a chunk: a grid cell. Queries that read a lane's lists together.
LANE_ROWS, CHUNK_ROWS, QUERY_ROWS = 1 << 14, 1 << 12, 1 << 7
#: How far every list has been read, as a share of its length, when bounds are compared anew; the last is the end.
DEPTHS = (1 / 32, 1 / 16, 1 / 8, 1 / 4, 3 / 8, 1 / 2, 5 / 8, 3 / 4, 7 / 8, 1)
#: Pairs of query and outsider that are left, as a share of all, at which reading stops and the final scores are resolved.
FEW = 1 / 64
#: Scores beyond a BIGINT are ranked by their whole digits and shown as its least or largest value.
_WIDE_BYTES, _WIDE_OFFSET, _WIDE = 264, 1 << 2100, 1 << 62


class Lists:
    """A lane's candidates as one list for each component, in falling order, read from either end.

    A query reads a component's list from the top if its own component is positive and
    from the bottom if negative: that is the order of falling contribution.
    """

    def __init__(self, values: np.ndarray, order: np.ndarray):
        self.values, self.order = values, order  # (rows, components), (components, rows)
        n, dim = values.shape
        self.rank = np.empty((n, dim), np.int32)
        np.put_along_axis(self.rank, order.T.astype(np.int64), np.arange(n, dtype=np.int32)[:, None], axis=0)
        each = np.arange(dim)
        self.high, self.low = values[order[:, 0], each], values[order[:, -1], each]

    @staticmethod
    def sort(values: np.ndarray) -> np.ndarray:
        """The order of every list: places of the rows, by falling value."""
        return np.ascontiguousarray(np.argsort(-values, axis=0, kind="stable").T.astype(np.uint16 if len(values) <= 1 << 16 else np.uint32))


def _least_of_best(scores: np.ndarray, k: int):
    """The k-th best of each column."""
    at = len(scores) - k
    return (np.sort(scores, axis=0) if scores.dtype == object else np.partition(scores, at, axis=0))[at]


def aggregate(queries: np.ndarray, own: np.ndarray, lists: Lists, k: int, beyond) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """(query, candidate, score) with the k best of each query among them, and how deep the lists were read.

    own: the place of a query's own row, or -1. ``beyond`` exceeds every score. Each round reads all
    lists on, entry after entry, and adds each to what is known of its candidate: a lower
    bound, in which parts not read yet count as the far end of their list; the upper bound
    counts them as the value last read. A query's outsider is out once its upper bound is
    below the k-th best lower bound, and a candidate that is out for all queries is not
    kept any longer. If few pairs are left, their scores are resolved; at the end of the
    lists the bounds are the scores. Ties with the k-th stay in.
    """
    n, dim = lists.values.shape
    plus, minus = np.maximum(queries, 0), np.minimum(queries, 0)
    base = plus @ lists.low + minus @ lists.high
    alive, place = np.arange(n), np.arange(n)
    known = np.zeros((n, len(queries)), queries.dtype)
    rank, mine = lists.rank, np.flatnonzero(own >= 0)
    depth = 0
    for share in DEPTHS:
        begin, depth = depth, max(1, math.ceil(n * share))
        for j in range(dim):
            for part, side, far in ((lists.order[j, begin:depth], plus, lists.low), (lists.order[j, n - depth : n - begin], minus, lists.high)):
                rows = place[part]
                kept = rows >= 0
                known[rows[kept]] += np.multiply.outer(lists.values[part[kept], j] - far[j], side[:, j])
        last_top, last_bottom = lists.values[lists.order[:, depth - 1], np.arange(dim)], lists.values[lists.order[:, n - depth], np.arange(dim)]
        lower = known + base
        upper = lower
        if depth < n:
            open_top = np.where(rank >= depth, last_top - lists.low, 0).astype(queries.dtype)
            open_bottom = np.where(rank < n - depth, last_bottom - lists.high, 0).astype(queries.dtype)
            upper = lower + open_top @ plus.T + open_bottom @ minus.T
        held = mine[place[own[mine]] >= 0]
        lower[place[own[held]], held] = -beyond
        upper[place[own[held]], held] = -beyond
        left = upper > -beyond
        if len(alive) > k:
            left &= upper >= _least_of_best(lower, k)
        if depth == n or left.sum() <= FEW * n * len(queries):
            row, query = np.nonzero(left)
            if depth == n:
                return query, alive[row], lower[row, query], depth
            return query, alive[row], (queries[query] * lists.values[alive[row]]).sum(axis=1), depth
        keep = left.any(axis=1)
        if keep.mean() < 0.8:
            alive, known, rank = alive[keep], known[keep], rank[keep]
            place = np.full(n, -1)
            place[alive] = np.arange(len(alive))
    raise AssertionError("the last depth is the end of the lists")


def _integers(v: np.ndarray) -> np.ndarray:
    """Whole doubles as integers of any size."""
    out = np.empty(v.size, object)
    out[:] = [int(x) for x in v.ravel().tolist()]
    return out.reshape(v.shape)


def cell_top(q_vec: np.ndarray, q_uid: np.ndarray, c_vec: np.ndarray, order: np.ndarray, c_uid: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """(query row, candidate row, score) of the k best candidates of each query, and the list entries read; candidates are in order of id.

    Sums of whole numbers are exact in 32 or 64-bit floats as long as they fit their
    mantissa; beyond that integers of any size are used.
    """
    largest = int(np.abs(q_vec).max(initial=0)) * int(np.abs(c_vec).max(initial=0)) * q_vec.shape[1]
    kind = np.float32 if 8 * largest < 1 << 24 else np.float64 if 8 * largest < 1 << 53 else object
    q_vec, c_vec = (_integers(q_vec), _integers(c_vec)) if kind is object else (q_vec.astype(kind), c_vec.astype(kind))
    lists, beyond = Lists(c_vec, order), 2 * largest + 1
    at = {u: i for i, u in enumerate(c_uid.tolist())}
    own = np.array([at.get(u, -1) for u in q_uid.tolist()], np.int64)
    out, reads = [], 0
    for a in range(0, len(q_vec), QUERY_ROWS):
        some = slice(a, a + QUERY_ROWS)
        query, row, score, depth = aggregate(q_vec[some], own[some], lists, k, beyond)
        reads += depth * q_vec.shape[1] * len(q_vec[some])
        best = np.lexsort((row, -score, query)) if kind is not object else np.array(sorted(range(len(query)), key=lambda i: (query[i], -score[i], row[i])), np.int64)  # noqa: B023
        query, row, score = query[best], row[best], score[best]
        first = np.searchsorted(query, np.arange(len(q_vec[some])))
        kept = np.arange(len(query)) - first[query] < k
        out.append((query[kept] + a, row[kept], score[kept] if kind is object else score[kept].astype(np.int64)))
    query, row, score = (np.concatenate([x[i] for x in out]) if out else np.zeros(0, np.int64) for i in range(3))
    return query, row, score, reads


def _matrix(column: pa.ChunkedArray, dim: int) -> np.ndarray:
    return column.combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(-1, dim)


_BLOCK = "dim int, {} int, n int, ids binary, uids binary, vectors binary, lists binary"


def _blocks(rows: DataFrame, part: str, with_lists: bool) -> DataFrame:
    """One row for each dimension and part: ids, rows and vectors in order of id, and if asked the sorted lists."""

    def build(table: pa.Table) -> pa.Table:
        table = table.sort_by([("vid", "ascending"), ("uid", "ascending")])
        dim = table["dim"][0].as_py()
        values = np.ascontiguousarray(_matrix(table["v"], dim))
        lists = Lists.sort(values).tobytes() if with_lists else b""
        whole = [dim, table[part][0].as_py(), len(table), table["vid"].to_numpy().tobytes(), table["uid"].to_numpy().tobytes(), values.tobytes(), lists]
        kinds = [pa.int32()] * 3 + [pa.binary()] * 4
        return pa.table([pa.array([x], t) for x, t in zip(whole, kinds, strict=True)], names=["dim", part, "n", "ids", "uids", "vectors", "lists"])

    return rows.groupBy("dim", part).applyInArrow(build, _BLOCK.format(part))


def _opened(block: pa.Table) -> tuple[int, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    row = block.slice(0, 1).to_pylist()[0]
    n, dim = row["n"], row["dim"]
    order = np.frombuffer(row["lists"], np.uint16 if n <= 1 << 16 else np.uint32).reshape(-1, n)
    return dim, np.frombuffer(row["ids"], np.int64), np.frombuffer(row["uids"], np.int64), np.frombuffer(row["vectors"], np.float64).reshape(n, dim), order


def top_k(vectors: DataFrame, id_col: str, vec_col: str, is_query, k: int = TOP, scale: int = SCALE) -> DataFrame:
    """(query_id, rank, vec_id, score): for each query row its k best other rows by inner product of floor(scale x).

    Ties go to the smaller id, then by row; repeated rows are rows of their own. Null vectors or ids, empty
    vectors and those with null or non-finite components, or components whose
    ``scale``-fold is, take no part, and vectors of different lengths don't
    meet; an empty table gives no rows. Scores are exact at any size: one beyond a BIGINT is ranked by its true
    value and shown as the least or largest BIGINT.

    The rows are dealt by a hash into lanes of bounded size, and each lane's lists are
    sorted once. A grid of lanes and query chunks, sized by counts, spreads the work:
    each cell reads its lists for its queries and keeps k rows a query; then the best
    over the lanes are ranked. Every query meets every lane, as any exact search
    without an index must, so lanes and chunks are as large as a worker's memory allows.
    """
    x = F.col(vec_col)
    finite = lambda y: y.isNotNull() & ~F.isnan(y) & (F.abs(y.cast("double") * F.lit(float(scale))) != float("inf"))
    sound = F.col(id_col).isNotNull() & x.isNotNull() & (F.size(x) > 0) & F.forall(x, finite)
    scaled = lambda y: F.lit(float(scale)) * y.cast("double")
    whole = F.transform(x, lambda y: F.when(F.abs(scaled(y)) < float(1 << 53), F.floor(scaled(y)).cast("double")).otherwise(scaled(y)))
    rows = checkpointed(
        vectors.where(F.coalesce(sound, F.lit(False))).select(
            F.col(id_col).cast("long").alias("vid"), F.monotonically_increasing_id().alias("uid"), whole.alias("v"), F.size(x).alias("dim"), F.coalesce(is_query(F.col(id_col)), F.lit(False)).alias("asks")
        )
    )
    n, asking = rows.agg(F.count("*"), F.count_if("asks")).first()
    lanes, chunks = max(1, math.ceil(n / LANE_ROWS)), max(1, math.ceil(asking / CHUNK_ROWS))
    spread = lambda parts, salt: F.pmod(F.xxhash64("uid", F.lit(salt)), F.lit(parts)).cast("int")
    every = lambda parts: F.explode(F.sequence(F.lit(0), F.lit(parts - 1)))
    asked = checkpointed(_blocks(rows.where("asks").select("dim", spread(chunks, 1).alias("chunk"), "vid", "uid", "v"), "chunk", False))
    offered = checkpointed(_blocks(rows.select("dim", spread(lanes, 2).alias("lane"), "vid", "uid", "v"), "lane", True))

    def cell(asked: pa.Table, offered: pa.Table) -> pa.Table:
        if not len(asked) or not len(offered):
            return pa.table([pa.array([], t) for t in (pa.int64(),) * 5 + (pa.binary(),)], names=["quid", "query_id", "vec_id", "cuid", "score", "wide"])
        _, q_id, q_uid, q_vec, _ = _opened(asked)
        _, c_id, c_uid, c_vec, order = _opened(offered)
        q, c, score, _ = cell_top(q_vec, q_uid, c_vec, order, c_uid, k)
        wide = [(int(s) + _WIDE_OFFSET).to_bytes(_WIDE_BYTES, "big") if abs(s) >= _WIDE else None for s in score] if score.dtype == object else [None] * len(score)
        shown = np.array([min(max(s, -(1 << 63)), (1 << 63) - 1) for s in score], np.int64) if score.dtype == object else score
        return pa.table([*map(pa.array, (q_uid[q], q_id[q], c_id[c], c_uid[c], shown)), pa.array(wide, pa.binary())], names=["quid", "query_id", "vec_id", "cuid", "score", "wide"])

    left = asked.withColumn("lane", every(lanes)).groupBy("dim", "lane", "chunk")
    near = left.cogroup(offered.withColumn("chunk", every(chunks)).groupBy("dim", "lane", "chunk")).applyInArrow(cell, "quid long, query_id long, vec_id long, cuid long, score long, wide binary")
    ranked = near.selectExpr("query_id", "row_number() over (partition by quid order by score desc, wide desc, vec_id, cuid) as rank", "vec_id", "score")
    return ranked.where(F.col("rank") <= k)


def op4_topk(spark, sf_dir: str) -> DataFrame:
    """The 20 best others of every row whose id is divisible by 20; see ``top_k`` for null, odd, repeated and huge vectors."""
    return top_k(spark.read.parquet(f"{sf_dir}/embeddings.parquet"), "vec_id", "embedding", lambda i: i % 20 == 0)


OP4_SQL = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(64 * CAST(x AS DOUBLE)) AS BIGINT)) AS v FROM embeddings
           WHERE embedding IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NOT NULL AND isfinite(x))) = len(embedding)),
s AS (SELECT q.vec_id AS query_id, c.vec_id, CAST(list_inner_product(CAST(q.v AS DOUBLE[]), CAST(c.v AS DOUBLE[])) AS BIGINT) AS score
      FROM v q JOIN v c ON q.vec_id % 20 = 0 AND q.vec_id <> c.vec_id)
SELECT * FROM (SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score FROM s)
WHERE rank <= 20
"""
