"""Sharding by best-fit-decreasing bin packing of indivisible groups."""

from __future__ import annotations

import random

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqcount.llm.common import checkpointed, join_by_weight, whole_text

OVERHEAD = 16
SLOT_BLOCKS = 4096
BROADCAST_SPANS = 500_000


class _Node:
    __slots__ = ("key", "heap", "left", "right")

    def __init__(self, key, heap):
        self.key, self.heap, self.left, self.right = key, heap, None, None


class Tree:
    """Ordered set of keys as a treap: a search tree kept balanced by random heap order."""

    def __init__(self, seed: int = 42):
        self.root, self.random = None, random.Random(seed).random

    def ceiling(self, key):
        """The least key that isn't below ``key``, or None."""
        at, found = self.root, None
        while at:
            if at.key < key:
                at = at.right
            else:
                found, at = at.key, at.left
        return found

    def add(self, key) -> None:
        new, path, at = _Node(key, self.random()), [], self.root
        while at and at.heap >= new.heap:
            path.append(at)
            at = at.left if key < at.key else at.right
        # what hangs below is parted by the key into the new node's two subtrees
        low, high = [], []
        rest = at
        while rest:
            if rest.key < key:
                low.append(rest)
                rest = rest.right
            else:
                high.append(rest)
                rest = rest.left
        new.left, new.right = self._joined(low, "right"), self._joined(high, "left")
        self._hang(path, key, new)

    def remove(self, key) -> None:
        path, at = [], self.root
        while at.key != key:
            path.append(at)
            at = at.left if key < at.key else at.right
        self._hang(path, key, self._merged(at.left, at.right))

    def _joined(self, spine: list, side: str):
        """Nodes of a spine linked anew on one side; what lay beyond has gone to the other spine."""
        for i, node in enumerate(spine):
            setattr(node, side, spine[i + 1] if i + 1 < len(spine) else None)
        return spine[0] if spine else None

    def _merged(self, low, high):
        """One tree of two, all keys of the first being below those of the second."""
        top, hang = None, None
        while low or high:
            if not high or (low and low.heap >= high.heap):
                node, side, low = low, "right", low.right
            else:
                node, side, high = high, "left", high.left
            if hang:
                setattr(hang[0], hang[1], node)
            else:
                top = node
            hang = (node, side)
        if hang:
            setattr(hang[0], hang[1], None)
        return top

    def _hang(self, path: list, key, node) -> None:
        if not path:
            self.root = node
        elif key < path[-1].key:
            path[-1].left = node
        else:
            path[-1].right = node


class Bins:
    """Open bins in a balanced tree by (remaining capacity, bin): the least that still fits is the tightest.

    A run of c equal items enters a bin together, as the tightest bin stays the
    tightest while it fills, so packing costs a search for each bin touched, not for
    each item.
    """

    def __init__(self, capacity: int, n_bins: int | None):
        self.capacity, self.n_bins, self.used = capacity, n_bins, 0
        self.left = Tree()

    def place(self, size: int, count: int) -> list[tuple[int, int]] | None:
        """[(bin, items)] for ``count`` items of one size, or None if the bins don't suffice."""
        out = []
        while count:
            found = self.left.ceiling((size, -1))
            if found:
                self.left.remove(found)
                rest, b = found
            elif self.n_bins is not None and self.used >= self.n_bins:
                return None
            else:
                rest, b, self.used = max(self.capacity, size), self.used, self.used + 1
            n = min(count, rest // size) if size else count
            self.left.add((rest - n * size, b))
            out.append((b, n))
            count -= n
        return out


def pack(histogram: list[tuple[int, int]], capacity: int, n_bins: int | None = None):
    """Best-fit-decreasing of {size: count}: [(size, first rank, end rank, bin)], or None beyond ``n_bins``.

    A group larger than the capacity gets a bin that it fills alone.
    """
    bins, spans = Bins(capacity, n_bins), []
    for size, count in sorted(histogram, reverse=True):
        placed = bins.place(size, count)
        if placed is None:
            return None
        at = 0
        for b, n in placed:
            spans.append((size, at, at + n, b))
            at += n
    return spans


def pack_evenly(histogram: list[tuple[int, int]], n_bins: int):
    """Spans for the least capacity, to one part in 4096 of the mean, at which best-fit-decreasing needs ``n_bins`` or fewer.

    Groups above the fair share keep bins of their own; the share is taken over the rest.
    """
    total = sum(s * c for s, c in histogram)
    rest, bins = total, n_bins
    for size, count in sorted(histogram, reverse=True):
        for _ in range(min(count, bins)):
            if bins > 1 and size * bins > rest:
                rest, bins = rest - size, bins - 1
            else:
                break
        else:
            continue
        break
    fair = max(1, -(-rest // bins))
    low, high, step = fair, None, max(1, fair // 4096)
    spans, grow = pack(histogram, low, n_bins), step
    if spans is not None:
        return spans
    while spans is None:
        high = low + grow
        spans = pack(histogram, high, n_bins)
        low, grow = (high, grow * 2) if spans is None else (low, grow)
    while high - low > step:
        mid = (low + high) // 2
        tried = pack(histogram, mid, n_bins)
        if tried is None:
            low = mid
        else:
            high, spans = mid, tried
    return spans


def shard_by_bytes(docs: DataFrame, n_shards: int, id_col: str = "doc_id", text_col: str = "text", overhead: int = OVERHEAD) -> DataFrame:
    """(rid, size, crc, shard, slot) of every row; equal texts share a shard, shards are near equal in bytes.

    Best-fit-decreasing depends on the multiset of group sizes only, so the driver packs
    the histogram {group size: groups}. Different sizes number at most sqrt(2 x total
    bytes), whatever the number of rows. Groups of one size are told apart by their rank
    in digest order; a group's copies follow it by a join in which heavy groups are
    broadcast. Slots count from 0 in each shard by (hash block, id, text).
    A null text has no bytes; a null id is an id like others; an empty table gives no rows.
    """
    if n_shards < 1:
        raise ValueError("n_shards must be positive")
    spark, text = docs.sparkSession, whole_text(text_col)
    rows = checkpointed(
        docs.select(
            F.col(id_col).cast("long").alias("rid"),
            F.monotonically_increasing_id().alias("uid"),
            F.unhex(F.sha2(text, 256)).alias("digest"),
            (F.octet_length(text).cast("long") + F.lit(overhead)).alias("size"),
            F.crc32(text.cast("binary")).alias("crc"),
        )
    )
    total = rows.count()
    groups = checkpointed(rows.groupBy("digest").agg(F.sum("size").alias("bytes"), F.count("*").alias("n")))
    block = F.conv(F.hex(F.substring("digest", 1, 2)), 16, 10).cast("int").alias("block")
    blocked = groups.select("digest", "bytes", "n", block)
    cells = checkpointed(blocked.groupBy("bytes", "block").agg(F.count("*").alias("c")))
    histogram = [(r["bytes"], r["c"]) for r in cells.groupBy("bytes").agg(F.sum("c").alias("c")).toLocalIterator()]
    spans = pack_evenly(histogram, n_shards) if histogram else []
    plan = spark.createDataFrame(spans, "bytes long, first long, end long, shard int")
    plan = F.broadcast(plan) if len(spans) <= BROADCAST_SPANS else plan
    # rank of a group among those of its size: rank in its digest block plus the groups in blocks before
    before = cells.selectExpr("bytes", "block", "sum(c) over (partition by bytes order by block) - c as before")
    ranked = blocked.selectExpr("digest", "bytes", "n", "block", "row_number() over (partition by bytes, block order by digest) - 1 as at")
    ranked = ranked.join(before, ["bytes", "block"]).withColumn("rank", F.col("at") + F.col("before"))
    where = ranked.join(plan, (ranked["bytes"] == plan["bytes"]) & (F.col("rank") >= plan["first"]) & (F.col("rank") < plan["end"]))
    homes = checkpointed(where.select("digest", "n", "shard"))
    placed = checkpointed(
        join_by_weight(rows, homes, ["digest"], "n", total).select(
            "rid", "uid", "digest", "size", "crc", "shard", F.pmod(F.xxhash64("rid", "digest"), F.lit(SLOT_BLOCKS)).alias("cell")
        )
    )
    counts = placed.groupBy("shard", "cell").agg(F.count("*").alias("c"))
    starts = counts.selectExpr("shard", "cell", "sum(c) over (partition by shard order by cell) - c as start")
    numbered = placed.selectExpr("*", "row_number() over (partition by shard, cell order by rid, digest, uid) - 1 as at")
    return numbered.join(starts, ["shard", "cell"]).select("rid", "size", "crc", "shard", (F.col("start") + F.col("at")).cast("long").alias("slot"))


def op3_sharding(spark, sf_dir: str) -> DataFrame:
    """Every document's shard and slot among 40; see ``shard_by_bytes`` for null, empty and repeated rows."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return shard_by_bytes(docs, 40).select(
        F.col("rid").alias("doc_id"),
        "size",
        F.col("crc").alias("text_crc32"),
        F.lit("bytes").alias("law"),
        "shard",
        "slot",
        F.lit(None).cast("int").alias("grown_shard"),
    )
