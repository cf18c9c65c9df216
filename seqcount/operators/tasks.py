"""The task layer: sizes, heavy tasks, and packing of tasks onto partitions."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def task_sizes(supermers: DataFrame) -> DataFrame:
    """(task, n_supermers, n_kmers, bytes) of supermer rows (task, n_bases, n_kmers, packed)."""
    return supermers.groupBy("task").agg(F.count("*").alias("n_supermers"), F.sum("n_kmers").alias("n_kmers"), F.sum(F.octet_length("packed") + 2).alias("bytes"))


def size_vector(rows, s: int) -> np.ndarray:
    """k-mers of every task, also of those without any."""
    sizes = np.zeros(s, np.int64)
    for r in rows:
        sizes[r["task"]] = r["n_kmers"]
    return sizes


def heavy_tasks(sizes: np.ndarray, factor: float = 3.0, filled: bool = False) -> np.ndarray:
    """Tasks with more than factor times the mean over all tasks, or over the filled ones: they're where frequent k-mers must be."""
    over = sizes[sizes > 0] if filled else sizes
    return np.flatnonzero(sizes > factor * over.mean()) if len(over) else np.zeros(0, np.int64)


def assign_tasks(sizes, partitions: int, growth: float = 0.05, policy: str = "greedy") -> np.ndarray:
    """Partition of each task.

    greedy: tasks in order of size go to the first partition that stays within a
    level, which begins at the mean load and grows until all tasks have a place; a tree
    of the most room below each node finds it, so a try takes s log(partitions) steps.
    Others: longest_first (to the emptiest partition), round_robin, modulo.
    """
    sizes = np.asarray(sizes, np.int64)
    n = len(sizes)
    if partitions < 1:
        raise ValueError("partitions must be positive")
    if policy in ("round_robin", "modulo"):
        return np.arange(n) % partitions
    order = np.lexsort((np.arange(n), -sizes))
    if policy == "longest_first":
        import heapq

        heap, out = [(0, p) for p in range(partitions)], np.zeros(n, np.int64)
        for t in order.tolist():
            load, p = heapq.heappop(heap)
            out[t] = p
            heapq.heappush(heap, (load + int(sizes[t]), p))
        return out
    if policy != "greedy":
        raise ValueError(f"unknown policy {policy}")
    level = max(sizes.sum() / partitions, float(sizes.max(initial=0)))
    while True:
        placed = _first_fit(sizes, order, partitions, level)
        if placed is not None:
            return placed
        level *= 1 + growth


def _first_fit(sizes: np.ndarray, order: np.ndarray, partitions: int, level: float) -> np.ndarray | None:
    leaves = 1 << max(0, (partitions - 1).bit_length())
    room = [-1.0] * (2 * leaves)  # room[1] is the root, the children of i are 2 i and 2 i + 1
    room[leaves : leaves + partitions] = [float(level)] * partitions
    for i in range(leaves - 1, 0, -1):
        room[i] = max(room[2 * i], room[2 * i + 1])
    out = np.zeros(len(sizes), np.int64)
    for t, size in zip(order.tolist(), sizes[order].tolist(), strict=True):
        if room[1] < size:
            return None
        i = 1
        while i < leaves:
            i = 2 * i if room[2 * i] >= size else 2 * i + 1
        out[t] = i - leaves
        room[i] -= size
        while i > 1:
            i //= 2
            room[i] = max(room[2 * i], room[2 * i + 1])
    return out


def loads(sizes, placed: np.ndarray, partitions: int) -> np.ndarray:
    return np.bincount(placed, weights=np.asarray(sizes, float), minlength=partitions)
