"""Measures: time, volume, balance, work, exactness and errors of sketches."""

from __future__ import annotations

import os
import threading
import time
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def timed(make: Callable[[], DataFrame]) -> float:
    """Seconds until every row of a frame has been made and dropped."""
    began = time.monotonic()
    make().write.format("noop").mode("overwrite").save()
    return time.monotonic() - began


def stage_times(reads: DataFrame, spec, partitions: int) -> dict[str, float]:
    """Seconds of preparation, exchange, and counting, each as what it adds to the stages before."""
    from seqcount.operators import counting, exchange
    from seqcount.plans.flagship import make_plan

    plan = make_plan(reads, spec, partitions)
    blocks = exchange.make_blocks(reads, spec, plan.placed, plan.heavy, partitions)
    a = timed(lambda: blocks)
    b = timed(lambda: exchange.exchange(blocks, partitions))
    c = timed(lambda: counting.count_blocks(exchange.exchange(blocks, partitions), spec, as_spectrum=True))
    return {"preparation": a, "exchange": max(0.0, b - a), "counting": max(0.0, c - b)}


def peak_memory(make: Callable[[], DataFrame], every: float = 0.05) -> int:
    """Most bytes that this process, its JVM and its workers hold while a frame is made; for local sessions."""
    stop, most = threading.Event(), [0]

    def watch():
        while not stop.is_set():
            most[0] = max(most[0], _resident(os.getpid()))
            stop.wait(every)

    thread = threading.Thread(target=watch, daemon=True)
    thread.start()
    try:
        timed(make)
    finally:
        stop.set()
        thread.join()
    return most[0]


def _resident(top: int) -> int:
    """Resident bytes of a process and all below it, from /proc."""
    parent, pages = {}, {}
    for name in filter(str.isdigit, os.listdir("/proc")):
        try:
            with open(f"/proc/{name}/stat") as f:
                parent[int(name)] = int(f.read().rpartition(")")[2].split()[1])
            with open(f"/proc/{name}/statm") as f:
                pages[int(name)] = int(f.read().split()[1])
        except OSError:
            continue
    own = {top}
    while more := {p for p, q in parent.items() if q in own and p not in own}:
        own |= more
    return sum(pages.get(p, 0) for p in own) * os.sysconf("SC_PAGE_SIZE")


def speedup(base: float, new: float) -> float:
    return base / new


def strong_efficiency(t1: float, p1: int, tp: float, p: int) -> float:
    """Of p workers against p1 on the same data; it may exceed 1."""
    return t1 * p1 / (tp * p)


def weak_efficiency(t1: float, tp: float) -> float:
    """Of more workers with as much more data."""
    return t1 / tp


def balance(sizes) -> dict[str, float]:
    """Spread of task sizes."""
    x = np.asarray(sizes, float)
    return {"mean": float(x.mean()), "stddev": float(x.std()), "max_min": float(x.max() / x.min()) if x.min() else float("inf"), "max_mean": float(x.max() / x.mean())}


def balance_of(sizes: DataFrame, column: str = "n_kmers") -> DataFrame:
    """(tasks, mean, stddev, max_min, max_mean) of a table of sizes."""
    c = F.col(column)
    return sizes.agg(
        F.count("*").alias("tasks"), F.round(F.avg(c), 6).alias("mean"), F.round(F.stddev_pop(c), 6).alias("stddev"),
        F.round(F.max(c) / F.min(c), 6).alias("max_min"), F.round(F.max(c) / F.avg(c), 6).alias("max_mean"),
    )


def supermer_stats(supermers: DataFrame, k: int) -> DataFrame:
    """(supermers, kmers, mean_bases, max_bases, bytes) of supermer rows."""
    n = F.col("n_bases")
    return supermers.agg(
        F.count("*").alias("supermers"), F.sum(n - (k - 1)).cast("long").alias("kmers"), F.round(F.avg(n), 6).alias("mean_bases"),
        F.max(n).cast("int").alias("max_bases"), F.sum(F.ceil(n / 4) + 2).cast("long").alias("bytes"),
    )


def heavy_stats(sizes: DataFrame, factor: float) -> DataFrame:
    """(task, n_kmers, times_mean) of tasks above ``factor`` times the mean."""
    mean = sizes.agg(F.avg("n_kmers").alias("mean"))
    return sizes.join(F.broadcast(mean)).where(F.col("n_kmers") > factor * F.col("mean")).select("task", "n_kmers", F.round(F.col("n_kmers") / F.col("mean"), 6).alias("times_mean"))


def minimizer_work(scores: np.ndarray, w: int) -> dict[str, int]:
    """Comparisons of each minimizer method on one sequence of scores."""
    from seqcount.functions.minimizers import METHODS, Work

    out = {}
    for name, find in METHODS.items():
        work = Work()
        find(scores, w, "right", work)
        out[name] = work.comparisons
    return out


def over_counts(approximate: DataFrame, exact: DataFrame) -> DataFrame:
    """(keys, under, over, excess): keys whose approximate count is below or above the exact one, and by how much in all."""
    both = approximate.select("kmer", F.col("cnt").alias("a")).join(exact.select("kmer", F.col("cnt").alias("e")), "kmer", "full_outer").na.fill(0, ["a", "e"])
    return both.agg(F.count("*").alias("keys"), F.count_if(F.col("a") < F.col("e")).alias("under"), F.count_if(F.col("a") > F.col("e")).alias("over"), F.sum(F.col("a") - F.col("e")).alias("excess"))


def shuffle_bytes(spark, make: Callable[[], DataFrame]) -> int:
    """Bytes that Spark's shuffles wrote while a frame was made, from its own status store; -1 where that isn't kept."""
    store = spark.sparkContext._jsc.sc().statusStore()
    total = lambda: sum(s.shuffleWriteBytes() for s in _scala_list(spark, store.stageList(None, False, False, spark.sparkContext._gateway.new_array(spark._jvm.double, 0), None)))
    try:
        before = total()
        timed(make)
        return total() - before
    except Exception:  # noqa: BLE001  a private interface of Spark: the measure is optional
        return -1


def _scala_list(spark, seq):
    return spark._jvm.scala.jdk.javaapi.CollectionConverters.asJava(seq)
