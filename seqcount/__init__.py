"""Exact, distributed counting of fixed-length subsequences (k-mers) on Spark."""

from seqcount.spec import CountSpec, default_m, tasks_from

__all__ = ["CountSpec", "default_m", "tasks_from"]
