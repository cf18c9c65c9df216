"""Parameters of a counting run."""

from __future__ import annotations

from dataclasses import dataclass, replace

#: Longest k-mer in one 64-bit word that is never negative, and in two such words.
ONE_WORD, TWO_WORDS = 31, 62
#: Minimizer lengths that the experiments use for these k.
TRIED_M = {17: 11, 31: 17, 55: 23}
SCORES = ("murmur3", "lex", "lex_mod", "arith", "universal")


def default_m(k: int) -> int:
    """About half of k for small k, 23 for large; below k always."""
    return min(TRIED_M.get(k, min(23, max(3, round(k / 2) + 1))), max(1, k - 1))


def tasks_from(partitions: int, workers: int = 1, per_worker: int = 3) -> int:
    """Batches for so many partitions, workers in each, and tasks for each worker."""
    return max(1, partitions * workers * per_worker)


@dataclass(frozen=True)
class CountSpec:
    """How reads are cut, scored, routed and counted; never inferred from data.

    k, m: lengths. s: tasks. lo, hi: inclusive frequency range. break_on: what ends a
    supermer. tie: which of equal scores is named as the minimizer: the first or last, or
    with 'lex' that of the least m-mer, of equal ones the last. dest: what a k-mer's task
    is made from: 'score', the least score itself, or 'second_hash', another hash of the
    minimizer, whose ties then are lexical, so that equal k-mers agree. heavy_factor: a task above it times the mean is heavy. chunk: bases
    that one row of a long read keeps. block_bytes: payload of a supermer block.
    worker_bytes: memory that the keys of a task may take while they're sorted.
    """

    k: int = 31
    m: int | None = None
    s: int = 256
    score: str = "murmur3"
    seed: int = 42
    tie: str = "right"
    dest: str = "score"
    break_on: str = "task"
    canonical: bool = False
    lo: int = 2
    hi: int = 50
    heavy_factor: float = 3.0
    growth: float = 0.05
    chunk: int = 1 << 16
    block_bytes: int = 80_000
    worker_bytes: int = 1 << 30

    def __post_init__(self):
        if self.m is None:
            object.__setattr__(self, "m", default_m(self.k))
        if not 1 <= self.k <= TWO_WORDS:
            raise ValueError(f"k must be 1 to {TWO_WORDS}")
        if not 1 <= self.m <= min(self.k, ONE_WORD):
            raise ValueError("m must be 1 to k, and fit one word")
        if self.s < 1 or self.lo < 1 or self.hi < self.lo:
            raise ValueError("s and lo must be positive, hi at least lo")
        if self.score not in SCORES or self.tie not in ("left", "right", "lex") or self.break_on not in ("task", "minimizer"):
            raise ValueError("unknown score, tie or break_on")
        if self.dest not in ("score", "second_hash"):
            raise ValueError("unknown dest")
        if self.chunk < 4 * self.k:
            raise ValueError("chunk must hold several k-mers")

    @property
    def w(self) -> int:
        """m-mers in a k-mer."""
        return self.k - self.m + 1

    @property
    def words(self) -> int:
        return 1 if self.k <= ONE_WORD else 2

    def but(self, **changes) -> CountSpec:
        return replace(self, **changes)
