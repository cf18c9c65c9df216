"""Least score of each window of w consecutive m-mers, by five methods that agree.

``window_block`` is what production runs. The others are the method that it stands for
and the older ones that the experiments compare; they count their comparisons.
Each returns (least score, its position) for every window; of equal scores the
rightmost is named, or the leftmost with tie='left'.
"""

from __future__ import annotations

from collections import deque

import numpy as np


class Work:
    """Comparisons of scores that a method has made."""

    def __init__(self):
        self.comparisons = 0


def window_deque(scores: np.ndarray, w: int, tie: str = "right", work: Work | None = None):
    """Monotone double-ended queue: each score enters and leaves once, whatever w."""
    n = max(0, len(scores) - w + 1)
    least, where = np.empty(n, np.int64), np.empty(n, np.int64)
    held: deque[tuple[int, int]] = deque()
    work = work or Work()
    for i, x in enumerate(scores.tolist()):
        if held and held[0][1] <= i - w:
            held.popleft()
        while held:
            work.comparisons += 1
            if held[-1][0] > x or (held[-1][0] == x and tie == "right"):
                held.pop()
            else:
                break
        held.append((x, i))
        if i >= w - 1:
            least[i - w + 1], where[i - w + 1] = held[0]
    return least, where


def window_rescan(scores: np.ndarray, w: int, tie: str = "right", work: Work | None = None):
    """Keep the current minimizer; look through the whole window again when it has left."""
    n = max(0, len(scores) - w + 1)
    least, where = np.empty(n, np.int64), np.empty(n, np.int64)
    work, at, x = work or Work(), -1, 0
    values = scores.tolist()
    for i in range(n):
        if at < i:
            work.comparisons += w
            span = values[i : i + w]
            x = min(span)
            at = i + (w - 1 - span[::-1].index(x) if tie == "right" else span.index(x))
        else:
            work.comparisons += 1
            new = values[i + w - 1]
            if new < x or (new == x and tie == "right"):
                x, at = new, i + w - 1
        least[i], where[i] = x, at
    return least, where


def window_naive(scores: np.ndarray, w: int, tie: str = "right", work: Work | None = None):
    """Each window by itself."""
    n = max(0, len(scores) - w + 1)
    work = work or Work()
    work.comparisons += n * w
    if not n:
        return np.empty(0, np.int64), np.empty(0, np.int64)
    spans = np.lib.stride_tricks.sliding_window_view(scores, w)
    at = w - 1 - np.argmin(spans[:, ::-1], axis=1) if tie == "right" else np.argmin(spans, axis=1)
    return spans[np.arange(n), at].astype(np.int64), np.arange(n) + at


def block_minimum(values: np.ndarray, w: int) -> np.ndarray:
    """Minimum of each window, in time linear in the length and without regard to w.

    The positions are cut into blocks of w. A window begins in one block and ends in
    it or the next: its minimum is that of the running minimum from its block's end
    back to its begin, and of the running minimum from the next block's begin to its end.
    """
    n = len(values) - w + 1
    if n <= 0:
        return values[:0]
    blocks = -(-len(values) // w)
    padded = np.full(blocks * w, np.iinfo(values.dtype).max, values.dtype)
    padded[: len(values)] = values
    grid = padded.reshape(blocks, w)
    ahead = np.minimum.accumulate(grid, axis=1).ravel()
    back = np.minimum.accumulate(grid[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(back[:n], ahead[w - 1 : w - 1 + n])


def window_block(scores: np.ndarray, w: int, tie: str = "right", work: Work | None = None):
    """Block minima of (score, position) in one 64-bit key; scores must be below 2^32 and positions below 2^31."""
    if work:
        work.comparisons += 3 * len(scores)
    at = np.arange(len(scores), dtype=np.uint64)
    place = np.uint64(0xFFFFFFFF) - at if tie == "right" else at
    key = block_minimum((scores.astype(np.uint64) << np.uint64(32)) | place, w)
    where = key & np.uint64(0xFFFFFFFF)
    where = np.uint64(0xFFFFFFFF) - where if tie == "right" else where
    return (key >> np.uint64(32)).astype(np.int64), where.astype(np.int64)


METHODS = {"deque": window_deque, "block": window_block, "rescan": window_rescan, "naive": window_naive}
