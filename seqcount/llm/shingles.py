"""XXH64 of word shingles by array passes over many texts at once: no Python loop over words."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash

SEED, BITS = 42, 64
#: Texts are taken in groups of about this many bytes, and longer ones in blocks that end at blanks.
GROUP_BYTES = 1 << 20
#: Longer shingles are hashed one by one.
_ONE_BY_ONE = 512
#: Shingles whose bits are added in lanes of one byte.
_LANE = 255
#: A-Z in lower case, and the six blanks as spaces.
_PLAIN = bytes(c + 32 if 65 <= c <= 90 else 32 if 9 <= c <= 13 else c for c in range(256))
#: Fixed values of XXH64.
_P1, _P2, _P3, _P4, _P5 = (
    np.uint64(x) for x in (11400714785074694791, 14029467366897019727, 1609587929392839161, 9650029242287828579, 2870177450012600261)
)
_ONES = np.uint64(0x0101010101010101)


def _rolled(x: np.ndarray, n: int) -> np.ndarray:
    return (x << np.uint64(n)) | (x >> np.uint64(64 - n))


def _round(acc: np.ndarray, lane: np.ndarray) -> np.ndarray:
    return _rolled(acc + lane * _P2, 31) * _P1


def hash_spans(data: np.ndarray, start: np.ndarray, size: np.ndarray) -> np.ndarray:
    """XXH64 of each span of bytes; ``data`` is followed by 8 spare bytes at least."""
    two = data[:-1].astype(np.uint16) | (data[1:].astype(np.uint16) << np.uint16(8))
    four = two[:-2].astype(np.uint32) | (two[2:].astype(np.uint32) << np.uint32(16))
    eight = four[:-4].astype(np.uint64) | (four[4:].astype(np.uint64) << np.uint64(32))
    size8, at = size.astype(np.uint64), start.copy()
    h = np.full(len(start), (SEED + int(_P5)) % (1 << 64), np.uint64)
    wide = np.flatnonzero((size >= 32) & (size <= _ONE_BY_ONE))
    if len(wide):
        stripes = size[wide] >> 5
        acc = [np.full(len(wide), (SEED + add) % (1 << 64), np.uint64) for add in (int(_P1) + int(_P2), int(_P2), 0, -int(_P1))]
        for turn in range(int(stripes.max())):
            go = np.flatnonzero(stripes > turn)
            for i in range(4):
                acc[i][go] = _round(acc[i][go], eight[at[wide[go]] + (32 * turn + 8 * i)])
        both = sum(_rolled(a, n) for a, n in zip(acc, (1, 7, 12, 18), strict=True))
        for a in acc:
            both = (both ^ _round(np.uint64(0), a)) * _P1 + _P4
        h[wide] = both
        at[wide] += stripes << 5
    h += size8
    rest = size & 31
    for turn in range(3):
        go = np.flatnonzero(rest >> 3 > turn)
        h[go] = _rolled(h[go] ^ _round(np.uint64(0), eight[at[go] + 8 * turn]), 27) * _P1 + _P4
    at += rest & 24
    go = np.flatnonzero(rest & 4)
    h[go] = _rolled(h[go] ^ (four[at[go]].astype(np.uint64) * _P1), 23) * _P2 + _P3
    at[go] += 4
    for turn in range(3):
        go = np.flatnonzero((rest & 3) > turn)
        h[go] = _rolled(h[go] ^ (data[at[go] + turn].astype(np.uint64) * _P5), 11) * _P1
    h = (h ^ (h >> np.uint64(33))) * _P2
    h = (h ^ (h >> np.uint64(29))) * _P3
    h ^= h >> np.uint64(32)
    for i in np.flatnonzero(size > _ONE_BY_ONE).tolist():
        h[i] = xxhash.xxh64_intdigest(data[start[i] : start[i] + size[i]].tobytes(), SEED)
    return h


class Part:
    """Words of whole texts, or of one block of a long text.

    ``first``, ``texts``: which texts. ``data``: their words, each followed by one space,
    and 8 spare bytes. ``ends``: where words end. ``before``: words before each text, and
    in all. ``lead``: words at the start that the block before had already; ``seen``: words
    of the text up to there; ``more``: the text goes on in the next block.
    """

    def __init__(self, plain: bytes, sizes: np.ndarray, first: int, lead: int = 0, seen: int = 0, more: bool = False):
        self.first, self.texts, self.lead, self.seen, self.more = first, len(sizes), lead, seen, more
        raw = np.frombuffer(plain, np.uint8)
        full = raw != 32
        head = full.copy()
        head[1:] &= ~full[:-1]
        edges = np.concatenate([[0], np.cumsum(sizes + 1)])
        self.before = np.searchsorted(np.flatnonzero(head), edges)
        full[1:] |= full[:-1]  # the first blank after each word
        self.data = np.concatenate([raw[full], np.zeros(8, np.uint8)])
        self.ends = np.flatnonzero(self.data[:-8] == 32)

    def shingles(self, words: int) -> tuple[np.ndarray, np.ndarray]:
        """(hashes, before): of each text's shingles in order, a text of fewer words as a whole; numbers before each text."""
        n = np.diff(self.before)
        count, had = np.maximum(n - words + 1, 0), max(0, self.lead - words + 1)
        if not self.more and self.seen < words:
            count = np.where(n > 0, np.maximum(1, count), 0)
        count = count - had
        before = np.concatenate([[0], np.cumsum(count)])
        first = had + np.arange(before[-1]) + np.repeat(self.before[:-1] - before[:-1], count)
        last = np.minimum(first + words - 1, np.repeat(self.before[1:], count) - 1)
        begins = np.concatenate([[0], self.ends + 1])[first]
        return hash_spans(self.data, begins, self.ends[last] - begins), before


def parts_of(texts: pa.Array, words: int, group_bytes: int | None = None) -> Iterator[Part]:
    """All texts, null as empty, in groups of whole texts, or blocks of a long one that share words - 1 words.

    A block ends at a blank, however long the word before it is, so that no word is cut.
    """
    most = group_bytes or GROUP_BYTES
    held, sizes, total, first = [], [], 0, 0

    def group():
        return Part(b" ".join([*held, b""]), np.array(sizes, np.int64), first)

    for i, t in enumerate(texts.cast(pa.large_string()).cast(pa.large_binary())):
        data = t.as_buffer()
        size = data.size if data is not None else 0
        if held and total + size > most:
            yield group()
            held, sizes, total = [], [], 0
        if not held:
            first = i
        if size > most:
            yield from _blocks(data.to_pybytes(), i, words, most)
            continue
        held.append(data.to_pybytes().translate(_PLAIN) if size else b"")
        sizes.append(size)
        total += size
    if held:
        yield group()


def _blocks(data: bytes, index: int, words: int, most: int) -> Iterator[Part]:
    data, at, tail, lead, seen = data.translate(_PLAIN), 0, b"", 0, 0
    while at < len(data):
        end = data.find(b" ", at + most) + 1 or len(data)
        plain = tail + data[at:end]
        part = Part(plain + b" ", np.array([len(plain)]), index, lead, seen, end < len(data))
        n = len(part.ends)
        keep = n if n < words else words - 1
        tail = part.data[part.ends[n - keep - 1] + 1 if keep < n else 0 : len(part.data) - 8].tobytes() if keep else b""
        at, lead, seen = end, keep, seen + n - lead
        yield part


def bit_counts(hashes: np.ndarray, before: np.ndarray) -> np.ndarray:
    """(texts, 64): in how many of a text's hashes each bit is set."""
    n = np.diff(before)
    out = np.zeros((len(n), 8, 8), np.int64)
    some = np.flatnonzero(n)
    if not len(some):
        return out.reshape(-1, BITS)
    lanes = -(-n[some] // _LANE)
    place = np.cumsum(lanes) - lanes
    begin = np.repeat(before[some], lanes) + _LANE * (np.arange(lanes.sum()) - np.repeat(place, lanes))
    for j in range(8):
        sums = np.add.reduceat((hashes >> np.uint64(j)) & _ONES, begin).view(np.uint8).reshape(-1, 8)
        out[some, :, j] = np.add.reduceat(sums, place, axis=0, dtype=np.int64)
    return out.reshape(-1, BITS)


def majority(ones: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Words of 64 bits, each set if it's set in over half of the n hashes; 0 of none."""
    return np.packbits(2 * ones > n[:, None], axis=1, bitorder="little").view("<i8").ravel()
