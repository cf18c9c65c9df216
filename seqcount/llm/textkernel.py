"""Vectorised words and word hashes of an Arrow batch of texts: no Python loop over words."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

#: Texts are taken in groups of about this many bytes, and longer ones in blocks, so memory follows neither batch nor text.
GROUP_BYTES = 1 << 20
#: Words that a block repeats from the one before: runs are told apart up to so many words.
CARRIED = 17

_CLASS = np.full(256, 4, np.uint8)  # 4: beyond ASCII, counted as a small letter
_CLASS[:128] = 0
_CLASS[ord("a") : ord("z") + 1] = 4
_CLASS[ord("A") : ord("Z") + 1] = 5
_CLASS[ord("0") : ord("9") + 1] = 6
_BLANK = np.zeros(256, bool)
_BLANK[[32, 9, 10, 11, 12, 13]] = True
_SPACES = bytes(32 if b else i for i, b in enumerate(_BLANK))
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[ord("A") : ord("Z") + 1] += 32
_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
_INVERSE = np.uint64(pow(int(_BASE), -1, 1 << 64))
_M1, _M2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
_powers: list[np.ndarray] = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def mix(h: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: close inputs get unrelated outputs."""
    h = (h ^ (h >> np.uint64(30))) * _M1
    h = (h ^ (h >> np.uint64(27))) * _M2
    return h ^ (h >> np.uint64(31))


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_powers[0]) < n + 1:
        for k, base in enumerate((_BASE, _INVERSE)):
            steps = np.full(n + 1, base, np.uint64)
            steps[0] = 1
            _powers[k] = np.multiply.accumulate(steps)
    return _powers[0], _powers[1]


def _polynomial(codes: np.ndarray):
    """A function that hashes spans [start, end) of codes, by prefix sums of a polynomial modulo 2^64."""
    up, down = _power_tables(len(codes))
    sums = np.zeros(len(codes) + 1, np.uint64)
    np.cumsum(codes.astype(np.uint64) * up[: len(codes)], out=sums[1:])
    return lambda starts, ends: (sums[ends] - sums[starts]) * down[starts]


class Words:
    """Words of a group of texts: ``doc`` of each word, ``word`` hash in lower case, ``style`` and ``stems`` hashes.

    ``stems``: for each asked length, (indexes of the words with more bytes, hash of their first bytes).
    ``lead``: words at the start that the block before had already; ``more``: the text goes on in the next block.
    """

    def __init__(self, doc: np.ndarray, word: np.ndarray, style: np.ndarray | None, stems: list):
        self.doc, self.word, self.style, self.stems = doc, word, style, stems
        self.first, self.n_docs, self.lead, self.more = 0, 1, 0, False


def groups_of_words(texts: pa.Array, style: bool = False, stems: tuple[int, ...] = ()) -> Iterator[Words]:
    """Words of all texts, in groups of whole texts, or blocks of a long one; null is the empty text.

    A word is a run of bytes other than space and tab to carriage return, however long. The style hash sees, in order, each change of
    character class within the word, symbols by themselves: it tells capitals, digits
    and trailing marks but no letters.
    """
    data = texts.cast(pa.large_string()).cast(pa.large_binary())
    if data.null_count:
        data = data.fill_null(b"")
    offsets = np.frombuffer(data.buffers()[1], np.int64)[data.offset : data.offset + len(data) + 1]
    body = np.frombuffer(data.buffers()[2] or b"", np.uint8) if data.buffers()[2] is not None else np.zeros(0, np.uint8)
    first = 0
    while first < len(data):
        last = max(first + 1, int(np.searchsorted(offsets, offsets[first] + GROUP_BYTES, "right")) - 1)
        last = min(last, len(data))
        at = offsets[first : last + 1] - offsets[first]
        if last == first + 1 and at[-1] > GROUP_BYTES:
            blocks = _blocks(body[offsets[first] : offsets[last]])
        else:
            blocks = [(body[offsets[first] : offsets[last]], at, 0, False)]
        for part, ends, lead, more in blocks:
            g = _group(part, ends, style, stems)
            g.first, g.n_docs, g.lead, g.more = first, last - first, lead, more
            yield g
        first = last


def _blocks(body: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, int, bool]]:
    """A long text in blocks that end at blanks, each with the last words of those before at its start."""
    data, at, tail = body.tobytes(), 0, []
    plain = data.translate(_SPACES)
    while at < len(data):
        end = plain.find(b" ", at + GROUP_BYTES) + 1 or len(data)
        part = b" ".join([*tail, data[at:end]])
        yield np.frombuffer(part, np.uint8), np.array([0, len(part)]), len(tail), end < len(data)
        tail = part.rsplit(None, CARRIED)[-CARRIED:]
        at = end


def whole_counts(groups: Iterator[Words], terms_of, n_terms: int):
    """(first text, texts, text, term, count, words of each text): counts of whole texts, of blocks put together."""
    held = None
    for g in groups:
        doc, term, n = counted(*terms_of(g), n_terms)
        words = np.bincount(g.doc[g.lead :], minlength=g.n_docs)
        if held:
            term, where = np.unique(np.concatenate([held[0], term]), return_inverse=True)
            n = np.bincount(where, np.concatenate([held[1], n])).astype(np.int64)
            doc, words = np.zeros(len(term), np.int64), words + held[2]
        held = (term, n, words) if g.more else None
        if not g.more:
            yield g.first, g.n_docs, doc, term, n, words


def _group(body: np.ndarray, at: np.ndarray, style: bool, stems: tuple[int, ...]) -> Words:
    if not len(body):
        none = np.zeros(0, np.uint64)
        return Words(np.zeros(0, np.int64), none, none, [(np.zeros(0, np.int64), none) for _ in stems])
    edge = np.zeros(len(body) + 1, bool)
    edge[at] = True
    full = ~_BLANK[body]
    left, right = np.ones(len(body), bool), np.ones(len(body), bool)
    left[1:] = ~full[:-1] | edge[1:-1]
    right[:-1] = ~full[1:] | edge[1:-1]
    starts, ends = np.flatnonzero(full & left), np.flatnonzero(full & right) + 1
    doc = np.searchsorted(at, starts, "right") - 1
    # plus one, so that a byte 0 counts; the length tells apart what ends in such bytes
    hashes = _polynomial(_LOWER[body].astype(np.uint16) + 1)
    word = mix(hashes(starts, ends) + (ends - starts).astype(np.uint64))
    heads = []
    for n in stems:
        longer = np.flatnonzero(ends - starts > n)
        heads.append((longer, mix(hashes(starts[longer], starts[longer] + n) - np.uint64(n))))
    if not style:
        return Words(doc, word, None, heads)
    kind = _CLASS[body]
    kind = np.where(kind == 0, body.astype(np.uint16) + 8, kind)
    fresh = np.ones(len(body), bool)
    fresh[1:] = (kind[1:] != kind[:-1]) | left[1:]
    keep = np.flatnonzero(fresh & full)
    lo, hi = np.searchsorted(keep, starts), np.searchsorted(keep, ends)
    shape = mix(_polynomial(kind[keep])(lo, hi) + np.uint64(0x5EED))
    return Words(doc, word, shape, heads)


def counted(doc: np.ndarray, term: np.ndarray, n_terms: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Different (doc, term) pairs in order, and how often each occurs."""
    key, n = np.unique(doc.astype(np.int64) * n_terms + term.astype(np.int64), return_counts=True)
    return key // n_terms, key % n_terms, n
