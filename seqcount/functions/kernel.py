"""Vectorised passes over a batch of reads: packing, scoring, supermers and their expansion."""

from __future__ import annotations

import numpy as np
import pyarrow as pa

from seqcount.functions.minimizers import block_minimum
from seqcount.functions.scores import NO_SCORE, lexical_ranks, score_array, second_hash
from seqcount.spec import ONE_WORD, CountSpec

#: Bases that one pass takes at once, so that memory doesn't follow the batch.
PASS_BASES = 1 << 20
#: Supermers are cut so that their length fits 16 bits.
MAX_BASES = 65_535

_CODE = np.full(256, 4, np.uint8)
for _i, _c in enumerate(b"ACGT"):
    _CODE[_c] = _i


#: Bits of a run's last byte that its bases fill, by the number of bases modulo 4.
_LAST = np.array([0xFF, 0xC0, 0xF0, 0xFC], np.uint8)


def rolling_pack(codes: np.ndarray, length: int) -> np.ndarray:
    """Packed word of the ``length`` codes from each position, by doubling; garbage where a code is 4."""
    n = len(codes) - length + 1
    if n <= 0:
        return np.zeros(0, np.int64)
    power, have = (codes & 3).astype(np.int64), 1
    out, done = None, 0
    rest = length
    while rest:
        if rest & 1:
            if out is None:
                out, done = power.copy(), have
            else:  # what has been put together lies before this power
                m = min(len(out), len(power) - done)
                out = (out[:m] << (2 * have)) | power[done : done + m]
                done += have
        rest >>= 1
        if rest:
            m = len(power) - have
            power, have = (power[:m] << (2 * have)) | power[have:], 2 * have
    return out[:n]


def window_valid(codes: np.ndarray, length: int) -> np.ndarray:
    """Whether the ``length`` codes from each position are all bases."""
    n = len(codes) - length + 1
    if n <= 0:
        return np.zeros(0, bool)
    bad = np.concatenate([[0], np.cumsum(codes == 4)])
    return bad[length:] == bad[:n]


def reverse_complement(words: np.ndarray, length: int) -> np.ndarray:
    """Of packed words."""
    x = ~words.astype(np.uint64)
    for shift, mask in ((2, 0x3333333333333333), (4, 0x0F0F0F0F0F0F0F0F), (8, 0x00FF00FF00FF00FF), (16, 0x0000FFFF0000FFFF), (32, 0xFFFFFFFF)):
        s, m = np.uint64(shift), np.uint64(mask)
        x = ((x >> s) & m) | ((x & m) << s)
    return (x >> np.uint64(64 - 2 * length)).astype(np.int64)


def kmer_words(codes: np.ndarray, k: int, canonical: bool = False) -> list[np.ndarray]:
    """Packed k-mers from each position: one word, or [hi, lo] with the last 31 bases in lo."""
    if k <= ONE_WORD:
        words = rolling_pack(codes, k)
        return [np.minimum(words, reverse_complement(words, k))] if canonical else [words]
    cut = k - ONE_WORD
    hi, lo = rolling_pack(codes, cut)[: max(0, len(codes) - k + 1)], rolling_pack(codes[cut:], ONE_WORD)
    if canonical:
        head, tail = rolling_pack(codes, ONE_WORD)[: len(hi)], rolling_pack(codes[ONE_WORD:], cut)
        other_hi, other_lo = reverse_complement(tail, cut), reverse_complement(head, ONE_WORD)
        less = (other_hi < hi) | ((other_hi == hi) & (other_lo < lo))
        hi, lo = np.where(less, other_hi, hi), np.where(less, other_lo, lo)
    return [hi, lo]


def mmer_words(codes: np.ndarray, spec: CountSpec) -> np.ndarray:
    """Packed m-mer from each position."""
    words = rolling_pack(codes, spec.m)
    return np.minimum(words, reverse_complement(words, spec.m)) if spec.canonical else words


def mmer_scores(codes: np.ndarray, spec: CountSpec) -> np.ndarray:
    """Score of the m-mer from each position; above all scores where it isn't one."""
    words = mmer_words(codes, spec)
    return np.where(window_valid(codes, spec.m), score_array(words, spec.m, spec.score, spec.seed), NO_SCORE)


def groups(seqs: pa.Array, pass_bases: int = PASS_BASES):
    """(first row, row of each place, place within its row, codes) of groups of whole reads, an N after each."""
    data = seqs.cast(pa.large_string()).cast(pa.large_binary()).fill_null(b"")
    offsets = np.frombuffer(data.buffers()[1], np.int64)[data.offset : data.offset + len(data) + 1]
    body = np.frombuffer(data.buffers()[2], np.uint8) if data.buffers()[2] is not None else np.zeros(0, np.uint8)
    first = 0
    while first < len(data):
        last = int(np.searchsorted(offsets, offsets[first] + pass_bases, "right")) - 1
        last = min(max(first + 1, last), len(data))
        sizes = np.diff(offsets[first : last + 1])
        at = np.concatenate([[0], np.cumsum(sizes + 1)])
        codes = np.full(at[-1], 4, np.uint8)
        row = np.repeat(np.arange(last - first), sizes + 1)
        place = np.arange(at[-1]) - at[row]
        codes[place < sizes[row]] = _CODE[body[offsets[first] : offsets[last]]]
        yield first, row, place, codes
        first = last


class Supermers:
    """Runs of k-mers with one destination: begin in ``codes``, bases, and task of each."""

    def __init__(self, begin: np.ndarray, n_bases: np.ndarray, task: np.ndarray):
        self.begin, self.n_bases, self.task = begin, n_bases, task


def find_supermers(codes: np.ndarray, spec: CountSpec) -> Supermers:
    """Cut a coded sequence into supermers.

    A k-mer's destination is its least m-mer score modulo the number of tasks; as the
    destination depends on the score alone, equal scores of different m-mers can't
    part equal k-mers. With a second hash it's another hash of the minimizer, of which
    the one with the least m-mer is taken. A supermer ends where the destination changes (or the score,
    if asked), at symbols that aren't bases, and at 65,535 bases.
    """
    valid = window_valid(codes, spec.k)
    if not len(valid) or not valid.any():
        none = np.zeros(0, np.int64)
        return Supermers(none, none, none)
    scores = mmer_scores(codes, spec)
    if spec.dest == "second_hash":
        words = mmer_words(codes, spec)
        ranks = lexical_ranks(scores, words)
        by_rank = np.empty(int(ranks.max()) + 1, np.int64)
        by_rank[ranks] = words
        least = block_minimum(ranks, spec.w)
        task = second_hash(by_rank[least]) % spec.s
    else:
        least = block_minimum(scores, spec.w)
        task = least % spec.s
    mark = least if spec.break_on == "minimizer" else task
    begins = valid.copy()
    begins[1:] &= ~valid[:-1] | (mark[1:] != mark[:-1])
    begin = np.flatnonzero(begins)
    ends = np.zeros(len(valid) + 1, bool)
    ends[1:-1] = valid[:-1] & (~valid[1:] | begins[1:])
    ends[-1] = valid[-1]
    n = np.flatnonzero(ends) - begin  # k-mers of each
    most = MAX_BASES - spec.k + 1
    if len(n) and n.max() > most:
        parts = -(-n // most)
        piece = np.arange(parts.sum()) - np.repeat(np.cumsum(parts) - parts, parts)
        begin = np.repeat(begin, parts) + piece * most
        n = np.minimum(np.repeat(n, parts) - piece * most, most)
    return Supermers(begin, n + spec.k - 1, task[begin])


def pack_runs(codes: np.ndarray, begin: np.ndarray, n_bases: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets): each run at 2 bits a base, first base in the high bits, beginning at a byte."""
    n_bytes = -(-n_bases // 4)
    offsets = np.concatenate([[0], np.cumsum(n_bytes)])
    if not len(begin):
        return np.zeros(0, np.uint8), offsets
    bases = np.concatenate([codes & 3, np.zeros(3, np.uint8)])
    four = (bases[:-3] << 6) | (bases[1:-2] << 4) | (bases[2:-1] << 2) | bases[3:]  # from each base on
    out = four[np.repeat(begin - 4 * offsets[:-1], n_bytes) + 4 * np.arange(offsets[-1])]
    out[offsets[1:] - 1] &= _LAST[n_bases & 3]
    return out, offsets


def unpack_runs(packed: np.ndarray, n_bases: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(codes, begins): the runs one after another, a 4 after each."""
    n_bytes = -(-n_bases // 4)
    quads = np.empty((len(packed), 4), np.uint8)
    for i in range(4):
        quads[:, i] = (packed >> (6 - 2 * i)) & 3
    begins = np.concatenate([[0], np.cumsum(n_bases + 1)])
    codes = np.full(begins[-1], 4, np.uint8)
    run = np.repeat(np.arange(len(n_bases)), 4 * n_bytes)
    place = np.arange(4 * n_bytes.sum()) - np.repeat(4 * (np.cumsum(n_bytes) - n_bytes), 4 * n_bytes)
    real = place < n_bases[run]
    codes[begins[run[real]] + place[real]] = quads.ravel()[real]
    return codes, begins[:-1]


def run_starts(packed: np.ndarray, n_bases: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(run, place in the run, bit in ``packed``) of each k-mer of packed runs, one run after another."""
    n = n_bases - k + 1
    n_bytes = -(-n_bases // 4)
    before = np.cumsum(n) - n
    run = np.repeat(np.arange(len(n)), n)
    place = np.arange(len(run)) - before[run]
    return run, place, 8 * (np.cumsum(n_bytes) - n_bytes)[run] + 2 * place


def run_kmers(packed: np.ndarray, n_bases: np.ndarray, k: int, canonical: bool = False, bits: np.ndarray | None = None) -> list[np.ndarray]:
    """Packed words of the k-mers of packed runs, each read from the bytes that it lies in: work for each k-mer, not for each base."""
    if not len(n_bases):
        return [np.zeros(0, np.int64)] * (1 if k <= ONE_WORD else 2)
    if canonical:
        return valid_kmers(unpack_runs(packed, n_bases)[0], k, True)
    bits = run_starts(packed, n_bases, k)[2] if bits is None else bits
    padded = np.concatenate([packed, np.zeros(24, np.uint8)])
    n = len(padded) - 8
    eight = np.zeros(n, np.uint64)  # the eight bytes from each byte on
    for i in range(8):
        eight <<= np.uint64(8)
        eight |= padded[i : i + n]

    def words(skip: int, length: int) -> np.ndarray:
        at = bits + 2 * skip
        byte, shift = at >> 3, (at & 7).astype(np.uint64)
        word = eight[byte] << shift
        word |= padded[byte + 8] >> (np.uint64(8) - shift)
        word >>= np.uint64(64 - 2 * length)
        return word.view(np.int64)

    return [words(0, k)] if k <= ONE_WORD else [words(0, k - ONE_WORD), words(k - ONE_WORD, ONE_WORD)]


def valid_kmers(codes: np.ndarray, k: int, canonical: bool = False) -> list[np.ndarray]:
    """Packed words of the k-mers without a 4."""
    ok = window_valid(codes, k)
    return [w[ok] for w in kmer_words(codes, k, canonical)]


#: Elements of a bucket that is sorted by comparison; elements that the exchange in place moves at once; bits of a digit.
BUCKET, MOVED, DIGIT_BITS = 1 << 17, 1 << 14, 11


def _top_bit(words: list[np.ndarray], bits: int | None) -> int:
    """Bits that any key has, of all its words together."""
    if bits is not None:
        return bits
    high = int(words[0].max(initial=0)).bit_length()
    return high if len(words) == 1 else high + 2 * ONE_WORD if high else int(words[1].max(initial=0)).bit_length()


def _digit(words: list[np.ndarray], shift: int, bits: int) -> np.ndarray:
    """``bits`` bits of each key from bit ``shift`` on; a digit doesn't run over the border of two words."""
    low = 2 * ONE_WORD
    word, shift = (words[0], shift) if len(words) == 1 else (words[0], shift - low) if shift >= low else (words[1], shift)
    return ((word >> shift) & ((1 << bits) - 1)).astype(np.uint16)


def _digit_below(words: list[np.ndarray], top: int, bits: int) -> tuple[int, int]:
    """(shift, bits) of the digit that ends below bit ``top``."""
    floor = 2 * ONE_WORD if len(words) == 2 and top > 2 * ONE_WORD else 0
    return max(floor, top - bits), min(bits, top - max(floor, top - bits))


def _sorted_bucket(words: list[np.ndarray], weights: np.ndarray | None) -> None:
    """Sort a small bucket where it lies."""
    if len(words) == 1 and weights is None:
        words[0].sort()
        return
    order = np.lexsort(words[::-1]) if len(words) > 1 else np.argsort(words[0], kind="stable")
    for x in (*words, *([] if weights is None else [weights])):
        x[:] = x[order]


def aux_radix(words: list[np.ndarray], weights: np.ndarray | None = None, top: int | None = None) -> tuple[list[np.ndarray], np.ndarray | None]:
    """Keys in order, in other arrays: digits from the highest down, each dealing its bucket into a second array."""
    top = _top_bit(words, top)
    if len(words[0]) <= BUCKET or not top:
        words, weights = [w.copy() for w in words], None if weights is None else weights.copy()
        if top:
            _sorted_bucket(words, weights)
        return words, weights
    shift, bits = _digit_below(words, top, DIGIT_BITS)
    digit = _digit(words, shift, bits)
    ends = np.cumsum(np.bincount(digit, minlength=1 << bits))
    order = np.argsort(digit, kind="stable")  # 16-bit keys: numpy counts and deals them
    words, weights = [w[order] for w in words], None if weights is None else weights[order]
    begin = 0
    for end in ends[np.diff(ends, prepend=0) > 0].tolist():
        part = slice(begin, end)
        if end - begin <= BUCKET:
            _sorted_bucket([w[part] for w in words], None if weights is None else weights[part])
        elif shift:
            inner, inner_weights = aux_radix([w[part] for w in words], None if weights is None else weights[part], shift)
            for w, x in zip(words, inner, strict=True):
                w[part] = x
            if weights is not None:
                weights[part] = inner_weights
        begin = end
    return words, weights


def inplace_radix(words: list[np.ndarray], weights: np.ndarray | None = None, top: int | None = None) -> None:
    """Sort keys where they lie: bits from the highest down; a bit's zeros and ones change places through a small buffer."""
    todo = [(0, len(words[0]), _top_bit(words, top))]
    arrays = [*words, *([] if weights is None else [weights])]
    while todo:
        begin, end, top = todo.pop()
        if not top or end - begin < 2:
            continue
        if end - begin <= BUCKET:
            _sorted_bucket([w[begin:end] for w in words], None if weights is None else weights[begin:end])
            continue
        middle = _exchanged(words, arrays, begin, end, top - 1)
        todo += [(begin, middle, top - 1), (middle, end, top - 1)]


def _exchanged(words: list[np.ndarray], arrays: list[np.ndarray], begin: int, end: int, bit: int) -> int:
    """Put the keys of [begin, end) without a bit before those with it; where the latter begin."""
    lo, hi = begin, end
    ones, zeros = np.zeros(0, np.int64), np.zeros(0, np.int64)  # places on the wrong side, of the blocks in hand
    while True:
        if not len(ones) and lo < hi:
            stop = min(hi, lo + MOVED)
            ones = lo + np.flatnonzero(_digit([w[lo:stop] for w in words], bit, 1))
            lo = stop
        if not len(zeros) and lo < hi:
            stop = max(lo, hi - MOVED)
            zeros = stop + np.flatnonzero(_digit([w[stop:hi] for w in words], bit, 1) == 0)[::-1]
            hi = stop
        n = min(len(ones), len(zeros))
        for x in arrays:
            x[ones[:n]], x[zeros[:n]] = x[zeros[:n]], x[ones[:n]]
        ones, zeros = ones[n:], zeros[n:]
        if lo >= hi and (not len(ones) or not len(zeros)):
            break
    # what one side has left over lies within one block: it's parted by itself
    if len(ones):
        first, last = int(ones[0]), lo
    elif len(zeros):
        first, last = hi, int(zeros[0]) + 1
    else:
        return lo
    one = _digit([w[first:last] for w in words], bit, 1) > 0
    order = np.concatenate([np.flatnonzero(~one), np.flatnonzero(one)])
    for x in arrays:
        x[first:last] = x[first:last][order]
    return first + int((~one).sum())


SORTS = ("inplace", "aux_radix")


def count_runs(words: list[np.ndarray], weights: np.ndarray | None = None, method: str = "aux_radix") -> tuple[list[np.ndarray], np.ndarray]:
    """Different keys and their (weighted) numbers, by sorting and one scan over equal runs.

    aux_radix: by digits into second arrays. inplace: by bits within the arrays, which
    must be the caller's to change. For one word or two, with weights or without.
    """
    if not len(words[0]):
        return words, np.zeros(0, np.int64)
    if method == "inplace":
        inplace_radix(words, weights)
    elif method == "aux_radix":
        words, weights = aux_radix(words, weights)
    else:
        raise ValueError(f"unknown sort {method}")
    fresh = np.ones(len(words[0]), bool)
    fresh[1:] = np.any([w[1:] != w[:-1] for w in words], axis=0)
    heads = np.flatnonzero(fresh)
    n = np.diff(np.append(heads, len(fresh))) if weights is None else np.add.reduceat(weights, heads)
    return [w[heads] for w in words], n.astype(np.int64)
