"""Byte-level BPE encoding and decoding as a tree reduction over halves of each text."""

from __future__ import annotations

import base64
import hashlib

import numpy as np
import pyarrow as pa
import public_tokenizers
import regex
import tiktoken
from pyspark.sql import DataFrame
from pyspark.sql.types import ArrayType, IntegerType, LongType, StructField, StructType

from seqcount.llm.common import fresh

VOCABULARY = "byte_bpe_50k.tiktoken"
#: Characters, or tokens when decoding, of a leaf; bytes of a leaf within one unbroken piece.
LEAF_CHARS, LEAF_BYTES = 96, 256
#: Longest run of characters without a seam that the library gets as a whole.
_RUN = 2048
#: A space after other text is the commonest seam; beyond so many characters another kind is sought.
_NEAR = 64
_coders: dict[str, "Coder"] = {}
#: The last character of a piece whatever follows: a character of another kind comes next, and no match of the
#: pattern runs over that, for only blanks before a word and an apostrophe before a letter do.
_SEAM = regex.compile(r"\p{L}(?=\P{L})|\p{N}(?=\P{N})|[^\s\p{L}\p{N}'](?=[\s\p{L}\p{N}])|'(?=[\s\p{N}])")
_PIECE = regex.compile(public_tokenizers.PATTERN)


class Coder:
    """Encoder and decoder of one vocabulary of ranks.

    Encoding is a monoid over pieces of the text: a node holds the tokens of its span
    as if that were a text of its own, and two neighbours join by encoding a window
    around their boundary afresh. Every text is halved down to leaves of ``leaf_chars``
    characters, wherever the halves fall. The splitting pattern always ends a match at
    a seam, and what it matches before and after a seam doesn't depend on the other
    side. So tokens left of the last seam before the boundary and right of the first
    seam after it are final; the window between them grows until it reaches seams, or
    the ends of the node. A window that is one long unbroken piece is encoded as a tree
    over its bytes in turn, see ``piece``. ``joins`` counts the joins of both trees.
    """

    def __init__(self, path: str, leaf_chars: int = LEAF_CHARS, leaf_bytes: int = LEAF_BYTES):
        with open(path, "rb") as f:
            ranks = {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, f)}
        self.encoding = tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
        self.bytes_of = [b""] * (max(ranks.values()) + 1)
        for token, rank in ranks.items():
            self.bytes_of[rank] = token
        self.size_of = [len(x) for x in self.bytes_of]
        self.leaf_chars, self.leaf_bytes = max(1, leaf_chars), max(1, leaf_bytes)
        self._plain = self.encoding._core_bpe.encode_ordinary
        self.joins = 0

    def encode(self, text: str) -> list[int]:
        return self._span(text, 0, len(text))

    def _span(self, text: str, lo: int, hi: int) -> list[int]:
        if hi - lo <= self.leaf_chars:
            return self._plain(text[lo:hi])
        cut = (lo + hi) // 2
        return self._join(text, lo, cut, hi, self._span(text, lo, cut), self._span(text, cut, hi))

    def _join(self, text: str, lo: int, cut: int, hi: int, left: list[int], right: list[int]) -> list[int]:
        """Tokens of [lo, hi) from those of its halves."""
        self.joins += 1
        begin, end = text.rfind(" ", lo, cut), text.find(" ", cut, hi)
        if end == cut and not text[cut - 1].isspace():  # the halves meet at a seam: nothing to encode afresh
            return left + right
        if begin <= lo or cut - begin > _NEAR or text[begin - 1].isspace():
            begin = self._seam_before(text, lo, cut)
        if end < 0 or end - cut > _NEAR or text[end - 1].isspace():
            end = self._seam_after(text, cut, hi)
        middle = self._plain(text[begin:end]) if end - begin <= _RUN else self._pieces(text[begin:end])
        size_of = self.size_of
        a, n = len(left), len(text[begin:cut].encode())
        while n > 0:
            a -= 1
            n -= size_of[left[a]]
        b, n = 0, len(text[cut:end].encode())
        while n > 0:
            n -= size_of[right[b]]
            b += 1
        return left[:a] + middle + right[b:]

    def _seam_before(self, text: str, lo: int, cut: int) -> int:
        reach = 16
        while True:
            found, near = None, max(lo, cut - reach)
            for found in _SEAM.finditer(text, near, cut):  # a seam shows only if the next character lies left of the cut too
                pass
            if found or near == lo:
                return found.end() if found else lo
            reach *= 2

    def _seam_after(self, text: str, cut: int, hi: int) -> int:
        reach = 16
        while True:
            near = min(hi, cut + reach)
            found = _SEAM.search(text, cut, near)
            if found or near == hi:
                return found.end() if found else hi
            reach *= 2

    def _pieces(self, text: str) -> list[int]:
        """Each match of the pattern by itself, as a tree."""
        out: list[int] = []
        for match in _PIECE.finditer(text):
            out += self.piece(match.group().encode())
        return out

    def piece(self, data: bytes) -> list[int]:
        """Merges of one piece: halves, then the tokens at the boundary afresh.

        Tokens are the merges of their bytes if and only if each pair of neighbours is
        (the merge order is by rank, so a token list fails at some neighbouring pair or
        nowhere). The window at the boundary takes in more tokens on a side until its
        outer token and the token beyond agree in this sense.
        """
        if len(data) <= self.leaf_bytes:
            return self.encoding._encode_single_piece(data)
        self.joins += 1
        cut = len(data) // 2
        left, right = self.piece(data[:cut]), self.piece(data[cut:])
        a, b = min(4, len(left)), min(4, len(right))
        while True:
            held = left[len(left) - a :] + right[:b]
            window = self.encoding._encode_single_piece(b"".join([self.bytes_of[t] for t in held]))
            low = a == len(left) or self._agree(left[len(left) - a - 1], window[0])
            high = b == len(right) or self._agree(window[-1], right[b])
            if low and high:
                return left[: len(left) - a] + window + right[b:]
            a = a if low else min(len(left), 2 * a)
            b = b if high else min(len(right), 2 * b)

    def _agree(self, one: int, two: int) -> bool:
        return self.encoding._encode_single_piece(self.bytes_of[one] + self.bytes_of[two]) == [one, two]

    def decode(self, tokens: list[int]) -> bytes:
        """Bytes of the halves, concatenated up the tree."""
        return self._decoded(tokens, 0, len(tokens))

    def _decoded(self, tokens: list[int], lo: int, hi: int) -> bytes:
        if hi - lo <= self.leaf_chars:
            table = self.bytes_of
            return b"".join([table[t] for t in tokens[lo:hi]])
        cut = (lo + hi) // 2
        return self._decoded(tokens, lo, cut) + self._decoded(tokens, cut, hi)


def coder(vocabulary: str = VOCABULARY) -> Coder:
    """The process's coder: it's read from the installed vocabulary once."""
    path = vocabulary if "/" in vocabulary else public_tokenizers.path(vocabulary)
    if path not in _coders:
        _coders[path] = Coder(path)
    return _coders[path]


def encoded_frame(docs: DataFrame, text_col: str = "text", vocabulary: str = VOCABULARY) -> DataFrame:
    """``docs`` with n_tokens and ids (array of int); names that the table has already get two underscores in front.

    A null text is encoded as the empty text, to no ids; equal rows give equal ids; an
    empty table gives no rows.
    """
    at = docs.columns.index(text_col)
    taken = {c.lower() for c in docs.columns}
    n_name, ids_name = (c if c not in taken else fresh(docs, c)[0] for c in ("n_tokens", "ids"))
    schema = StructType([*docs.schema.fields, StructField(n_name, LongType()), StructField(ids_name, ArrayType(IntegerType()))])

    def run(batches):
        c = coder(vocabulary)
        for batch in batches:
            for part in _pieces_of(batch):
                ids = [np.asarray(c.encode(t.as_py() or ""), np.int32) for t in part.column(at)]
                flat = np.concatenate(ids) if ids else np.zeros(0, np.int32)
                sizes = np.array([len(x) for x in ids], np.int64)
                lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(sizes)]), pa.int32()), pa.array(flat))
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(sizes), lists], names=schema.names)

    return docs.mapInArrow(run, schema)


def _pieces_of(batch: pa.RecordBatch, rows: int = 256):
    for first in range(0, batch.num_rows, rows):
        yield batch.slice(first, rows)


def token_digests(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", vocabulary: str = VOCABULARY) -> DataFrame:
    """Per row: the id, n_tokens, and SHA-256 of the ids and of the bytes decoded from them.

    A null text counts as empty: no tokens, and the digests of nothing. Null ids and
    repeated rows are kept as they are; an empty table gives no rows.
    """
    rows = docs.select(id_col, text_col)
    schema = StructType(docs.select(id_col).schema.fields).add("n_tokens", "long").add("ids_sha256", "string").add("decoded_sha256", "string")

    def run(batches):
        c = coder(vocabulary)
        for batch in batches:
            n, ids_sha, out_sha = [], [], []
            for t in batch.column(1):
                ids = c.encode(t.as_py() or "")
                n.append(len(ids))
                ids_sha.append(hashlib.sha256(np.asarray(ids, "<u4").tobytes()).hexdigest())
                out_sha.append(hashlib.sha256(c.decode(ids)).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(ids_sha, pa.string()), pa.array(out_sha, pa.string())], names=schema.names)

    return rows.mapInArrow(run, schema)


def token_lengths(docs: DataFrame, text_col: str = "text", vocabulary: str = VOCABULARY) -> DataFrame:
    """One column, n_tokens, of every row."""

    def run(batches):
        c = coder(vocabulary)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array([len(c.encode(t.as_py() or "")) for t in batch.column(0)], pa.int64())], names=["n_tokens"])

    return docs.select(text_col).mapInArrow(run, "n_tokens long")


def op7_bpe(spark, sf_dir: str) -> DataFrame:
    """Digests of every document's tokens; see ``token_digests`` for null and empty texts and repeated rows."""
    return token_digests(spark.read.parquet(f"{sf_dir}/documents.parquet"))
