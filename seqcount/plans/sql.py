"""The same results in plain SQL, for checking: reads, k-mers, minimizers and supermers as one query."""

from __future__ import annotations

from seqcount.functions.alphabet import FOLD_FROM, FOLD_TO
from seqcount.functions.scores import PRIME, _coefficients
from seqcount.sources.reads import DRAW_COPY, DRAW_MIX, DRAW_PLACE, DRAW_PRIME, DRAW_READ, EVENT_BASES
from seqcount.spec import CountSpec

_WORD = 4294967295
#: Rows that a long read is cut into before its windows, so that cuts of a string stay short.
_PIECE = 1000


def fold(text: str) -> str:
    return f"regexp_replace(translate(lower({text}), '{FOLD_FROM}', '{FOLD_TO}'), '[^ACGT]', 'N', 'g')"


def reads(view: str = "docs") -> str:
    """A query for (read_id, seq)."""
    docs = f"SELECT doc_id AS read_id, {fold('text')} AS seq FROM documents"
    if view == "docs":
        return docs
    if view == "heavy":
        return f"{docs} UNION ALL SELECT -1, repeat('ACTTG', 20000)"
    if view == "cov":
        start = f"(read_id % {DRAW_PRIME}) * {DRAW_READ} + copy * {DRAW_COPY}"
        mixed = f"((((start % {DRAW_PRIME}) + i * {DRAW_PLACE}) % {DRAW_PRIME}) * {DRAW_MIX}) % {DRAW_PRIME}"
        drawn = f"(({mixed}) * ({mixed}) + ({mixed}) * {DRAW_READ} + i) % {DRAW_PRIME}"
        base = f"CASE WHEN {drawn} < {int(0.005 * DRAW_PRIME)} THEN substr('ACGT', CAST(({drawn}) % 4 + 1 AS BIGINT), 1) ELSE x END"
        copies = f"SELECT read_id, copy, {start} AS start, seq FROM ({docs}), (SELECT unnest(range(0, 5)) AS copy)"
        return f"SELECT read_id * 5 + copy AS read_id, array_to_string(list_transform(string_split(seq, ''), lambda x, i: {base}), '') AS seq FROM ({copies})"
    if view == "pages":
        return f"SELECT page_id AS read_id, {fold('html')} AS seq FROM pages"
    if view == "small":
        return f"SELECT item_id AS read_id, {fold('text')} AS seq FROM benchmark"
    if view == "events":
        base = " ".join(f"WHEN '{k}' THEN '{v}'" for k, v in EVENT_BASES.items())
        return f"SELECT user_id AS read_id, string_agg(CASE event_type {base} ELSE 'N' END, '' ORDER BY ts, event_id) AS seq FROM events GROUP BY user_id"
    raise ValueError(view)


def kmers(k: int, source: str | None = None, extra: str = "") -> str:
    """A query for (read_id, pos, kmer), with columns of the reads in ``extra``, each followed by a comma."""
    return f"""
SELECT * FROM (
  SELECT read_id, {extra} off + i - 1 AS pos, substr(piece, CAST(i AS BIGINT), {k}) AS kmer FROM (
    SELECT read_id, {extra} off, piece, unnest(range(1, least({_PIECE}, length(piece) - {k - 1}) + 1)) AS i FROM (
      SELECT read_id, {extra} off, substr(seq, off + 1, {_PIECE + k - 1}) AS piece FROM (
        SELECT read_id, {extra} seq, unnest(range(0, length(seq) - {k - 1}, {_PIECE})) AS off FROM ({source or reads()}) WHERE length(seq) >= {k}))))
WHERE kmer NOT LIKE '%N%'"""


def counts(k: int, source: str | None = None) -> str:
    return f"SELECT kmer, count(*) AS cnt FROM ({kmers(k, source)}) GROUP BY kmer"


def spectrum(counted: str) -> str:
    return f"SELECT cnt, count(*) AS n_kmers FROM ({counted}) GROUP BY cnt"


def packed(column: str) -> str:
    """2 bits a base, as a number."""
    bits = f"replace(replace(replace(replace({column}, 'A', '00'), 'C', '01'), 'G', '10'), 'T', '11')"
    return f"CAST(CAST({bits} AS BIT) AS BIGINT)"


def _murmur(source: str, keep: str) -> str:
    """A query with ``score``, 32-bit Murmur3 of the column mmer, from one with it."""
    step = f"SELECT {keep}, mmer, CAST(42 AS UBIGINT) AS h, CAST(mmer & {_WORD} AS UBIGINT) AS x FROM ({source})"
    for _ in range(2):
        step = f"SELECT {keep}, mmer, h, (x * 3432918353) & {_WORD} AS x FROM ({step})"
        step = f"SELECT {keep}, mmer, h, ((((x << 15) | (x >> 17)) & {_WORD}) * 461845907) & {_WORD} AS x FROM ({step})"
        step = f"SELECT {keep}, mmer, xor(h, x) AS h FROM ({step})"
        step = f"SELECT {keep}, mmer, ((((h << 13) | (h >> 19)) & {_WORD}) * 5 + 3864292196) & {_WORD} AS h, CAST(mmer >> 32 AS UBIGINT) AS x FROM ({step})"
    step = f"SELECT {keep}, xor(h, 8) AS h FROM ({step})"
    step = f"SELECT {keep}, (xor(h, h >> 16) * 2246822507) & {_WORD} AS h FROM ({step})"
    step = f"SELECT {keep}, (xor(h, h >> 13) * 3266489909) & {_WORD} AS h FROM ({step})"
    return f"SELECT {keep}, CAST(xor(h, h >> 16) AS BIGINT) AS score FROM ({step})"


def mmer_scores(spec: CountSpec, source: str | None = None) -> str:
    """A query for (read_id, pos, mmer, score)."""
    m = spec.m
    base = f"SELECT read_id, pos, kmer AS word, {packed('kmer')} AS mmer FROM ({kmers(m, source)})"
    if spec.score == "murmur3":
        return _murmur(f"SELECT *, mmer AS code FROM ({base})", "read_id, pos, code")
    if spec.score == "lex":
        return f"SELECT read_id, pos, mmer AS code, mmer AS score FROM ({base})"
    if spec.score == "lex_mod":
        late = "substr(word, 1, 3) IN ('AAA', 'ACA') OR contains(substr(word, 2), 'AA')"
        return f"SELECT read_id, pos, mmer AS code, CASE WHEN {late} THEN mmer + {1 << (2 * m)} ELSE mmer END AS score FROM ({base})"
    if spec.score in ("arith", "universal"):
        a, b = _coefficients(spec.score, spec.seed)
        return f"SELECT read_id, pos, mmer AS code, CAST(({a} * CAST(mmer % {PRIME} AS HUGEINT) + {b}) % {PRIME} AS BIGINT) AS score FROM ({base})"
    raise ValueError(spec.score)


def minimizers(spec: CountSpec, source: str | None = None) -> str:
    """A query for (read_id, pos, score, task) of every k-mer."""
    frame = f"PARTITION BY read_id ORDER BY pos RANGE BETWEEN CURRENT ROW AND {spec.w - 1} FOLLOWING"
    inner = f"SELECT read_id, pos, min(score) OVER w AS score, count(*) OVER w AS seen FROM ({mmer_scores(spec, source)}) WINDOW w AS ({frame})"
    return f"SELECT read_id, pos, score, score % {spec.s} AS task FROM ({inner}) WHERE seen = {spec.w}"


def supermers(spec: CountSpec, source: str | None = None) -> str:
    """A query for (read_id, task, start, n_bases)."""
    mark = "task" if spec.break_on == "task" else "score"
    fresh = f"CASE WHEN lag(pos) OVER a = pos - 1 AND lag({mark}) OVER a = {mark} THEN 0 ELSE 1 END"
    marked = f"SELECT read_id, pos, task, {fresh} AS fresh FROM ({minimizers(spec, source)}) WINDOW a AS (PARTITION BY read_id ORDER BY pos)"
    island = f"SELECT read_id, pos, task, sum(fresh) OVER (PARTITION BY read_id ORDER BY pos) AS island FROM ({marked})"
    return f"SELECT read_id, min(task) AS task, min(pos) AS start, count(*) + {spec.k - 1} AS n_bases FROM ({island}) GROUP BY read_id, island"


def occurrences(spec: CountSpec, source: str | None = None) -> str:
    """A query for (kmer, cnt, read_id, pos) of k-mers in range."""
    inner = f"SELECT kmer, read_id, pos, count(*) OVER (PARTITION BY kmer) AS cnt FROM ({kmers(spec.k, source)})"
    return f"SELECT * FROM ({inner}) WHERE cnt BETWEEN {spec.lo} AND {spec.hi}"
