"""The four-letter alphabet: folding of text, packing into words, complements, as columns."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from seqcount.spec import ONE_WORD

#: The character fold that makes reads of text, one character to one base.
FOLD_FROM = "abcdefghijklmnopqrstuvwxyz .,\n0123456789éèêçóñáíúäöüßà"
FOLD_TO = "GGGCCCATCGGTAGTTGGATAAGGATACTGAAAACATCTACCCATCCCCTAATC"
#: Bases of a hexadecimal digit, for the lossless encoding: four bases to a byte.
HEX_BASES = {format(d, "x"): "ACGT"[d >> 2] + "ACGT"[d & 3] for d in range(16)}


def fold_text(text: Column) -> Column:
    """Text as bases; what the fold doesn't know becomes N."""
    return F.regexp_replace(F.translate(F.lower(text), FOLD_FROM, FOLD_TO), "[^ACGT]", "N")


def text_to_bases(text: Column) -> Column:
    """Text without loss: two bases for each hexadecimal digit of its UTF-8 bytes."""
    out = F.lower(F.hex(F.encode(text, "UTF-8")))
    marked = F.translate(out, "abcdef", "ghijkl")  # digits that aren't bases, so no replacement is replaced again
    for digit, bases in HEX_BASES.items():
        marked = F.replace(marked, F.lit(chr(ord(digit) + 6) if digit.isalpha() else digit), F.lit(bases))
    return marked


def bases_to_text(bases: Column) -> Column:
    """Inverse of ``text_to_bases``."""
    # a lambda evaluates what it captures for each element, so it only gets the pair itself
    digits = F.regexp_extract_all(F.translate(bases, "ACGT", "0123"), F.lit("(..)"), 1)
    pairs = F.transform(digits, lambda pair: F.conv(pair, 4, 16))
    return F.when(F.length(bases) == 0, F.lit("")).otherwise(F.decode(F.unhex(F.array_join(pairs, "")), "UTF-8"))


def pack(kmer: Column, k: int) -> Column:
    """2 bits a base, first base most significant: a BIGINT up to 31 bases, else STRUCT<hi, lo> with 31 in lo."""
    digits = F.translate(kmer, "ACGT", "0123")
    word = lambda d: F.conv(d, 4, 10).cast("long")
    if k <= ONE_WORD:
        return word(digits)
    cut = k - ONE_WORD
    return F.struct(word(F.substring(digits, 1, cut)).alias("hi"), word(F.substring(digits, cut + 1, ONE_WORD)).alias("lo"))


def unpack(packed: Column, k: int) -> Column:
    """Inverse of ``pack``."""
    word = lambda c, n: F.translate(F.lpad(F.conv(c.cast("string"), 10, 4), n, "0"), "0123", "ACGT")
    if k <= ONE_WORD:
        return word(packed, k)
    return F.concat(word(packed.getField("hi"), k - ONE_WORD), word(packed.getField("lo"), ONE_WORD))


def revcomp(seq: Column) -> Column:
    return F.reverse(F.translate(seq, "ACGT", "TGCA"))


def canonical(kmer: Column) -> Column:
    """The lesser of a k-mer and its reverse complement."""
    return F.least(kmer, revcomp(kmer))


def gc(seq: Column) -> Column:
    """Share of G and C among the bases; null without any."""
    bases = F.length(F.regexp_replace(seq, "[^ACGT]", ""))
    return F.when(bases > 0, F.length(F.regexp_replace(seq, "[^GC]", "")) / bases)


def low_complexity(mmer: Column, m: int) -> Column:
    """Whether an m-mer is one that the modified lexical order puts last; see ``scores.lex_mod``."""
    head = F.shiftright(mmer, 2 * (m - 3)) if m >= 3 else F.lit(-1)
    pairs = [F.shiftright(mmer, 2 * i).bitwiseAND(F.lit(15)) == 0 for i in range(m - 2)]
    out = (head == 0) | (head == 4)
    for p in pairs:
        out = out | p
    return out
