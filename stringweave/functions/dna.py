"""DNA as Column functions: all of them stay inside code generation."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

# Hexadecimal digits to bases, two bases a byte.
HEX, BASES = "0123456789ABCDEF", "ACGTACGTACGTACGT"


def _c(c) -> Column:
    return F.col(c) if isinstance(c, str) else c


def hex2(text) -> Column:
    """Text as DNA, a base for each hexadecimal digit of its bytes."""
    return F.translate(F.hex(_c(text).cast("binary")), HEX, BASES)


def word16(text) -> Column:
    """Text as DNA, sixteen bases of digest for each blank-separated word."""
    word = lambda w: F.translate(F.upper(F.substring(F.md5(w.cast("binary")), 1, 16)), HEX, BASES)
    return F.array_join(F.transform(F.split(_c(text), " "), word), "")


def revcomp(seq) -> Column:
    """The other strand, read in its own direction."""
    return F.reverse(F.translate(_c(seq), "ACGT", "TGCA"))


def oslice(seq, lo, hi, rev) -> Column:
    """Bases ``lo`` to ``hi``, both included, or their reverse complement; empty when ``hi`` is below ``lo``."""
    part = F.substring(_c(seq), _c(lo) + 1, F.greatest(F.lit(0), _c(hi) - _c(lo) + 1))
    return F.when(_c(rev), revcomp(part)).otherwise(part)


def canonical(kmer) -> Column:
    """The smaller of a k-mer and its reverse complement."""
    return F.least(_c(kmer), revcomp(kmer))


def pack(kmer) -> Column:
    """A k-mer of up to 31 bases as a long, two bits a base; its order is the order of the strings."""
    digits = F.translate(_c(kmer), "ACGT", "0123")
    return F.conv(digits, 4, 10).cast("long")


def unpack(code, k: int) -> Column:
    """The k-mer of a packed code."""
    return F.translate(F.lpad(F.conv(_c(code).cast("string"), 10, 4), k, "0"), "0123", "ACGT")


def base_at(seq, i) -> Column:
    return F.substring(_c(seq), _c(i) + 1, F.lit(1))


def gc_content(seq) -> Column:
    """Share of G and C; null for an empty sequence."""
    return F.try_divide(F.length(F.regexp_replace(_c(seq), "[^GC]", "")), F.length(_c(seq)))


def hamming(a, b) -> Column:
    """Positions at which two sequences of one length differ."""
    pairs = F.zip_with(F.split(_c(a), ""), F.split(_c(b), ""), lambda x, y: F.when(x == y, 0).otherwise(1))
    return F.aggregate(pairs, F.lit(0), lambda s, x: s + x)
