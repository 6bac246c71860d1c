"""What SQL users call by name: k-mer codes, x-drop extension, k-mers as rows, consensus."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, BooleanType, IntegerType, LongType, StringType, StructField, StructType

from stringweave.operators.overlap import packed, xdrop_many

#: Types as objects: a string needs a session, and this module is imported before there is one.
EXTENSION = StructType([StructField(c, IntegerType()) for c in ("score", "u_bases", "v_bases")])
KMER_ROW = StructType([StructField("pos", IntegerType()), StructField("kmer", StringType()), StructField("rev", BooleanType())])


@F.pandas_udf(ArrayType(LongType()))
def kmer_pack(seq: pd.Series, k: pd.Series) -> pd.Series:
    """Packed forward k-mers of each sequence; null stays null, a sequence below k gives none."""
    return pd.Series([None if s is None else packed(s.encode(), int(n))[0].tolist() if len(s) >= n else [] for s, n in zip(seq, k)])


@F.pandas_udf(EXTENSION)
def xdrop_extend(u: pd.Series, v: pd.Series, x: pd.Series) -> pd.DataFrame:
    """Gapped extension of two sequences from their beginnings; null counts as empty."""
    out = pd.DataFrame(0, index=u.index, columns=["score", "u_bases", "v_bases"])
    for bound in x.unique():
        at = (x == bound).to_numpy()
        out.loc[at] = xdrop_many([(s or "").encode() for s in u[at]], [(s or "").encode() for s in v[at]], int(bound))
    return out


@F.pandas_udf(StringType())
def consensus(base: pd.Series, weight: pd.Series) -> str:
    """The base of the largest weight in a column of a pile; ties go to the first letter."""
    sums = weight.groupby(base).sum()
    return None if sums.empty else min(sums[sums == sums.max()].index)


class KmersOf:
    """Rows ``(pos, kmer, rev)`` of a sequence: the smaller strand's k-mers."""

    def eval(self, seq: str, k: int):
        if seq is None:
            return
        flip = str.maketrans("ACGT", "TGCA")
        for p in range(len(seq) - k + 1):
            w = seq[p : p + k]
            b = w[::-1].translate(flip)
            yield p, min(w, b), b < w


kmers_of = F.udtf(KmersOf, returnType=KMER_ROW)


def register(spark: SparkSession) -> None:
    """Make all of them known to SQL."""
    spark.udf.register("kmer_pack", kmer_pack)
    spark.udf.register("xdrop_extend", xdrop_extend)
    spark.udf.register("consensus", consensus)
    spark.udtf.register("kmers_of", kmers_of)


def pile(reads: DataFrame) -> DataFrame:
    """``(chrom, at, base)`` of reads laid where their truth says; ``reads`` as ``shotgun`` returns them."""
    from stringweave.functions.dna import revcomp

    fore = F.when(F.col("rev"), revcomp("seq")).otherwise(F.col("seq"))
    return reads.select("chrom", "start", F.posexplode(F.split(fore, "")).alias("i", "base")).where("base <> ''").select("chrom", (F.col("start") + F.col("i")).alias("at"), "base")


def polish(piled: DataFrame, weight: Column | None = None) -> DataFrame:
    """``(chrom, at, base, depth)``: the majority base of every column of a pile, without Python."""
    n = piled.groupBy("chrom", "at", "base").agg(F.sum(F.lit(1) if weight is None else weight).alias("w"))
    best = F.min(F.struct((-F.col("w")).alias("w"), "base"))
    return n.groupBy("chrom", "at").agg(best["base"].alias("base"), F.sum("w").alias("depth"))
