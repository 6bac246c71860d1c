"""Where tables, graphs and matrices go and come from."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stringweave.sources.reads import read_fasta, write_fasta

FORMATS = ["csv", "fasta", "json", "orc", "parquet"]
GENOME = "chrom long, seq string"


def save(genomes: DataFrame, path: str, kind: str) -> str:
    """Write ``(chrom, seq)`` as ``kind`` and return the path."""
    if kind == "fasta":
        write_fasta(genomes, path, "chrom", "seq")
    else:
        genomes.write.format(kind).save(path)
    return path


def load(spark: SparkSession, path: str, kind: str) -> DataFrame:
    """Read what ``save`` wrote; the schema is given, never inferred."""
    if kind == "fasta":
        return read_fasta(spark, path).select(F.col("name").cast("long").alias("chrom"), "seq")
    return spark.read.schema(GENOME).format(kind).load(path)


def read_fastq(spark: SparkSession, path: str) -> DataFrame:
    """``(name, seq, quality)`` of four-line records.

    Every record is one text row cut at the line break before ``@``; a quality line that begins with ``@``
    would be cut too, so pieces that do not have four lines raise an error.
    """
    raw = spark.read.option("lineSep", "\n@").text(path).where("length(trim(value)) > 0")
    lines = F.split(F.regexp_replace("value", "^@|\n$", ""), "\n")
    rec = raw.select(F.when(F.size(lines) == 4, lines).otherwise(F.raise_error(F.lit("not a four-line record")).cast("array<string>")).alias("x"))
    return rec.select(F.col("x")[0].alias("name"), F.col("x")[1].alias("seq"), F.col("x")[3].alias("quality"))


def write_triples(a: DataFrame, path: str) -> None:
    """A matrix as coordinate text: row, column and value, counted from 1."""
    a.select(F.concat_ws(" ", (F.col("row") + 1).cast("string"), (F.col("col") + 1).cast("string"), F.col("val").cast("string")).alias("value")).write.text(path)


def read_triples(spark: SparkSession, path: str) -> DataFrame:
    """``(row, col, val)`` of coordinate text; comment lines begin with ``%``."""
    p = F.split("value", " ")
    raw = spark.read.text(path).where("value not like '!%%' escape '!'")
    return raw.select((p[0].cast("long") - 1).alias("row"), (p[1].cast("long") - 1).alias("col"), p[2].cast("double").alias("val"))


def write_graph(edges: DataFrame, reads: DataFrame, path: str) -> None:
    """A string graph as text: a line ``S id length`` per read and ``L u end v end overlap`` per edge, ``u < v``."""
    s = reads.select(F.concat_ws("\t", F.lit("S"), F.col("read_id").cast("string"), F.length("seq").cast("string")).alias("value"))
    e = edges.where("u < v").select(F.concat_ws("\t", F.lit("L"), *[F.col(c).cast("string") for c in ("u", "u_end", "v", "v_end", "score")]).alias("value"))
    s.unionByName(e).write.text(path)


def by_owner(df: DataFrame, path: str) -> str:
    """A table in a folder per owner, so that one owner's rows are read alone."""
    df.repartition("owner").write.partitionBy("owner").parquet(path)
    return path
