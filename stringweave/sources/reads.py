"""Genomes and reads: encoded tables, shotgun reads with known truth, FASTA files."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from stringweave.functions.dna import hamming, hex2, revcomp, word16
from stringweave.measures import covered
from stringweave.session import Scratch


def genome(table: DataFrame, key: str, text: str, enc: str = "hex2") -> DataFrame:
    """``(chrom, seq, len)`` of a text table; a chromosome per row, null and empty texts left out."""
    made = (hex2 if enc == "hex2" else word16)(text)
    return table.where(F.length(text) > 0).select(F.col(key).cast("long").alias("chrom"), made.alias("seq")).withColumn("len", F.length("seq"))


def numbered(rows: DataFrame, order: list[str], name: str) -> DataFrame:
    """Rows with their rank in an order of all, from 0, as ``name``; rows of equal keys share no number.

    Rows are cut into ranges and ranked inside them; only the sizes of the ranges are summed in one place.
    """
    store = Scratch(rows.sparkSession, "numbers")
    cut = store.keep(rows.repartitionByRange(*order).withColumn("__range", F.spark_partition_id()))
    sizes = cut.groupBy("__range").agg(F.count("*").alias("__n"))
    before = sizes.select("__range", (F.sum("__n").over(Window.orderBy("__range")) - F.col("__n")).alias("__before"))
    rank = F.row_number().over(Window.partitionBy("__range").orderBy(*order)) - 1
    return cut.withColumn(name, rank).join(before, "__range").withColumn(name, F.col(name) + F.col("__before")).drop("__range", "__before")


def shotgun(genomes: DataFrame, length: int, stride: int, flip: bool = True, error: float = 0.0) -> DataFrame:
    """Windows of a genome as reads with their truth.

    A window starts at every multiple of ``stride`` that leaves ``length`` bases, and one ends flush
    with the chromosome.  The strand is the lowest bit of the first digit of md5(chrom:start).
    ``error`` substitutes bases where a digest of read and position says so.
    Returns ``(read_id, seq, len, chrom, start, end, rev)``; ids number chromosome and start.
    """
    if error:
        return _damaged(genomes, length, stride, flip, error)
    last = F.greatest(F.lit(0), F.col("len") - length)
    starts = F.array_distinct(F.concat(F.sequence(F.lit(0), last, F.lit(stride)), F.array(last)))
    cut = genomes.select("chrom", "len", "seq", F.explode(starts).alias("start")).withColumn("end", F.least(F.col("len"), F.col("start") + length))
    rev = (F.conv(F.substring(F.md5(F.concat_ws(":", "chrom", "start").cast("binary")), 1, 1), 16, 10).cast("int") % 2 == 1) if flip else F.lit(False)
    piece = F.substring("seq", F.col("start") + 1, F.col("end") - F.col("start"))
    reads = cut.select((F.col("chrom") * 1_000_000_000 + F.col("start")).alias("read_id"), "chrom", "start", "end", rev.alias("rev"), piece.alias("seq"))
    return reads.withColumn("seq", F.when(F.col("rev"), revcomp("seq")).otherwise(F.col("seq"))).select("read_id", "seq", F.length("seq").alias("len"), "chrom", "start", "end", "rev")


_P1, _P2, _P3, _P4, _P5 = (np.uint64(p) for p in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))
_NEXT, _OTHER = np.arange(256, dtype=np.uint8), np.arange(256, dtype=np.uint8)
_NEXT[list(b"ACGT")], _OTHER[list(b"ACGT")] = list(b"CGTA"), list(b"TGCA")


def _last_mix(h: np.ndarray, spare: np.ndarray) -> None:
    """All of the last mixing but its last step, in place."""
    for bits, prime in ((33, _P2), (29, _P3)):
        np.right_shift(h, np.uint64(bits), out=spare)
        h ^= spare
        h *= prime


def _low_digests(reads: np.ndarray, places: np.ndarray, room: np.ndarray) -> np.ndarray:
    """The low 16 bits of ``xxhash64(read, place)`` as Spark has it, a row for each read; ``room`` holds two numbers for each."""
    one = reads.astype(np.uint64) * _P2
    one = ((one << np.uint64(31)) | (one >> np.uint64(33))) * _P1 ^ (np.uint64(42) + _P5 + np.uint64(8))
    one = ((one << np.uint64(27)) | (one >> np.uint64(37))) * _P1 + _P4
    _last_mix(one, np.empty_like(one))
    one ^= one >> np.uint64(32)
    n = len(reads) * len(places)
    h, spare = (r[:n].reshape(len(reads), len(places)) for r in room)
    np.bitwise_xor((one + (_P5 + np.uint64(4)))[:, None], places.astype(np.uint64) * _P1, out=h)
    np.right_shift(h, np.uint64(41), out=spare)
    h <<= np.uint64(23)
    h |= spare
    h *= _P2
    h += _P3
    _last_mix(h, spare)
    parts = h.reshape(-1).view("<u2")
    return parts[0::4] ^ parts[2::4]


def _damaged(genomes: DataFrame, length: int, stride: int, flip: bool, error: float) -> DataFrame:
    """Reads of ``shotgun`` with errors: every base is replaced by the next one where a digest of read and place falls below ``error``.

    The digests of many bases are computed at once, and only genomes are moved to Python.
    """
    bound, most = int(error * 65536), 1 << 17  # bases at once

    def of(chrom: int, text: bytes):
        seq = np.frombuffer(text, np.uint8)
        size, last = min(length, len(seq)), max(0, len(seq) - length)
        starts = np.arange(0, last + 1, stride, dtype=np.int64)
        starts = starts if starts[-1] == last else np.append(starts, last)
        windows = np.lib.stride_tricks.sliding_window_view(seq, size) if size else np.zeros((1, 0), np.uint8)
        step, places = max(1, most // max(1, size)), np.arange(size)
        room = np.empty((2, step * size), np.uint64)
        for a in range(0, len(starts), step):
            at = starts[a : a + step]
            ids = at + chrom * 1_000_000_000
            got = windows[at]
            hit = np.flatnonzero(_low_digests(ids, places, room) < bound)
            flat = got.reshape(-1)
            flat[hit] = _NEXT[flat[hit]]
            rev = np.array([hashlib.md5(b"%d:%d" % (chrom, s)).digest()[0] >> 4 & 1 for s in at.tolist()] if flip else np.zeros(len(at)), bool)
            got[rev] = _OTHER[got[rev][:, ::-1]]
            text = pa.Array.from_buffers(pa.string(), len(at), [None, pa.py_buffer(np.arange(0, len(at) + 1, dtype=np.int32) * np.int32(size)), pa.py_buffer(got)])
            yield pa.RecordBatch.from_arrays([pa.array(ids), text, pa.array(np.full(len(at), size, np.int32)), pa.array(np.full(len(at), chrom, np.int64)), pa.array(at.astype(np.int32)), pa.array((at + size).astype(np.int32)), pa.array(rev)], names=["read_id", "seq", "len", "chrom", "start", "end", "rev"])

    def work(batches):
        held, n = [], 0
        for batch in batches:
            for chrom, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                for made in of(chrom, text.as_py().encode()):
                    held.append(made)
                    n += made.num_rows
                    if n >= 8192:
                        yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]
                        held, n = [], 0
        if n:
            yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]

    kept = genomes.where("chrom is not null and seq is not null").select("chrom", "seq")
    return kept.mapInArrow(work, 'read_id long, seq string, len int, chrom long, start int, `end` int, rev boolean')


def profile(reads: DataFrame, genomes: DataFrame) -> DataFrame:
    """Data-set descriptors: reads, their lengths and bases, genome bases and how many of them reads touch, depth, error rate.

    ``error`` is the share of the reads' bases that differ from the genome where the truth has them.
    """
    on = F.when(F.col("rev"), revcomp("seq")).otherwise(F.col("seq"))
    told = reads.agg(
        F.count("*").alias("n_reads"), F.avg("len").alias("mean_len"), F.sum("len").alias("bases"), F.count_distinct("chrom").alias("chroms"),
        F.min("len").alias("min_len"), F.max("len").alias("max_len"),
    )
    size = genomes.agg(F.sum("len").cast("long").alias("genome_bases"))
    touched = covered(reads.select("chrom", "start", "end")).agg(F.sum("covered").cast("long").alias("touched"))
    truth = F.substring("ref", F.col("start") + 1, F.col("end") - F.col("start"))
    wrong = reads.join(genomes.select("chrom", F.col("seq").alias("ref")), "chrom").agg(F.sum(F.when(on == truth, 0).otherwise(hamming(on, truth))).alias("wrong"))
    both = told.join(size, F.lit(True)).join(touched, F.lit(True)).join(wrong, F.lit(True))
    return both.withColumn("depth", F.try_divide("bases", "genome_bases")).withColumn("error", F.try_divide("wrong", "bases")).drop("wrong")


def clean(reads: DataFrame, min_len: int = 1) -> DataFrame:
    """Upper-case reads of A, C, G and T only, of ``min_len`` bases at least."""
    up = reads.withColumn("seq", F.upper("seq"))
    return up.where(F.col("seq").rlike("^[ACGT]*$") & (F.length("seq") >= min_len))


def write_fasta(rows: DataFrame, path: str, name: str, seq: str) -> None:
    """One record per row."""
    rows.select(F.concat(F.lit(">"), F.col(name).cast("string"), F.lit("\n"), F.col(seq)).alias("value")).write.text(path)


def read_fasta(spark: SparkSession, path: str) -> DataFrame:
    """``(name, seq)`` of FASTA files; records may span lines.  Files are split at records."""
    raw = spark.read.option("lineSep", ">").text(path).where("length(value) > 0")
    name = F.trim(F.substring_index("value", "\n", 1))
    body = F.expr("substring(value, length(substring_index(value, '\n', 1)) + 2)")
    return raw.select(name.alias("name"), F.regexp_replace(body, r"\s", "").alias("seq"))
