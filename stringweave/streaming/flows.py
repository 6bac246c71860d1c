"""Streaming forms: each reads files as a stream and must end where the batch form ends."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from stringweave.operators.overlap import count_kmers, kmers, partial_codes
from stringweave.session import Scratch
from stringweave.sources.reads import genome, shotgun


def stream(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table, one file or a folder of files, as a file stream; a folder comes in batches of some megabytes."""
    table = f"{sf_dir}/{name}.parquet"
    come = spark.readStream.schema(spark.read.parquet(table).schema)
    path = spark._jvm.org.apache.hadoop.fs.Path(table)
    if path.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).getFileStatus(path).isDirectory():
        return come.option("maxBytesPerTrigger", 128 << 20).parquet(table)
    return come.option("maxFilesPerTrigger", 1).option("pathGlobFilter", f"{name}.parquet").parquet(sf_dir)


def drain(df: DataFrame, mode: str) -> DataFrame:
    """Run a stream over what is there and return its rows; state and output live in the shared folder."""
    spark = df.sparkSession
    store = Scratch(spark, "stream")

    def sink(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite" if mode == "complete" else "append").parquet(f"{store.root}/out")

    q = df.writeStream.outputMode(mode).option("checkpointLocation", f"{store.root}/state").trigger(availableNow=True).foreachBatch(sink).start()
    q.awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{store.root}/out")


def tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = stream(spark, sf_dir, "events").groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("n"))
    return drain(e, "complete").select(F.unix_micros(F.col("window.start").cast("timestamp")).alias("day_us"), "event_type", "n")


def sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = stream(spark, sf_dir, "events").groupBy(F.window("ts", "2 days", "1 day")).agg(F.count("*").alias("n"))
    return drain(e, "complete").select(F.unix_micros(F.col("window.start").cast("timestamp")).alias("day_us"), "n")


def sessions(spark: SparkSession, sf_dir: str, minutes: int = 240) -> DataFrame:
    """Chains of a user's events as session windows; the gap is a microsecond wider, as a chain allows the gap itself."""
    e = stream(spark, sf_dir, "events").groupBy(F.session_window("ts", f"{minutes * 60_000_000 + 1} microseconds"), "user_id").agg(F.count("*").alias("n"))
    return drain(e, "complete").select("user_id", F.unix_micros(F.col("session_window.start").cast("timestamp")).alias("start_us"), "n")


CHAIN = "user_id long, start_us long, n long"


def stateful_chains(spark: SparkSession, sf_dir: str, minutes: int = 240) -> DataFrame:
    """A user's open chain as state; a chain is emitted when an event past the gap closes it.

    The state is three numbers a user.  Events of one batch are put in order; an event before the open
    chain's end joins it.  Chains still open when the stream ends are not emitted.
    """
    gap = minutes * 60_000_000

    def grow(key, frames, state):
        start, end, n = state.get if state.exists else (None, None, 0)
        closed = []
        for at in sorted(x for f in frames for x in f["at"].tolist()):
            if start is not None and at - end > gap:
                closed.append((key[0], start, n))
                start, end, n = None, None, 0
            start, end, n = at if start is None else start, at if end is None else max(end, at), n + 1
        if n:
            state.update((start, end, n))
        yield pd.DataFrame(closed, columns=["user_id", "start_us", "n"])

    e = stream(spark, sf_dir, "events").where("user_id is not null and ts is not null").select("user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("at"))
    return drain(e.groupBy("user_id").applyInPandasWithState(grow, CHAIN, "start long, end long, n long", "append", GroupStateTimeout.NoTimeout), "append")


def kmer_counts(spark: SparkSession, sf_dir: str, k: int = 17) -> DataFrame:
    reads = shotgun(genome(stream(spark, sf_dir, "benchmark"), "item_id", "text"), 100, 25)
    return drain(count_kmers(kmers(reads, k)), "complete").groupBy("n").agg(F.count("*").alias("kmers"))


def dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    # the state of a key goes ten years of shipping dates after it was first seen
    lines = stream(spark, sf_dir, "lineitem").select("l_orderkey", F.col("l_shipdate").cast("timestamp").alias("at")).withWatermark("at", "3650 days")
    ids = lines.dropDuplicatesWithinWatermark(["l_orderkey"]).select("l_orderkey")
    return drain(ids, "append").agg(F.count("*").alias("orders"))


def interval_join(spark: SparkSession, sf_dir: str, hours: int = 24) -> DataFrame:
    """Purchases with the same user's views of the hours before."""
    e = stream(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type").withWatermark("ts", "1 day")
    v = e.where("event_type = 'view'").select(F.col("event_id").alias("view_id"), F.col("ts").alias("vt"), F.col("user_id").alias("vu"))
    p = e.where("event_type = 'purchase'").select("event_id", "ts", "user_id")
    near = (F.col("vu") == F.col("user_id")) & (F.col("vt") <= F.col("ts")) & (F.col("vt") >= F.col("ts") - F.expr(f"interval {hours} hours"))
    return drain(p.join(v, near).select("event_id", "view_id"), "append")


def static_candidates(spark: SparkSession, sf_dir: str, k: int = 31) -> DataFrame:
    """Arriving reads against fixed k-mers: shared words per pair of chromosomes."""
    fixed = genome(spark.read.parquet(f"{sf_dir}/benchmark.parquet"), "item_id", "text").withColumnRenamed("chrom", "read_id")
    known = Scratch(spark, "fixed").keep(kmers(fixed, k, both_strands=False).select(F.col("read_id").alias("item"), "kmer"))
    come = genome(stream(spark, sf_dir, "documents"), "doc_id", "text")
    hits = partial_codes(come, k, both_strands=False).join(known, "kmer").groupBy("item").agg(F.sum("n").alias("shared"))
    return drain(hits, "complete")
