"""Joins that Spark lacks as such: the last row before, and overlapping ranges."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def as_of(left: DataFrame, right: DataFrame, by: str, at: str, pick: str, out: str) -> DataFrame:
    """Every row of ``left`` with ``pick`` of the last row of ``right`` of its key, not after it.

    Both sides are sorted once by key and time and the last value seen is carried on, so nothing
    multiplies.  Of rows of ``right`` at one time the largest ``pick`` counts; null where there is
    none, or where key or time is null.
    """
    kinds = [F.col(f"`{c}`") for c in left.columns]
    l = left.select(F.col(by).alias("__k"), F.col(at).alias("__t"), F.lit(1).alias("__side"), F.lit(None).cast(right.schema[pick].dataType).alias("__pick"), F.struct(*kinds).alias("__row"))
    r = right.where(F.col(by).isNotNull() & F.col(at).isNotNull()).select(F.col(by).alias("__k"), F.col(at).alias("__t"), F.lit(0).alias("__side"), F.col(pick).alias("__pick"), F.lit(None).cast(l.schema["__row"].dataType).alias("__row"))
    w = Window.partitionBy("__k").orderBy("__t", "__side", "__pick").rowsBetween(Window.unboundedPreceding, 0)
    got = r.unionByName(l).withColumn(out, F.when(F.col("__t").isNotNull(), F.last("__pick", ignorenulls=True).over(w)))
    return got.where("__side = 1").select("__row.*", out)


def ranges_meet(a: DataFrame, b: DataFrame, by: str, size: int, at_least: int = 1) -> DataFrame:
    """Pairs of rows of one key whose ``[start, end)`` share ``at_least`` bases: ``(u, v, shared)``.

    ``a`` and ``b`` have ``id, start, end`` and ``by``.  Ranges meet in bins of ``size``, an equi-join; a
    pair is reported in the bin where its shared part begins only, so no distinct follows.
    """

    def binned(df: DataFrame, name: str) -> DataFrame:
        bins = F.sequence(F.expr(f"start div {size}"), F.expr(f"(end - 1) div {size}"))
        return df.where("end > start").select(by, F.col("id").alias(name), F.col("start").alias(f"{name}s"), F.col("end").alias(f"{name}e"), F.explode(bins).alias("bin"))

    j = binned(a, "u").join(binned(b, "v"), [by, "bin"])
    first, shared = F.greatest("us", "vs"), F.least("ue", "ve") - F.greatest("us", "vs")
    return j.where((shared >= at_least) & (F.floor(first / size) == F.col("bin"))).select("u", "v", shared.cast("long").alias("shared"))
