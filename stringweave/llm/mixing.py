"""Mixing sources to target weights by weighted fair queueing.

Documents stand in shuffled order inside their source.  The virtual finish time of a
document is the words its source has served up to and including it, over the
source's target; a source whose target is above its size is served again from its
start, up to three times.  All servings are sorted by finish time over all sources,
and the mix is the longest beginning of that order within the total budget.

The order inside a source is by a hash of the id, so its high bits cut every source
into even buckets, as many as its documents ask for.  Running totals are sums over groups
of buckets, over the buckets of one group, and inside one bucket: no task holds a source.
The end of the mix in the global order, and the source up to which targets stop at their
cap, are found by descent: sums over FAN ranges of the key, then over FAN ranges of the
range that holds the end, until EDGE_ROWS are left.  No table is ordered as a whole.

A null text has size 0 and is never taken; a null source comes last and has a weight
like any other; documents of one id, or of none, share one place
in the order and are taken or left together.  Repeated rows keep their number.  An empty table gives an empty mix.
"""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from stringweave.llm._common import word_count
from stringweave.session import Scratch

WEIGHTS = (1, 2, 3)
MAX_REPEATS = 3
#: Documents per bucket of the shuffled order, on average.
BUCKET_ROWS = 512
#: Ranges of a key whose sums reach the driver at one step of a descent; also buckets in a group of buckets.
FAN = 1024
#: Rows at the end of a descent that the driver takes.
EDGE_ROWS = 2048
HASH_BITS = 60


def _range(rows: DataFrame, col: str) -> tuple[int, Column | None]:
    """How many rows there are, and the range of ``col`` that a row lies in, null where all have one value."""
    n, lo, hi = rows.agg(F.count("*"), F.min(col), F.max(col)).first()
    if n <= EDGE_ROWS or lo == hi:
        return n, None
    return n, F.least(F.lit(FAN - 1), F.floor((F.col(col) - F.lit(lo)) / F.lit((hi - lo) / FAN))).cast("int")


def ranked(store: Scratch, sources: DataFrame) -> DataFrame:
    """``sources`` with ``rank``, their number by code point from 1, null last; sorted in ranges of sources."""
    cut = store.keep(sources.repartitionByRange(F.col("source").asc_nulls_last()).withColumn("part", F.spark_partition_id()))
    held = sorted((r.part, r.n) for r in cut.groupBy("part").agg(F.count("*").alias("n")).collect())
    before, first = 0, {}
    for part, n in held:
        first[part], before = before, before + n
    offset = F.array(*[F.lit(first.get(p, 0)).cast("long") for p in range(max(first, default=0) + 1)])
    own = F.row_number().over(Window.partitionBy("part").orderBy(F.col("source").asc_nulls_last()))
    return cut.withColumn("rank", F.element_at(offset, F.col("part") + 1) + own).drop("part")


def fill_level(capped: DataFrame, budget: int, beyond: int) -> tuple[Fraction | None, int, int]:
    """The largest cap over weight of a source that stops at its cap, what the others share, and their weights.

    Shares grow together, so a source stops if all caps up to its own ratio, and its ratio times the
    weights beyond, are within the budget.  ``capped`` has ``cap`` and ``weight``, which add up to
    ``beyond``; sums are exact.
    """
    rows = capped.select((F.col("cap") / F.col("weight")).alias("ratio"), "cap", "weight")
    taken, level = 0, None
    while True:
        n, cell = _range(rows, "ratio")
        if cell is None:
            cells = [(Fraction(r.cap, r.weight), r.cap * r.n, r.weight * r.n, None) for r in rows.groupBy("cap", "weight").agg(F.count("*").alias("n")).collect()]
        else:
            top = F.max(F.struct("ratio", "cap", "weight")).alias("top")
            sums = rows.groupBy(cell.alias("cell")).agg(F.sum("cap").alias("c"), F.sum("weight").alias("w"), top).collect()
            cells = [(Fraction(r.top.cap, r.top.weight), r.c, r.w, r.cell) for r in sums]
        by: dict = {}
        for ratio, c, w, at in cells:  # equal ratios stop together
            c0, w0, _ = by.get(ratio, (0, 0, None))
            by[ratio] = (c0 + c, w0 + w, at)
        for ratio in sorted(by):
            c, w, at = by[ratio]
            if taken + c + ratio * (beyond - w) > budget:
                break
            taken, beyond, level, at = taken + c, beyond - w, ratio, None
        else:
            at = None
        if at is None:
            return level, budget - taken, beyond
        rows = rows.where(cell == at)


def targets(store: Scratch, sources: DataFrame) -> tuple[DataFrame, int]:
    """Source sizes to targets: ``(source, source_size)`` in, ``rank``, ``weight``, ``target`` added; and the sum of all sizes.

    Targets share the sum of all sizes by weight and stop at MAX_REPEATS times the
    source's size; the excess goes to the others by weight until none is above.
    """
    weight = F.element_at(F.array(*[F.lit(w) for w in WEIGHTS]), (F.pmod(F.col("rank") - 1, F.lit(len(WEIGHTS))) + 1).cast("int")).cast("long")
    t = store.keep(ranked(store, sources).withColumn("weight", weight).withColumn("cap", F.col("source_size") * MAX_REPEATS))
    budget, weights = t.agg(F.sum("source_size"), F.sum("weight")).first()
    level, rest, weights = fill_level(t, budget or 0, weights or 0)
    stops = F.lit(False) if level is None else F.col("cap") / F.col("weight") <= level.numerator / level.denominator
    share = (F.col("weight") * rest).cast("double") / F.lit(float(max(weights, 1)))
    return t.select("source", "source_size", "rank", "weight", F.when(stops, F.col("cap").cast("double")).otherwise(share).alias("target")), budget or 0


def _serve(df: DataFrame, text: str, doc_id: str, source: str, seed: int) -> tuple[DataFrame, DataFrame]:
    """Documents with their size and place, and the ends of the mix: a row per source.

    ``ends`` has the source's size, rank and target and, per turn, the last place of the shuffled
    order that the mix takes.
    """
    spark = df.sparkSession
    store = Scratch(spark, "mixing")
    sized = store.keep(
        df.select(F.col(doc_id).alias("doc_id"), F.col(source).alias("source"), word_count(F.col(text)).alias("size")).withColumn("h", shuffled(F.col("doc_id"), seed))
    )
    n = sized.count()
    bits = (max(16, n // BUCKET_ROWS) - 1).bit_length()
    bucket = F.shiftright("h", HASH_BITS - bits)
    # rows of one id are one place from here on, so that no bucket grows with them
    places = store.keep(sized.groupBy("source", bucket.alias("bucket"), "h", "doc_id").agg(F.sum("size").alias("size")))
    per_bucket = store.keep(places.groupBy("source", "bucket").agg(F.sum("size").alias("in_bucket")))
    goals, budget = targets(store, per_bucket.groupBy("source").agg(F.sum("in_bucket").alias("source_size")))
    goal = goals.select(F.col("source").alias("src"), "rank", "source_size", "target")
    known = lambda t: t.join(goal, t["source"].eqNullSafe(F.col("src")))
    numbered = known(per_bucket).select("rank", "bucket", F.shiftright("bucket", FAN.bit_length() - 1).alias("group"), "in_bucket")
    earlier = lambda by, at: Window.partitionBy(*by).orderBy(at).rowsBetween(Window.unboundedPreceding, -1)
    groups = numbered.groupBy("rank", "group").agg(F.sum("in_bucket").alias("in_group"))
    groups = groups.select("rank", "group", F.coalesce(F.sum("in_group").over(earlier(["rank"], "group")), F.lit(0)).alias("before_group"))
    before = F.col("before_group") + F.coalesce(F.sum("in_bucket").over(earlier(["rank", "group"], "bucket")), F.lit(0))
    starts = numbered.join(groups, ["rank", "group"]).select("rank", "bucket", before.alias("before"))
    inside = Window.partitionBy("rank", "bucket").orderBy("h", F.col("doc_id").asc_nulls_first()).rowsBetween(Window.unboundedPreceding, 0)
    lined = known(places).select("rank", "bucket", "h", "doc_id", "size", "source_size", "target").join(starts, ["rank", "bucket"])
    served = store.keep(lined.withColumn("upto", F.col("before") + F.sum("size").over(inside)).where("size > 0 and target > 0").select("doc_id", "size", "rank", "h", "upto", "source_size", "target"))
    within = _cut(served, budget)
    last = lambda r: F.max(F.when(within(F.lit(r)), F.struct("h", "doc_id"))).alias(f"__end{r}")
    ends = served.groupBy("rank").agg(*[last(r) for r in range(MAX_REPEATS)])
    # written, so that the join with the rows knows how small it is and leaves their texts where they are
    return sized, store.keep(goals.withColumnRenamed("source", "__source").join(ends, "rank", "left").drop("weight"))


def _times() -> Column:
    """How often the mix serves a document at place ``h``, ``doc_id``: within a source and a turn it takes a beginning of the order."""
    place = F.struct("h", "doc_id")
    return sum(F.when(place <= F.col(f"__end{r}"), 1).otherwise(0) for r in range(MAX_REPEATS))


def mix(df: DataFrame, text: str = "text", doc_id: str = "doc_id", source: str = "source", seed: int = 7) -> DataFrame:
    """``(doc_id, source, size, source_size, target, taken)``, a row per document.

    ``taken`` is the size times the servings inside the mix.
    """
    sized, ends = _serve(df, text, doc_id, source, seed)
    taken = F.when(F.col("size") > 0, F.col("size") * _times()).otherwise(0).cast("long")
    return sized.join(ends, sized["source"].eqNullSafe(ends["__source"])).select("doc_id", "source", "size", "source_size", "target", taken.alias("taken"))


def mixed(df: DataFrame, text: str = "text", doc_id: str = "doc_id", source: str = "source", seed: int = 7) -> DataFrame:
    """The rows of ``df`` as the mix serves them: those not taken go, those served again repeat.

    The ends of the mix, a row per source, are all that the rows need to be told: no text is moved.
    """
    _, ends = _serve(df, text, doc_id, source, seed)
    own = {c: f"__{i}" for i, c in enumerate(df.columns)}  # no name clashes with those of the ends
    rows = df.where(F.coalesce(F.col(f"`{text}`").rlike(r"[^\x20\x09-\x0D]"), F.lit(False)))
    rows = rows.select(*[F.col(f"`{c}`").alias(n) for c, n in own.items()], shuffled(F.col(doc_id), seed).alias("h"), F.col(doc_id).alias("doc_id"))
    out = rows.join(ends, rows[own[source]].eqNullSafe(ends["__source"])).withColumn("__times", _times()).where("__times > 0")
    return out.withColumn("__turn", F.explode(F.sequence(F.lit(1), F.col("__times")))).select(*[F.col(n).alias(c) for c, n in own.items()])


def shuffled(doc_id: Column, seed: int) -> Column:
    """The place of an id in the shuffled order: HASH_BITS bits of a digest."""
    named = F.concat(F.coalesce(doc_id.cast("string"), F.lit("")), F.lit(f":{seed}"))
    return F.conv(F.substring(F.md5(named), 1, HASH_BITS // 4), 16, 10).cast("long")


def _finish(turn: Column) -> Column:
    """The virtual finish time of a place in a turn."""
    return (F.col("upto") + turn * F.col("source_size")) / F.col("target")


def _cut(served: DataFrame, budget: int):
    """Where the mix ends in the order of finish time, rank, hash and id, as a condition on a place and its turn.

    The mix takes whole places while their sum is within ``budget``.
    """
    kind = served.schema["doc_id"].dataType
    key = ("finish", "rank", "h")
    rows = served.withColumn("turn", F.explode(F.sequence(F.lit(0), F.lit(MAX_REPEATS - 1)))).select(_finish(F.col("turn")).alias("finish"), "rank", "h", "doc_id", "size")
    before = 0
    for col in key:
        while True:
            n, cell = _range(rows, col)
            if cell is None:
                break
            for at, inside in sorted(map(tuple, rows.groupBy(cell.alias("cell")).agg(F.sum("size")).collect())):
                if before + inside > budget:
                    break
                before += inside
            rows = rows.where(cell == at)
        if n <= EDGE_ROWS:
            break
    edge = sorted(rows.groupBy(*key, "doc_id").agg(F.sum("size").alias("size")).collect(), key=lambda r: (r.finish, r.rank, r.h, r.doc_id is not None, r.doc_id))
    last = None
    for r in edge:
        if before + r["size"] > budget:
            break
        before, last = before + r["size"], r
    place = lambda finish, rank, h, doc_id: F.struct(finish.cast("double").alias("finish"), rank.cast("long").alias("rank"), h.cast("long").alias("h"), doc_id.alias("doc_id"))
    literal = lambda r: place(F.lit(r.finish), F.lit(r.rank), F.lit(r.h), F.lit(r.doc_id).cast(kind))

    def within(turn: Column) -> Column:
        own = place(_finish(turn), F.col("rank"), F.col("h"), F.col("doc_id"))
        return own <= literal(last) if last is not None else own < literal(edge[0]) if edge else F.lit(False)

    return within
