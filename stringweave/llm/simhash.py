"""Near duplicates by 64-bit SimHash, with pivot distance tables.

A fingerprint takes one whole text.  Equal fingerprints are one node, so copies
never meet each other.  Different fingerprints meet in band buckets (some band of a
close pair is equal bit for bit), as a reference alone gives no key that an equi-join
could use.  A bucket is judged by its pivot table: the Hamming distances of every
fingerprint to many reference fingerprints.  By the triangle inequality a pair whose
coordinates differ by more than the radius at any reference cannot be close.  The bucket
is sorted by its first coordinate, pairs outside the window of that radius are never
formed, and those whose largest difference over the other coordinates is above it are
discarded.  Survivors are verified bit by bit.  What a bucket reports is a spanning forest
of its close pairs, so the links written follow the nodes, not the pairs, and how many
pairs each step left.

Nulls and empty texts have the fingerprint zero, which links like any other.
Rows with a null id take part; their component has the smallest id that is not
null, or null.  Repeated rows are returned as often as they are given.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stringweave.llm._common import fields, per_text
from stringweave.operators.contraction import contract_components
from stringweave.session import Scratch, task_count

RADIUS = 4
SHINGLE = 4
SEED = 42
PIVOTS = 32
#: Fingerprints of one bucket compared in one piece; a larger bucket is cut into pieces
#: of this size and every two pieces meet in a group of their own.
PIECE = 2048
#: Pairs that a task holds at once.
SLICE = 1 << 18


def pivots(n: int = PIVOTS) -> np.ndarray:
    """``n`` fixed reference fingerprints, from the digests of their numbers."""
    return np.array([xxhash.xxh64_intdigest(f"pivot {i}", seed=SEED) for i in range(n)], dtype=np.uint64)


def fingerprint(text: bytes | None, k: int = SHINGLE) -> int:
    """The fingerprint of one text, unsigned."""
    words = (text or b"").lower().split()
    if not words:
        return 0
    if len(words) <= k:
        return xxhash.xxh64_intdigest(b" ".join(words), seed=SEED)
    line = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))[: len(words) - k + 1].tolist()
    digest = xxhash.xxh64_intdigest
    hashes = np.array([digest(line[a:b], 42) for a, b in zip(starts, ends[k - 1 :].tolist())], dtype=np.uint64)
    half, total = len(hashes) / 2, np.zeros(64, np.int64)
    for at in range(0, len(hashes), 1 << 16):
        part = hashes[at : at + (1 << 16)]
        total += np.unpackbits(part.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(total > half, bitorder="little").view("<u8")[0])


def fingerprints(df: DataFrame, text: str = "text", keep: list[str] | None = None) -> DataFrame:
    """Append ``fp``, the fingerprint as a signed long."""

    def make():
        return lambda texts: {"fp": np.array([fingerprint(t) for t in texts], dtype=np.uint64).astype(np.int64)}

    return per_text(df, make, fields("fp long"), text, keep)


#: Blocks of bits by the fingerprints below which they serve; any number above RADIUS finds every link.
BLOCKS = ((1 << 22, 5), (1 << 30, 6), (1 << 62, 8))


def band_masks(n: int, blocks: int | None = None) -> list[int]:
    """Masks such that two fingerprints within the radius agree under one of them at least.

    The bits fall into ``blocks``, by default those of BLOCKS for ``n`` fingerprints; a mask keeps all
    but RADIUS of them.  More blocks keep more bits, so that the buckets stay small as the
    fingerprints grow in number; the links are the same with any number.
    """
    parts = blocks or next(b for below, b in BLOCKS if n < below)
    edges = [64 * i // parts for i in range(parts + 1)]
    block = [((1 << edges[i + 1]) - 1) ^ ((1 << edges[i]) - 1) for i in range(parts)]
    return [sum(block[i] for i in kept) for kept in combinations(range(parts), parts - RADIUS)]


def pair_slices(left: np.ndarray, right: np.ndarray, table_l: np.ndarray, table_r: np.ndarray, same: bool, radius: int = RADIUS) -> Iterator[tuple[np.ndarray, np.ndarray, int, int]]:
    """Positions of the close pairs of two arrays of fingerprints, by their pivot tables, in slices.

    Each slice also tells how many pairs the window of the first coordinate formed, and how many the
    whole table left to be verified.  With ``same`` both arrays are one, and each pair is formed once.
    """
    by = np.argsort(table_r[:, 0], kind="stable")
    line = table_r[by, 0].astype(np.int16)
    if same:
        own, first = by, np.arange(1, len(by) + 1)
        until = np.searchsorted(line, line + radius, "right")
    else:
        own, at = np.arange(len(left)), table_l[:, 0].astype(np.int16)
        first, until = np.searchsorted(line, at - radius, "left"), np.searchsorted(line, at + radius, "right")
    room = np.maximum(until - first, 0)
    upto = np.concatenate(([0], np.cumsum(room)))
    a = 0
    while a < len(own):
        b = max(a + 1, int(np.searchsorted(upto, upto[a] + SLICE, "right")) - 1)
        n = room[a:b]
        i, j = np.repeat(own[a:b], n), by[np.arange(upto[b] - upto[a]) + np.repeat(first[a:b] - upto[a:b] + upto[a], n)]
        for p in range(1, table_l.shape[1]):
            if not len(i):
                break
            ok = np.abs(table_l[i, p].astype(np.int16) - table_r[j, p]) <= radius
            i, j = i[ok], j[ok]
        ok = np.bitwise_count(left[i] ^ right[j]) <= radius
        yield i[ok], j[ok], int(upto[b] - upto[a]), len(i)
        a = b


def close_pairs(left: np.ndarray, right: np.ndarray, table_l: np.ndarray, table_r: np.ndarray, same: bool, radius: int = RADIUS) -> tuple[np.ndarray, np.ndarray, int, int]:
    """All slices of ``pair_slices`` in one."""
    i, j, formed, kept = zip((np.empty(0, np.int64), np.empty(0, np.int64), 0, 0), *pair_slices(left, right, table_l, table_r, same, radius))
    return np.concatenate(i), np.concatenate(j), sum(formed), sum(kept)


def join_trees(root: np.ndarray, i: np.ndarray, j: np.ndarray) -> None:
    """Joins the trees of the pairs' ends in ``root``, which holds the smallest position reachable from each."""
    while len(i):
        a, b = root[i], root[j]
        low = np.minimum(a, b)
        np.minimum.at(root, a, low)
        np.minimum.at(root, b, low)
        while not np.array_equal(root, above := root[root]):
            root[:] = above
        left = root[i] != root[j]
        i, j = i[left], j[left]


def forest(n: int, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """The smallest position reachable from each of ``n`` positions over the pairs."""
    root = np.arange(n)
    join_trees(root, i, j)
    return root


LINKS = "a long, b long, pairs long, formed long, verified long"


def _judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Links of each group of one partition; a group's rows follow one another."""
    refs, rest = pivots(), None
    names = [f.split()[0] for f in LINKS.split(", ")]

    def links(fps: np.ndarray, side: np.ndarray) -> tuple[np.ndarray, np.ndarray, tuple[int, int, int]]:
        tables = np.bitwise_count(fps[:, None] ^ refs).astype(np.int8)
        if side.all() or not side.any():
            li = ri = np.arange(len(fps))
            found = pair_slices(fps, fps, tables, tables, True)
            pairs = len(fps) * (len(fps) - 1) // 2
        else:
            li, ri = np.nonzero(side == 0)[0], np.nonzero(side == 1)[0]
            found = pair_slices(fps[li], fps[ri], tables[li], tables[ri], False)
            pairs = len(li) * len(ri)
        root, formed, kept = np.arange(len(fps)), 0, 0
        for i, j, made, left in found:
            join_trees(root, li[i], ri[j])
            formed, kept = formed + made, kept + left
        moved = np.nonzero(root != np.arange(len(fps)))[0]
        return fps[root[moved]], fps[moved], (pairs, formed, kept)

    def groups(keys, fps, sides, last: bool):
        cut = np.nonzero(np.any(keys[1:] != keys[:-1], axis=1))[0] + 1
        bounds = [0, *cut.tolist(), len(keys)]
        done = bounds if last else bounds[:-1]
        a, b, told = [], [], np.zeros(3, np.int64)
        for lo, hi in zip(done, done[1:]):
            if hi - lo > 1:
                x, y, counts = links(fps[lo:hi], sides[lo:hi])
                a.append(x)
                b.append(y)
                told += counts
        return np.concatenate(a or [np.empty(0, np.uint64)]), np.concatenate(b or [np.empty(0, np.uint64)]), told, bounds[-2]

    def emit(a, b, told):
        """The links, and a row without ends that holds the counts."""
        ends = [pa.array([*x.astype(np.int64).tolist(), None], pa.int64()) for x in (a, b)]
        return pa.RecordBatch.from_arrays([*ends, *[pa.array([0] * len(a) + [int(n)], pa.int64()) for n in told]], names=names)

    for batch in batches:
        if not batch.num_rows:
            continue
        cols = [batch.column(i).to_numpy(zero_copy_only=False) for i in range(6)]
        part = [np.stack(cols[:4], axis=1), cols[4].astype(np.uint64), cols[5]]
        if rest is not None:
            part = [np.concatenate(x) for x in zip(rest, part)]
        a, b, told, at = groups(*part, last=False)
        rest = [x[at:] for x in part]
        if told[0]:
            yield emit(a, b, told)
    if rest is not None:
        a, b, told, _ = groups(*rest, last=True)
        yield emit(a, b, told)


def links(nodes: DataFrame, n: int) -> DataFrame:
    """A spanning set of the close pairs among distinct fingerprints ``fp``: ``(a, b, pairs, formed, verified)``.

    Rows without ends count what the judged groups held: all their pairs, those that the first pivot's
    window formed, and those that the whole table left to be verified; ``discards`` sums them.
    Band buckets larger than PIECE are cut by a hash into pieces, and each two pieces form a group, so
    that no group and no task grows with a bucket.
    """
    spark = nodes.sparkSession
    masks = band_masks(n)
    keyed = nodes.select(
        "fp", F.posexplode(F.array(*[F.col("fp").bitwiseAND(F.lit(m - (1 << 64) if m >> 63 else m).cast("long")) for m in masks])).alias("band", "value")
    )
    hot = keyed.groupBy("band", "value").agg(F.count("*").alias("n")).where(F.col("n") > PIECE).select("band", "value", F.ceil(F.col("n") / PIECE).cast("int").alias("pieces"))
    cut = (
        keyed.join(hot, ["band", "value"], "left")
        .withColumn("pieces", F.coalesce("pieces", F.lit(1)))
        .withColumn("own", F.when(F.col("pieces") == 1, 0).otherwise(F.pmod(F.xxhash64("fp"), F.col("pieces"))).cast("int"))
        .withColumn("other", F.explode(F.sequence(F.lit(0), F.col("pieces") - 1)))
        .select(
            F.col("band").cast("long").alias("band"), "value",
            F.least("own", "other").cast("long").alias("lo"), F.greatest("own", "other").cast("long").alias("hi"),
            "fp", F.when(F.col("own") > F.col("other"), 1).otherwise(0).cast("long").alias("side"),
        )
    )
    parts = task_count(spark, n * len(masks), 1_000_000)
    key = ["band", "value", "lo", "hi"]
    grouped = cut.repartition(parts, *key).sortWithinPartitions(*key)
    return grouped.mapInArrow(_judge, LINKS)


def discards(found: DataFrame) -> DataFrame:
    """``(pairs, formed, verified)`` of what ``links`` returned: how much the pivots discard."""
    return found.agg(*[F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in ("pairs", "formed", "verified")])


def near_duplicates(df: DataFrame, text: str = "text", doc_id: str = "doc_id", keep: list[str] | None = None) -> DataFrame:
    """Append ``fp`` (long), ``fingerprint`` (16 hex digits) and ``component_id``.

    ``component_id`` is the smallest id reachable over links of at most four differing
    bits.  See the module for nulls, empty texts and repeated rows.
    """
    spark = df.sparkSession
    store = Scratch(spark, "simhash")
    carried = [c for c in (keep if keep is not None else df.columns) if c.lower() not in ("fp", "fingerprint", "component_id")]
    rows = store.keep(fingerprints(df, text, keep=carried))
    nodes = store.keep(rows.groupBy("fp").agg(F.min(doc_id).alias("least_id")))
    n = nodes.count()
    found = store.keep(links(nodes.select("fp"), n))
    labels = contract_components(spark, found.select("a", "b"))
    roots = nodes.join(labels.select(F.col("v").alias("fp"), "root"), "fp", "left").select("fp", "least_id", F.coalesce("root", "fp").alias("root"))
    roots = store.keep(roots)
    least = store.keep(roots.groupBy("root").agg(F.min("least_id").alias("component_id")))
    named = store.keep(roots.join(least, "root").select("fp", "component_id"))
    out = rows.join(named, "fp", "left")
    return out.select(*carried, "fp", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def keep_one(df: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """One document of each group: the one with the smallest id.

    Decided on ids and fingerprints alone; whole rows move once, in the join with the ids
    that go.  Of repeated rows of a kept id one stays.  Rows without an id can't be named
    by a decision and stay.
    """
    store, cols = Scratch(df.sparkSession, "keep-one"), df.columns
    tagged = store.keep(near_duplicates(df.select(doc_id, text), text, doc_id, keep=[doc_id]).select(F.col(doc_id).alias("__id"), "component_id"))
    odd = store.keep(
        tagged.where("__id is not null")
        .groupBy("__id")
        .agg(F.count("*").alias("__n"), (F.min("component_id") < F.col("__id")).alias("__goes"))
        .where("__n > 1 or __goes")
    )
    joined = df.join(odd, df[doc_id] == odd["__id"], "left").where("not coalesce(__goes, false)")
    once = joined.where("__id is null").select(*cols)
    rows = joined.where("__id is not null").groupBy("__id").agg(F.min(F.struct(*[F.col(f"`{c}`") for c in cols])).alias("__row"))
    return once.unionByName(rows.select("__row.*"))
