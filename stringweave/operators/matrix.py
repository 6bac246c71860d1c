"""Sparse matrices as triples ``(row, col, val)`` over semirings."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Semiring:
    """How products are formed and summed; the same over arrays of longs or flags, for products in tiles."""

    name: str
    mul: Callable[[Column, Column], Column]
    add: Callable[[Column], Column]
    of_arrays: tuple[Callable, np.ufunc, int] | None = None  # product, sum, what the sum begins with


_LEAST, _MOST = -(1 << 63), (1 << 63) - 1
PLUS_TIMES = Semiring("plus-times", lambda a, b: a * b, F.sum, (np.multiply, np.add, 0))
MIN_PLUS = Semiring("min-plus", lambda a, b: a + b, F.min, (np.add, np.minimum, _MOST))
MAX_TIMES = Semiring("max-times", lambda a, b: a * b, F.max, (np.multiply, np.maximum, _LEAST))
OR_AND = Semiring("or-and", lambda a, b: a & b, F.bool_or, (np.logical_and, np.logical_or, 0))
COUNT = Semiring("count", lambda a, b: F.lit(1), F.count, (lambda x, y: np.ones((len(x), y.shape[1]), np.int64), np.add, 0))

#: Rows and columns of a product that one call forms whole, on average.
TILE = 1024


def transpose(a: DataFrame) -> DataFrame:
    """Rows for columns; no data moves."""
    return a.select(F.col("col").alias("row"), F.col("row").alias("col"), "val")


def _tiling(x: DataFrame, y: DataFrame, sr: Semiring) -> tuple[int, int] | None:
    """Tiles down and across where forming the product tile by tile moves less than its single products; else None."""
    kinds = {f.dataType.simpleString() for df in (x, y) for f in df.schema}
    values = {df.schema[c].dataType.simpleString() for df, c in ((x, "x"), (y, "y"))}
    if sr.of_arrays is None or not kinds <= {"bigint", "int", "boolean"} or values not in ({"bigint"}, {"boolean"}) or (values == {"boolean"} and sr.name not in ("or-and", "count")) or (values == {"bigint"} and sr.name == "or-and"):
        return None

    def facts(df, line, val):
        v = F.col(val).cast("long")
        null = F.sum((F.col(line).isNull() | F.col(val).isNull()).cast("long"))
        return df.where("k is not null").agg(F.count("*"), F.count_distinct(line), F.coalesce(null, F.lit(0)), F.coalesce(F.min(v), F.lit(0)), F.coalesce(F.max(v), F.lit(0))).first()

    (na, rows, null_a, lo_a, hi_a), (nb, cols, null_b, lo_b, hi_b) = facts(x, "row", "x"), facts(y, "col", "y")
    most = max(abs(lo_a), abs(hi_a), 1) * max(abs(lo_b), abs(hi_b), 1) * 2 * max(na, nb, 1)
    if null_a or null_b or most > _MOST:  # sums of columns pass over nulls and notice an overflow
        return None
    per_k = x.groupBy("k").agg(F.count("*").alias("m")).join(y.groupBy("k").agg(F.count("*").alias("n")), "k")
    made = per_k.agg(F.sum(F.col("m").cast("double") * F.col("n"))).first()[0] or 0
    down, across = max(1, -(-rows // TILE)), max(1, -(-cols // TILE))
    return (down, across) if 4 * (na * across + nb * down) < made else None


def _tiled(x: DataFrame, y: DataFrame, sr: Semiring, upper: bool, down: int, across: int) -> DataFrame:
    """The product in tiles of rows by columns: one call holds all that enters its cells, so no product is shuffled."""
    mul, add, start = sr.of_arrays
    flags = sr.name == "or-and"
    named = [x.schema["row"].dataType.simpleString(), y.schema["col"].dataType.simpleString(), "boolean" if flags else "bigint"]

    def by_k(t, line, val):
        ids, at = np.unique(t.column(line).to_numpy(), return_inverse=True)
        k = t.column("k").to_numpy()
        order = np.argsort(k, kind="stable")
        found, first = np.unique(k[order], return_index=True)
        return ids, dict(zip(found.tolist(), np.split(order, first[1:]))), at, t.column(val).to_numpy()

    def work(left: pa.Table, right: pa.Table) -> pa.Table:
        rows, in_a, ra, xs = by_k(left, "row", "x")
        cols, in_b, cb, ys = by_k(right, "col", "y")
        out, seen = np.full((len(rows), len(cols)), start, bool if flags else np.int64), np.zeros((len(rows), len(cols)), bool)
        for k in in_a.keys() & in_b.keys():
            i, j = ra[in_a[k]], cb[in_b[k]]
            made = mul(xs[in_a[k]][:, None], ys[in_b[k]][None, :])
            if len(np.unique(i)) < len(i) or len(np.unique(j)) < len(j):  # an element given more than once
                add.at(out, (i[:, None], j[None, :]), made)
                seen[np.ix_(i, j)] = True
            elif len(i) == len(rows) and len(j) == len(cols):
                put = np.empty_like(made)
                put[np.ix_(i, j)] = made
                add(out, put, out=out)
                seen[:] = True
            else:
                cells = np.ix_(i, j)
                out[cells] = add(out[cells], made)
                seen[cells] = True
        if upper:
            seen &= rows[:, None] < cols[None, :]
        if seen.all():
            cells = [np.repeat(rows, len(cols)), np.tile(cols, len(rows)), out.ravel()]
        else:
            i, j = np.nonzero(seen)
            cells = [rows[i], cols[j], out[seen]]
        return pa.Table.from_arrays([pa.array(c) for c in cells], names=["row", "col", "val"])

    lot = lambda c, n: F.pmod(F.xxhash64(c), F.lit(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    a = x.where("k is not null").select(lot("row", down).alias("bi"), every(across).alias("bj"), "row", "k", "x")
    b = y.where("k is not null").select(every(down).alias("bi"), lot("col", across).alias("bj"), "k", "col", "y")
    kinds = "row {}, col {}, val {}".format(*named)
    return a.groupBy("bi", "bj").cogroup(b.groupBy("bi", "bj")).applyInArrow(work, kinds)


def spgemm(a: DataFrame, b: DataFrame, sr: Semiring = PLUS_TIMES, upper: bool = False) -> DataFrame:
    """The product over a semiring; ``upper`` keeps row < col, which halves a symmetric product.

    Where its single products are many for the elements of ``a`` and ``b``, the product is formed in tiles.
    """
    x = a.select("row", F.col("col").alias("k"), F.col("val").alias("x"))
    y = b.select(F.col("row").alias("k"), "col", F.col("val").alias("y"))
    tiles = _tiling(x, y, sr)
    if tiles:
        return _tiled(x, y, sr, upper, *tiles)
    return _joined(x, y, sr, upper)


def _joined(x: DataFrame, y: DataFrame, sr: Semiring, upper: bool) -> DataFrame:
    j = x.join(y, "k")
    j = j.where("row < col") if upper else j
    return j.groupBy("row", "col").agg(sr.add(sr.mul(F.col("x"), F.col("y"))).alias("val"))


def spmv(a: DataFrame, x: DataFrame, sr: Semiring = PLUS_TIMES) -> DataFrame:
    """Matrix times sparse vector ``(i, val)``."""
    v = x.select(F.col("i").alias("col"), F.col("val").alias("y"))
    return a.join(v, "col").groupBy(F.col("row").alias("i")).agg(sr.add(sr.mul(F.col("val"), F.col("y"))).alias("val"))


def apply(a: DataFrame, f: Callable[[Column], Column]) -> DataFrame:
    """A function of every element."""
    return a.select("row", "col", f(F.col("val")).alias("val"))


def select(a: DataFrame, keep: Callable[[Column, Column, Column], Column]) -> DataFrame:
    """The elements that a condition on row, column and value keeps."""
    return a.where(keep(F.col("row"), F.col("col"), F.col("val")))


def prune(a: DataFrame, drop: Callable[[Column], Column]) -> DataFrame:
    """Without the elements whose value a condition names."""
    return a.where(~drop(F.col("val")))


def emul(a: DataFrame, b: DataFrame, mul=lambda x, y: x * y) -> DataFrame:
    """Element-wise product over the common pattern."""
    return a.join(b.withColumnRenamed("val", "y"), ["row", "col"]).select("row", "col", mul(F.col("val"), F.col("y")).alias("val"))


def eadd(a: DataFrame, b: DataFrame) -> DataFrame:
    """Element-wise sum over the union of the patterns."""
    j = a.join(b.withColumnRenamed("val", "y"), ["row", "col"], "full")
    return j.select("row", "col", (F.coalesce("val", F.lit(0)) + F.coalesce("y", F.lit(0))).alias("val"))


def ediff(a: DataFrame, b: DataFrame) -> DataFrame:
    """Elements of ``a`` outside the pattern of ``b``."""
    return a.join(b.select("row", "col"), ["row", "col"], "left_anti")


def reduce(a: DataFrame, axis: str = "row", agg=F.sum) -> DataFrame:
    """Row or column sums, or another aggregate."""
    return a.groupBy(F.col(axis).alias("i")).agg(agg("val").alias("val"))


def mask(a: DataFrame, out: DataFrame) -> DataFrame:
    """Clear the rows and columns named in ``out.i``; indices stay."""
    return a.join(out.select(F.col("i").alias("row")), "row", "left_anti").join(out.select(F.col("i").alias("col")), "col", "left_anti").select("row", "col", "val")


def extract(a: DataFrame, rows: DataFrame, cols: DataFrame) -> DataFrame:
    """The submatrix of two index sets."""
    return a.join(rows.select(F.col("i").alias("row")), "row", "left_semi").join(cols.select(F.col("i").alias("col")), "col", "left_semi").select("row", "col", "val")


def blocks(a: DataFrame, n: int, grid: int) -> DataFrame:
    """Elements per block of a ``grid`` x ``grid`` layout of an n x n matrix."""
    size = -(-n // grid)
    at = lambda c: F.expr(f"cast({c} div {size} as long)")
    return a.groupBy(at("row").alias("bi"), at("col").alias("bj")).agg(F.count("*").alias("nnz"))


def props(a: DataFrame) -> DataFrame:
    """Elements, rows, columns, bandwidth, and how many elements lack their mirror."""
    lone = a.join(transpose(a).select("row", "col"), ["row", "col"], "left_anti").agg(F.count("*").alias("lone"))
    main = a.agg(F.count("*").alias("nnz"), F.count_distinct("row").alias("n_rows"), F.count_distinct("col").alias("n_cols"), F.max(F.abs(F.col("row") - F.col("col"))).alias("bandwidth"))
    return main.join(F.broadcast(lone), F.lit(True), "inner")
