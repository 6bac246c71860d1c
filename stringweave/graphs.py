"""String graphs that the given tables hold ready-made."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def orders(lineitem: DataFrame) -> DataFrame:
    """Orders that share a (part, supplier): the upper triangle of a matrix times its transpose."""
    a = lineitem.select("l_orderkey", "l_partkey", "l_suppkey").distinct()
    u, v = a.withColumnRenamed("l_orderkey", "u"), a.withColumnRenamed("l_orderkey", "v")
    return u.join(v, ["l_partkey", "l_suppkey"]).where("u < v").groupBy("u", "v").agg(F.count("*").alias("n_shared"))


def sessions(events: DataFrame, minutes: int) -> DataFrame:
    """A user's neighbouring events at most some minutes apart."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = events.select("event_id", F.lead("event_id").over(w).alias("v"), F.unix_micros(F.col("ts").cast("timestamp")).alias("t"), F.unix_micros(F.lead("ts").over(w).cast("timestamp")).alias("t2"))
    return e.where((F.col("t2") - F.col("t")) <= minutes * 60_000_000).select(F.col("event_id").alias("u"), "v")


def customers(orders_table: DataFrame) -> DataFrame:
    """A customer's neighbouring orders by date and key."""
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return orders_table.select(F.col("o_orderkey").alias("u"), F.lead("o_orderkey").over(w).alias("v")).where("v is not null")


#: Room for the turns of one conversation in the number of a turn.
TURNS = 1_000_000_000


def conversations(turns: DataFrame) -> DataFrame:
    """Neighbouring turns as reads that follow one another whole: ``u, v, u_end, v_end, pre, post``.

    Turns meet inside their conversation; a turn's number is the conversation's times TURNS, plus the turn.
    """
    t = turns.select("conv_id", "turn", (F.col("conv_id") * TURNS + F.col("turn")).alias("u"), F.length("text").alias("n"))
    nxt = t.select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("u").alias("v"), F.col("n").alias("m"))
    j = t.join(nxt, ["conv_id", "turn"]).select("u", "v", "n", "m")
    fore = j.select("u", "v", F.lit(1).alias("u_end"), F.lit(0).alias("v_end"), (F.col("n") - 1).alias("pre"), F.lit(0).alias("post"))
    back = j.select(F.col("v").alias("u"), F.col("u").alias("v"), F.lit(0).alias("u_end"), F.lit(1).alias("v_end"), F.lit(0).alias("pre"), (F.col("n") - 1).alias("post"))
    return fore.unionByName(back)


#: Vectors of one label that are held against one another at once.
BLOCK = 4096


def _matrix(table: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ids, vectors and which of them are whole; those that are null or hold a null are zeros."""
    table = table.sort_by("vec_id")
    col = table["e"].combine_chunks()
    whole = np.array([x is not None and None not in x for x in col.to_pylist()], bool) if col.null_count or col.flatten().null_count else np.ones(len(col), bool)
    some = col.filter(pa.array(whole))
    lengths = np.unique(pc.list_value_length(some).to_numpy(zero_copy_only=False))
    if len(lengths) > 1:
        raise ValueError("vectors of different lengths have no cosine")
    e = np.zeros((len(col), int(lengths[0]) if len(lengths) else 0))
    e[whole] = some.flatten().to_numpy(zero_copy_only=False).reshape(len(some), -1)
    return table["vec_id"].to_numpy(), e, whole


def _firsts(e: np.ndarray, whole: np.ndarray, n: int) -> np.ndarray:
    """Places of the first ``n`` of every group of equal vectors; the others of a group come after them in any order of likeness."""
    raw = np.concatenate((e, whole[:, None]), axis=1)
    _, group = np.unique(np.ascontiguousarray(raw).view(f"V{8 * raw.shape[1]}").ravel(), return_inverse=True)
    order = np.argsort(group, kind="stable")
    sizes = np.bincount(group)
    place = np.arange(len(group)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
    return np.sort(order[place < n])


def _nearest(left: pa.Table, right: pa.Table, k: int) -> pa.Table:
    """The ``k`` nearest of every left vector among the right ones.  Matrix products leave few pairs; these are computed number by number in their order, so equal ones stay equal."""
    (u, x, xw), (v, y, yw) = _matrix(left), _matrix(right)
    if x.shape[1] and y.shape[1] and x.shape[1] != y.shape[1]:
        raise ValueError("vectors of different lengths have no cosine")
    d = max(x.shape[1], y.shape[1])
    x, y = (a if a.shape[1] else np.zeros((len(a), d)) for a in (x, y))
    keep = _firsts(y, yw, k + 1)
    v, y, yw = v[keep], y[keep], yw[keep]
    out, place = [], np.arange(len(v))
    with np.errstate(all="ignore"):
        squares = [sum((a[:, i] * a[:, i] for i in range(d)), np.zeros(len(a))) for a in (x, y)]
        unit_x, unit_y = (a / np.sqrt(s)[:, None] for a, s in zip((x, y), squares))
        for a in range(0, len(u), 512):
            b = min(len(u), a + 512)
            s = unit_x[a:b] @ unit_y.T
            s = np.where(np.isnan(s), 3 + len(v) - place, s)  # as the largest, as in an ORDER BY, and the smallest id first
            s[~xw[a:b]] = -3 - place
            s[:, ~yw] = -3 - place[~yw]
            s[u[a:b, None] == v[None, :]] = -np.inf
            bound = np.partition(s, -k, axis=1)[:, -k] if s.shape[1] >= k else np.full(b - a, -np.inf)
            i, j = np.nonzero((s >= bound[:, None] - 1e-9) & (s > -np.inf))
            exact = np.zeros(len(i))
            for c in range(d):
                exact += x[a + i, c] * y[j, c]
            exact = exact / np.sqrt(squares[0][a + i] * squares[1][j])
            exact = np.where(np.isnan(exact), exact, np.clip(exact, -1, 1))
            none = ~(xw[a + i] & yw[j])
            order = np.lexsort((v[j], -exact, ~np.isnan(exact), none, i))
            i, j, exact, none = i[order], j[order], exact[order], none[order]
            first = np.concatenate(([0], np.flatnonzero(i[1:] != i[:-1]) + 1)) if len(i) else np.zeros(0, np.int64)
            top = np.arange(len(i)) - np.repeat(first, np.diff(first, append=len(i))) < k
            out.append(pa.table({"u": u[a + i[top]], "v": v[j[top]], "sim": pa.array(exact[top], pa.float64(), mask=none[top])}))
    return pa.concat_tables(out)


def neighbours(embeddings: DataFrame, k: int = 2) -> DataFrame:
    """Vectors of one label that are mutually among each other's ``k`` nearest by cosine: ``u, v, sim``.

    A label is cut into blocks of about BLOCK vectors, of which every two meet in a task; a task passes on the ``k``
    nearest it has seen of every vector, not the pairs.
    """
    e = embeddings.where("label is not null").select(F.col("vec_id").cast("long").alias("vec_id"), "label", F.col("embedding").cast("array<double>").alias("e"))
    blocks = e.groupBy("label").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("n"))
    cut = e.join(blocks, "label").withColumn("own", F.pmod(F.xxhash64("vec_id"), F.col("n")).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.col("n") - 1))
    names = ["label", "i", "j", "vec_id", "e"]  # toDF: columns of their own for either side
    a, b = cut.select("label", "own", other, "vec_id", "e").toDF(*names), cut.select("label", other, "own", "vec_id", "e").toDF(*names)

    def near(left: pa.Table, right: pa.Table) -> pa.Table:
        if not left.num_rows or not right.num_rows:
            return pa.table({"u": pa.array([], pa.int64()), "v": pa.array([], pa.int64()), "sim": pa.array([], pa.float64())})
        return _nearest(left, right, k)

    s = a.groupBy("label", "i", "j").cogroup(b.groupBy("label", "i", "j")).applyInArrow(near, "u long, v long, sim double")
    top = s.withColumn("r", F.row_number().over(Window.partitionBy("u").orderBy(F.desc("sim"), "v"))).where(F.col("r") <= k)
    return top.join(top.select(F.col("v").alias("u"), F.col("u").alias("v")), ["u", "v"], "left_semi").where("u < v").select("u", "v", "sim")
