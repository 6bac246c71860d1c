"""From a string graph to contigs: mask, components, sizes, owners, one move, local walks."""

from __future__ import annotations

import heapq
import time
from collections.abc import Iterable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from stringweave.functions.dna import oslice
from stringweave.operators.contraction import contract_components
from stringweave.session import Scratch

#: Contigs assigned on the driver at most; beyond, the histogram form is used, or tasks assign theirs as they come.
DRIVER_LPT = 2_000_000
#: Contigs of one size that one task ranks in the histogram form, on average.
RANK_ROWS = 100_000
#: Bases that one owner walks and spells, and the fewest owners.
OWNER_BASES, LEAST_OWNERS = 1 << 28, 16


def both_ways(pairs: DataFrame) -> DataFrame:
    """``(u, v)`` and ``(v, u)`` of undirected pairs."""
    return pairs.select("u", "v").unionByName(pairs.select(F.col("v").alias("u"), F.col("u").alias("v"))).distinct()


def degrees(s: DataFrame) -> DataFrame:
    """Row sums of the pattern: ``(v, deg)``."""
    return s.groupBy(F.col("u").alias("v")).agg(F.count("*").alias("deg"))


def branching(deg: DataFrame, max_degree: int = 2) -> DataFrame:
    """Vertices of more than ``max_degree`` edges."""
    return deg.where(F.col("deg") > max_degree).select("v")


def branching_ends(s: DataFrame) -> DataFrame:
    """``(u, u_end)`` of read ends with more than one edge: the milder mask."""
    return s.groupBy("u", "u_end").agg(F.count("*").alias("n")).where("n > 1").select("u", "u_end")


def mask(s: DataFrame, b: DataFrame) -> DataFrame:
    """Clear rows and columns of branching vertices; ids stay."""
    return s.join(b.select(F.col("v").alias("u")), "u", "left_anti").join(b.select("v"), "v", "left_anti").select(*s.columns)


def mask_flags(s: DataFrame, deg: DataFrame, max_degree: int = 2) -> DataFrame:
    """``mask`` by flags: every edge learns the degrees of both ends and stays if neither branches.

    No list of branching vertices is made, so nothing can be broadcast; ``mask`` joins such a list, which
    adaptive execution broadcasts where it is small.
    """
    d = lambda end: deg.select(F.col("v").alias(end), (F.col("deg") > max_degree).alias(f"__{end}"))
    return s.join(d("u"), "u").join(d("v"), "v").where("not __u and not __v").select(*s.columns)


def mask_ends(s: DataFrame, ends: DataFrame) -> DataFrame:
    """Clear only the edges at branching ends, from either side."""
    twin = ends.select(F.col("u").alias("v"), F.col("u_end").alias("v_end"))
    return s.join(ends, ["u", "u_end"], "left_anti").join(twin, ["v", "v_end"], "left_anti").select(*s.columns)


def roots(l: DataFrame) -> DataFrame:
    """Vertices of degree one: where the chains begin."""
    return degrees(l).where("deg = 1").select("v")


def folded(l: DataFrame) -> DataFrame:
    """Vertices whose two edges touch one end: no valid walk passes them."""
    g = l.groupBy(F.col("u").alias("v")).agg(F.count("*").alias("n"), F.count_distinct("u_end").alias("ends"))
    return g.where("n = 2 and ends = 1").select("v")


def _smallest(labels: DataFrame) -> DataFrame:
    least = labels.groupBy("root").agg(F.min("v").alias("contig_id"))
    return labels.join(least, "root").select("v", "contig_id")


def _stars(l: DataFrame, store: Scratch, trace: list | None) -> DataFrame:
    """Large-star and small-star by turns on edges ``(u, v)`` with u > v, until the edges stay as they are."""
    now = store.keep(l.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct())
    mark = lambda df: df.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)"))).first()
    seen = mark(now)
    while True:
        both = both_ways(now)
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = store.keep(both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct())
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        near = large.join(low, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        then = store.keep(near.unionByName(low.select("u", F.col("m").alias("v"))).distinct())
        store.drop(large)
        store.drop(now)
        now, before, seen = then, seen, mark(then)
        if trace is not None:
            trace.append(seen[0])
        if seen == before:
            break
    return now.select(F.col("u").alias("v"), F.col("v").alias("contig_id")).unionByName(now.select("v", F.col("v").alias("contig_id")).distinct())


def components(l: DataFrame, method: str = "contract", skip_inactive: bool = True, trace: list | None = None) -> DataFrame:
    """``(v, contig_id)``: the smallest vertex of each connected component, for vertices with edges.

    ``contract``: random contraction.  ``hook``: hook each tree's root on the smallest
    neighbouring root, then shortcut, converged trees leaving the edge list if
    ``skip_inactive``.  ``label``: the smallest label travels one edge a round.  ``star``: every
    vertex points its larger, then its smaller neighbours at the smallest one, until all are stars.
    """
    spark = l.sparkSession
    if method == "contract":
        store = Scratch(spark, "membership")
        return _smallest(store.keep(contract_components(spark, l.select("u", "v"), trace=trace)))
    store = Scratch(spark, method)
    if method == "star":
        return _stars(l, store, trace)
    edges = store.keep(both_ways(l.where("u <> v")))
    parent = store.keep(edges.select(F.col("u").alias("v"), F.col("u").alias("p")).distinct())
    p = lambda k, a: parent.select(F.col("v").alias(k), F.col("p").alias(a))
    while True:
        if method == "label":
            best = edges.join(p("v", "q"), "v").groupBy(F.col("u").alias("v")).agg(F.min("q").alias("q"))
            then = store.keep(parent.join(best, "v").select("v", F.least("p", "q").alias("p")))
        else:
            near = edges.join(p("u", "pu"), "u").join(p("v", "pv"), "v").where("pu <> pv")
            hook = store.keep(near.groupBy(F.col("pu").alias("r")).agg(F.min("pv").alias("q")).where("q < r"))
            first = store.keep(parent.join(hook.select(F.col("r").alias("p"), "q"), "p", "left").select("v", F.coalesce("q", "p").alias("p")))
            then = store.keep(first.join(first.select(F.col("v").alias("p"), F.col("p").alias("g")), "p").select("v", F.col("g").alias("p")))
            if skip_inactive:  # edges inside one tree can hook nothing any more
                t = lambda k, a: then.select(F.col("v").alias(k), F.col("p").alias(a))
                edges = store.keep(edges.join(t("u", "pu"), "u").join(t("v", "pv"), "v").where("pu <> pv").select("u", "v"))
        moved = then.join(parent.withColumnRenamed("p", "old"), "v").where("p <> old").count()
        parent = then
        if trace is not None:
            trace.append(moved)
        if not moved:
            break
    # trees are flat once nothing moves, and their root is their smallest vertex
    return parent.select("v", F.col("p").alias("contig_id"))


def chain_ranks(l: DataFrame) -> DataFrame:
    """Components, order and direction of chains at once, by pointer doubling over arcs.

    For graphs of degree two at most.  An arc stands on a vertex and looks away from one of its
    neighbours; each round doubles how far it sees, so a chain of q vertices takes log q rounds.
    Returns ``(v, contig_id, pos, q)`` from the smaller end; vertices of cycles have no rows.
    """
    store = Scratch(l.sparkSession, "chains")
    e = store.keep(l.select("u", "v").distinct())
    # the arc (v, away) leaves v to its other neighbour; a chain's end has the arc (v, null)
    nb = e.groupBy(F.col("u").alias("v")).agg(F.min("v").alias("a"), F.max("v").alias("b"))
    ends = nb.where("a = b").select("v", F.lit(None).cast("long").alias("away"), F.col("a").alias("to"))
    stops = nb.where("a = b").select("v", F.col("a").alias("away"), F.lit(None).cast("long").alias("to"))
    inner = nb.where("a <> b")
    arcs = ends.unionByName(stops).unionByName(inner.select("v", F.col("a").alias("away"), F.col("b").alias("to"))).unionByName(inner.select("v", F.col("b").alias("away"), F.col("a").alias("to")))
    # where an arc leads: the vertex it leaves for, looking away from the vertex it came from
    now = store.keep(arcs.select("v", "away", F.col("to").alias("nv"), F.when(F.col("to").isNotNull(), F.col("v")).alias("na"), F.when(F.col("to").isNull(), 0).otherwise(1).cast("long").alias("steps"), F.coalesce("to", "v").alias("last")))
    for _ in range(now.count().bit_length()):  # whatever has not met an end by then is a cycle
        if not now.where("nv is not null").limit(1).count():
            break
        nxt = now.select(F.col("v").alias("nv"), F.col("away").alias("na"), F.col("nv").alias("nv2"), F.col("na").alias("na2"), F.col("steps").alias("s2"), F.col("last").alias("last2"))
        then, done = now.join(nxt, ["nv", "na"], "left"), F.col("nv").isNull()
        then = store.keep(
            then.select(
                "v", "away", F.when(~done, F.col("nv2")).alias("nv"), F.when(~done, F.col("na2")).alias("na"),
                (F.col("steps") + F.when(done, 0).otherwise(F.coalesce("s2", F.lit(0)))).alias("steps"),
                F.when(done, F.col("last")).otherwise(F.coalesce("last2", "last")).alias("last"),
            )
        )
        store.drop(now)
        now = then
    both = now.where("nv is null").groupBy("v").agg(F.min(F.struct("last", "steps")).alias("lo"), F.max(F.struct("last", "steps")).alias("hi"))
    return both.where("lo.last <> hi.last").select("v", F.col("lo.last").alias("contig_id"), F.col("lo.steps").cast("long").alias("pos"), (F.col("lo.steps") + F.col("hi.steps") + 1).cast("long").alias("q"))


def cycles(l: DataFrame, membership: DataFrame) -> DataFrame:
    """Components of as many edges as vertices: no chain begins in them."""
    n = membership.groupBy("contig_id").agg(F.count("*").alias("n"))
    m = l.join(membership.select(F.col("v").alias("u"), "contig_id"), "u").groupBy("contig_id").agg((F.count("*") / 2).cast("long").alias("m"))
    return n.join(m, "contig_id").where("n = m").select("contig_id", "n")


def sizes(membership: DataFrame, reads: DataFrame | None = None) -> DataFrame:
    """``(contig_id, n)``: reads of each contig, or bases where reads with ``len`` are given."""
    if reads is None:
        return membership.groupBy("contig_id").agg(F.count("*").alias("n"))
    return membership.join(reads.select(F.col("read_id").alias("v"), "len"), "v").groupBy("contig_id").agg(F.sum("len").alias("n"))


def lpt(items: Iterable[tuple[int, int]], owners: int, ordered: bool = True) -> list[tuple[int, int]]:
    """Greedy assignment of ``(id, size)`` to the least-loaded owner, largest first if ``ordered``.

    Ties go to the smaller id and the smaller owner.  Sorted, the largest load is at most
    (4P-1)/(3P) times the best possible; unsorted, 2-1/P times.
    """
    line = sorted(items, key=lambda x: (-x[1], x[0])) if ordered else sorted(items)
    heap = [(0, o) for o in range(owners)]
    out = []
    for i, n in line:
        load, o = heap[0]
        heapq.heapreplace(heap, (load + n, o))
        out.append((i, o))
    return out


def lpt_runs(runs: Iterable[tuple[int, int]], owners: int) -> list[tuple[int, list[int]]]:
    """LPT over runs ``(size, count)``: how many items of each size every owner gets.

    A run of equal sizes fills the lowest of the places load + i * size; a bisection finds the level
    up to which all are taken.  The loads are those of the heap.
    """
    loads, out = [0] * owners, []
    for s, c in sorted(runs, reverse=True):
        if s == 0:
            out.append((s, [c] + [0] * (owners - 1)))
            continue
        below = lambda t: sum(max(0, -(-(t - x) // s)) for x in loads)  # noqa: E731  places under level t
        lo, hi = min(loads), max(loads) + s * (c + 1)
        while lo < hi:
            mid = (lo + hi + 1) // 2
            lo, hi = (mid, hi) if below(mid) <= c else (lo, mid - 1)
        got = [max(0, -(-(lo - x) // s)) for x in loads]
        rest = c - sum(got)
        for o in range(owners):
            if rest and loads[o] + got[o] * s == lo:
                got[o] += 1
                rest -= 1
        loads = [x + g * s for x, g in zip(loads, got)]
        out.append((s, got))
    return out


def assign(contig_sizes: DataFrame, owners: int, ordered: bool = True, where: str = "auto") -> DataFrame:
    """``(contig_id, owner)``.  Contigs are few against reads; beyond DRIVER_LPT of them only their
    histogram of sizes reaches the driver, and items of one size are dealt by their rank.  Unordered,
    every task then deals its own contigs as they come, to owners empty at its beginning."""
    spark = contig_sizes.sparkSession
    if where == "auto":
        where = "driver" if contig_sizes.limit(DRIVER_LPT + 1).count() <= DRIVER_LPT else "histogram"
    if where == "histogram" and not ordered:

        def deal(batches):
            heap = [(0, o) for o in range(owners)]
            for b in batches:
                got = []
                for n in b.column(1).to_pylist():
                    load, o = heap[0]
                    heapq.heapreplace(heap, (load + n, o))
                    got.append(o)
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(got, pa.int32())], names=["contig_id", "owner"])

        return contig_sizes.select(F.col("contig_id").cast("long").alias("contig_id"), F.col("n").cast("long").alias("n")).mapInArrow(deal, "contig_id long, owner int")
    if where == "driver":
        rows = lpt(((r.contig_id, r.n) for r in contig_sizes.select("contig_id", "n").collect()), owners, ordered)
        return spark.createDataFrame(rows, "contig_id long, owner int")
    runs = [(r.n, r.c) for r in contig_sizes.groupBy("n").agg(F.count("*").alias("c")).collect()]
    spans, at = [], {}
    for s, got in lpt_runs(runs, owners):
        at[s] = 0
        for o, g in enumerate(got):
            if g:
                spans.append((s, at[s], at[s] + g, o))
                at[s] += g
    table = spark.createDataFrame(spans, "n long, lo long, hi long, owner int")
    # ranks inside a size: cells by hash, so that no task ranks all contigs of a common size
    cells = max(1, max((c for _, c in runs), default=0) // RANK_ROWS)
    celled = contig_sizes.withColumn("cell", F.pmod(F.xxhash64("contig_id"), F.lit(cells)))
    before = Window.partitionBy("n").orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)
    first = celled.groupBy("n", "cell").agg(F.count("*").alias("held")).select("n", "cell", F.coalesce(F.sum("held").over(before), F.lit(0)).alias("first"))
    own = F.row_number().over(Window.partitionBy("n", "cell").orderBy("contig_id")) - 1
    ranked = celled.withColumn("own", own).join(first, ["n", "cell"]).withColumn("i", F.col("first") + F.col("own"))
    return ranked.join(table, "n").where("i >= lo and i < hi").select("contig_id", "owner")


def placement(membership: DataFrame, assignment: DataFrame) -> DataFrame:
    """``(v, owner)``; a missing owner is an error, since a null would silently go to partition 0."""
    return membership.join(assignment, "contig_id", "left").select("v", F.coalesce("owner", F.raise_error(F.lit("contig without owner")).cast("int")).alias("owner"))


def induced(l: DataFrame, place: DataFrame, sides: int = 2) -> DataFrame:
    """Edges whose ends have one owner, with it.  ``sides=1`` is enough when the map is constant on components."""
    j = l.join(place.select(F.col("v").alias("u"), F.col("owner")), "u")
    if sides == 2:
        j = j.join(place.select("v", F.col("owner").alias("owner2")), "v").where("owner = owner2")
    return j.select("owner", *l.columns)


def induced_by_grid(l: DataFrame, place: DataFrame, n: int, grid: int) -> tuple[DataFrame, DataFrame]:
    """The induced subgraph by the grid's two exchanges, and what each process receives.

    A process of block (i, j) needs the owners of rows i, gathered along its row, and of columns j,
    which its transpose partner holds; blocks on the diagonal need no partner.
    """
    size = -(-n // grid)
    e = l.withColumn("bi", F.expr(f"u div {size}")).withColumn("bj", F.expr(f"v div {size}"))
    by_row = place.select(F.expr(f"v div {size}").alias("bi"), F.col("v").alias("u"), "owner")
    by_col = place.select(F.expr(f"v div {size}").alias("bj"), "v", F.col("owner").alias("owner2"))
    out = e.join(by_row, ["bi", "u"]).join(by_col, ["bj", "v"]).where("owner = owner2").select("owner", *l.columns)
    spark = l.sparkSession
    per_block = by_row.groupBy("bi").agg(F.count("*").alias("held"))
    pairs = spark.range(grid * grid).select(F.expr(f"id div {grid}").alias("bi"), (F.col("id") % grid).alias("bj"))
    cost = pairs.join(per_block, "bi").join(per_block.select(F.col("bi").alias("bj"), F.col("held").alias("other")), "bj")
    return out, cost.select("bi", "bj", (F.col("held") + F.when(F.col("bi") == F.col("bj"), 0).otherwise(F.col("other"))).alias("received"))


def induced_by_all_gather(l: DataFrame, place: DataFrame, n: int, grid: int) -> tuple[DataFrame, DataFrame]:
    """The induced subgraph where every process holds the whole vertex map, and what each receives: the baseline of the grid.

    The map is copied once per process and met there, as a gather of all by all would leave it.
    """
    size = -(-n // grid)
    spark = l.sparkSession
    procs = spark.range(grid * grid).select(F.expr(f"id div {grid}").alias("bi"), (F.col("id") % grid).alias("bj"))
    copies = place.select("v", "owner", F.explode(F.sequence(F.lit(0), F.lit(grid * grid - 1))).alias("proc"))
    e = l.withColumn("proc", F.expr(f"cast((u div {size}) * {grid} + v div {size} as int)"))
    one, two = copies.select("proc", F.col("v").alias("u"), "owner"), copies.select("proc", "v", F.col("owner").alias("owner2"))
    out = e.join(one, ["proc", "u"]).join(two, ["proc", "v"]).where("owner = owner2").select("owner", *l.columns)
    held = place.agg(F.count("*").alias("received"))
    return out, procs.join(held, F.lit(True)).select("bi", "bj", "received")


def to_owner(df: DataFrame, owners: int) -> DataFrame:
    """One bulk move: the rows of an owner to the partition of its number."""
    return df.repartitionById(owners, F.col("owner"))


def reindex(edges: DataFrame) -> DataFrame:
    """Local numbers of an owner's vertices: ``(owner, lid, v)``, in the order of global ids."""
    w = Window.partitionBy("owner").orderBy("v")
    return edges.select("owner", F.col("u").alias("v")).distinct().select("owner", (F.row_number().over(w) - 1).alias("lid"), "v")


def csc(edges: DataFrame) -> DataFrame:
    """Compressed columns per owner: column pointers and row indices in local numbers.

    An owner's edges are numbered, sorted and summed in one pass over arrays, so its cost follows their sort.
    """

    def work(t: pa.Table) -> pa.Table:
        u, v = t.column("u").to_numpy(), t.column("v").to_numpy()
        ids = np.unique(u)
        c = np.minimum(np.searchsorted(ids, v), len(ids) - 1)
        inner = ids[c] == v
        r, c = np.searchsorted(ids, u[inner]), c[inner]
        held = np.unique(c, return_counts=True)[1]
        jc, ir = np.concatenate(([0], np.cumsum(held))), r[np.lexsort((r, c))]
        n = 1 if len(ir) else 0
        lists = [pa.array([x.astype(np.int32)][:n], pa.list_(pa.int32())) for x in (jc, ir)]
        return pa.Table.from_arrays([t.column("owner").slice(0, n), *lists], names=["owner", "jc", "ir"])

    kind = edges.schema["owner"].dataType.simpleString()
    known = edges.where("owner is not null and u is not null and v is not null")
    long = known.select("owner", F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v"))
    return long.groupBy("owner").applyInArrow(work, f"owner {kind}, jc array<int>, ir array<int>")


def dcsc(edges: DataFrame) -> DataFrame:
    """Doubly compressed columns: a row per non-empty column."""
    return edges.groupBy(F.col("v").alias("col")).agg(F.array_sort(F.collect_list("u")).alias("rows"))


def decompressed(d: DataFrame, n: int) -> DataFrame:
    """Doubly compressed columns to plain ones: a pointer for each of ``n`` columns, empty ones included.

    One row ``(jc, ir)``, so for the matrix of one owner, in local numbers.
    """
    all_cols = d.sparkSession.range(n).select(F.col("id").alias("col"))
    full = all_cols.join(d, "col", "left").select("col", F.coalesce("rows", F.array().cast("array<long>")).alias("rows"))
    cols = full.agg(F.array_sort(F.collect_list(F.struct("col", "rows"))).alias("cols"))
    ptr = F.aggregate("cols", F.array(F.lit(0)), lambda acc, x: F.concat(acc, F.array(F.element_at(acc, -1) + F.size(x["rows"]))))
    return cols.select(ptr.alias("jc"), F.flatten(F.transform("cols", lambda x: x["rows"])).alias("ir"))


def ship_reads(reads: DataFrame, place: DataFrame, chunk: int = 1 << 26) -> DataFrame:
    """Bases of placed reads with their owner, in pieces below the row limit: ``(owner, read_id, part, seq)``."""
    j = reads.join(place.select(F.col("v").alias("read_id"), "owner"), "read_id")
    parts = F.sequence(F.lit(0), F.greatest(F.lit(0), F.expr(f"(length(seq) - 1) div {chunk}")))
    return j.select("owner", "read_id", "seq", F.explode(parts).alias("part")).select("owner", "read_id", "part", F.substring("seq", (F.col("part") * chunk + 1).cast("int"), F.lit(chunk)).alias("seq"))


_COMP = str.maketrans("ACGT", "TGCA")


def spell(steps: list[tuple[str, bool, int, int]]) -> tuple[str, bool]:
    """Concatenate pieces ``(sequence, reversed, first, last)``, both bases included, in walking order.

    A negative piece counts as empty and raises the flag.
    """
    out, overrun = [], False
    for seq, rev, first, last in steps:
        if rev:
            n = first - last + 1
            out.append(seq[last : first + 1][::-1].translate(_COMP) if n > 0 else "")
        else:
            n = last - first + 1
            out.append(seq[first : last + 1] if n > 0 else "")
        overrun |= n < 0
    return "".join(out), overrun


CONTIG = "owner int, contig_id long, n_reads long, len long, overrun boolean, invalid_walk boolean, cyclic boolean, seq string, reads array<long>"


def walk_owner(edges: list[dict], seqs: dict[int, str], cycle: str = "drop", strict: bool = False) -> list[dict]:
    """Walk every chain of one owner from its smaller root and spell it."""
    near: dict[int, list[dict]] = {}
    for e in edges:
        near.setdefault(e["u"], []).append(e)
    if strict:
        bad = {u for u, es in near.items() if len(es) == 2 and es[0]["u_end"] == es[1]["u_end"]}
        near = {u: [e for e in es if u not in bad and e["v"] not in bad] for u, es in near.items()}
        near = {u: es for u, es in near.items() if es}
    done, out = set(), []

    def go(root: int, cyclic: bool) -> None:
        chain, invalid, at, before, came = [], False, root, None, None
        if cyclic:  # cut before the smallest id: the edge to its larger neighbour is not walked
            cut = max(e["v"] for e in near[root])
        while True:
            done.add(at)
            step = [e for e in near[at] if e["v"] != before and not (cyclic and at == root and e["v"] == cut)]
            nxt = step[0] if step and not (cyclic and step[0]["v"] == root) else None
            if came is None:
                rev = nxt is not None and nxt["u_end"] == 0
                first = len(seqs[at]) - 1 if rev else 0
            else:
                rev, first = came["v_end"] == 1, came["post"]
                invalid |= nxt is not None and nxt["u_end"] == came["v_end"]
            last = nxt["pre"] if nxt is not None else (0 if rev else len(seqs[at]) - 1)
            chain.append((at, rev, first, last))
            if nxt is None:
                break
            before, at, came = at, nxt["v"], nxt
        seq, overrun = spell([(seqs[v], r, a, b) for v, r, a, b in chain])
        out.append({"contig_id": min(c[0] for c in chain), "n_reads": len(chain), "len": len(seq), "overrun": overrun, "invalid_walk": invalid, "cyclic": cyclic, "seq": seq, "reads": [c[0] for c in chain]})

    for v in sorted(near):
        if len(near[v]) == 1 and v not in done:
            go(v, False)
    for v in sorted(near):
        if v not in done and cycle != "drop":
            go(v, True)
    return out


def local_assembly(edges: DataFrame, bases: DataFrame, owners: int, cycle: str = "drop", strict: bool = False) -> DataFrame:
    """Walk and spell all chains, owner by owner; nothing is exchanged after the two bulk moves.

    ``edges`` are ``(owner, u, v, u_end, v_end, pre, post)``, ``bases`` are ``(owner, read_id, part, seq)``.
    """
    e = to_owner(edges.select(F.col("owner").alias("owner"), "u", "v", "u_end", "v_end", "pre", "post"), owners)
    b = to_owner(bases.select(F.col("owner").alias("owner"), "read_id", "part", "seq"), owners)
    names = [f.split()[0] for f in CONTIG.split(", ")]

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        parts: dict[int, list] = {}
        for r in right.sort_by([("read_id", "ascending"), ("part", "ascending")]).to_pylist():
            parts.setdefault(r["read_id"], []).append(r["seq"])
        found = walk_owner(left.to_pylist(), {k: "".join(v) for k, v in parts.items()}, cycle, strict) if left.num_rows else []
        owner = left["owner"][0].as_py() if left.num_rows else 0
        kinds = {"owner": pa.int32(), "overrun": pa.bool_(), "invalid_walk": pa.bool_(), "cyclic": pa.bool_(), "seq": pa.string(), "reads": pa.list_(pa.int64())}
        rows = [{"owner": owner} | r for r in found]
        return pa.table({n: pa.array([r[n] for r in rows], kinds.get(n, pa.int64())) for n in names})

    return e.groupBy("owner").cogroup(b.groupBy("owner")).applyInArrow(run, CONTIG)


def owners_for(reads: DataFrame) -> int:
    """Owners such that each has OWNER_BASES on average, LEAST_OWNERS at least."""
    bases = reads.agg(F.sum(F.length("seq").cast("long"))).first()[0] or 0
    return max(LEAST_OWNERS, -(-bases // OWNER_BASES))


def spell_relational(l: DataFrame, reads: DataFrame) -> DataFrame:
    """Contigs of a graph of degree two at most without an owner: ranks, pieces and one ordered concatenation.

    ``(contig_id, n_reads, len, seq)`` of chains, from the smaller end; the engine for chains too long
    for one owner's memory while walking.  ``l`` is ``(u, v, u_end, v_end, pre, post)``.
    """
    at = Scratch(l.sparkSession, "spelling").keep(chain_ranks(l))
    step = l.join(at.select(F.col("v").alias("u"), "contig_id", F.col("pos").alias("pu")), "u").join(at.select("v", F.col("pos").alias("pv")), "v").where("pv = pu + 1")
    out = step.select(F.col("u").alias("v"), F.col("u_end").alias("exit_end"), "pre")
    came = step.select("v", F.col("v_end").alias("entry_end"), "post")
    p = at.join(out, "v", "left").join(came, "v", "left").join(reads.select(F.col("read_id").alias("v"), "seq"), "v")
    rev = F.coalesce(F.col("entry_end") == 1, F.col("exit_end") == 0, F.lit(False))
    n = F.length("seq")
    first = F.coalesce("post", F.when(rev, n - 1).otherwise(0))
    last = F.coalesce("pre", F.when(rev, 0).otherwise(n - 1))
    piece = oslice("seq", F.when(rev, last).otherwise(first), F.when(rev, first).otherwise(last), rev)
    g = p.select("contig_id", "pos", piece.alias("piece")).groupBy("contig_id").agg(F.count("*").alias("n_reads"), F.array_sort(F.collect_list(F.struct("pos", "piece"))).alias("x"))
    seq = F.array_join(F.transform("x", lambda y: y["piece"]), "")
    return g.select("contig_id", "n_reads", F.length(seq).cast("long").alias("len"), seq.alias("seq"))


def generate_contigs(s: DataFrame, reads: DataFrame, owners: int | None = None, branch: str = "vertex", method: str = "contract", weight: str = "reads", ordered: bool = True, cycle: str = "drop", strict: bool = False, singletons: str = "drop", max_degree: int = 2, seconds: dict | None = None) -> DataFrame:
    """The contig stage on a string graph ``(u, v, u_end, v_end, pre, post)``: see CONTIG for what it returns.

    ``branch`` is vertex (a list of branching vertices), flags (degrees on every edge) or end.
    ``singletons="keep"`` adds the vertices that the mask left without an edge, each as a contig of one read.
    Without ``owners`` their number follows the bases.  ``seconds`` receives what every step took, under
    names that begin with ``contig:``; the induced subgraph and the reads are then written to be timed.
    """
    store, took = Scratch(s.sparkSession, "contigs"), {} if seconds is None else seconds

    def step(name, df):
        began = time.time()
        out = store.keep(df)
        took[f"contig:{name}"] = took.get(f"contig:{name}", 0) + time.time() - began
        return out

    owners = owners or owners_for(reads)
    s = store.keep(s.select("u", "v", "u_end", "v_end", "pre", "post"))
    masked = {"vertex": lambda: mask(s, branching(degrees(s), max_degree)), "flags": lambda: mask_flags(s, degrees(s), max_degree), "end": lambda: mask_ends(s, branching_ends(s))}
    l = step("branch removal", masked[branch]())
    member = step("components", components(l, method))
    size = sizes(member, reads if weight == "bases" else None)
    place = step("partitioning", placement(member, assign(size, owners, ordered)))
    own, bases = induced(l, place, sides=1), ship_reads(reads, place)
    if seconds is not None:
        own, bases = step("induced subgraph", own), step("read exchange", bases)
    out = local_assembly(own, bases, owners, cycle, strict)
    return out if singletons == "drop" else out.unionByName(lone(s, l, reads, owners))


def lone(s: DataFrame, l: DataFrame, reads: DataFrame, owners: int) -> DataFrame:
    """Vertices of ``s`` without an edge in ``l``, as contigs of one read; ids deal them to owners, as all weigh one."""
    v = s.select(F.col("u").alias("read_id")).distinct().join(l.select(F.col("u").alias("read_id")).distinct(), "read_id", "left_anti")
    no = F.lit(False)
    return reads.join(v, "read_id").select(
        F.pmod("read_id", F.lit(owners)).cast("int").alias("owner"), F.col("read_id").alias("contig_id"), F.lit(1).cast("long").alias("n_reads"), F.length("seq").cast("long").alias("len"),
        no.alias("overrun"), no.alias("invalid_walk"), no.alias("cyclic"), "seq", F.array("read_id").alias("reads"),
    )


def load_report(contig_sizes: DataFrame, assignment: DataFrame, owners: int) -> DataFrame:
    """Load of every owner, idle ones included."""
    spark: SparkSession = contig_sizes.sparkSession
    load = contig_sizes.join(assignment, "contig_id").groupBy("owner").agg(F.sum("n").alias("load"), F.count("*").alias("contigs"))
    all_owners = spark.range(owners).select(F.col("id").cast("int").alias("owner"))
    return all_owners.join(load, "owner", "left").fillna(0, ["load", "contigs"])
