"""What the distributed pipeline is compared with."""

from __future__ import annotations

import time
from collections import defaultdict
from itertools import product

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stringweave.functions.dna import revcomp as revcomp_col
from stringweave.operators.contigs import roots
from stringweave.session import Scratch

_COMP = str.maketrans("ACGT", "TGCA")


def revcomp(s: str) -> str:
    return s.translate(_COMP)[::-1]


def union_find(edges) -> dict[int, int]:
    """Exact serial components: smallest member of each vertex's component."""
    up: dict[int, int] = {}

    def top(x):
        while up.setdefault(x, x) != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    for a, b in edges:
        a, b = sorted((top(a), top(b)))
        up[b] = a
    return {v: top(v) for v in list(up)}


def optimal_makespan(sizes: list[int], owners: int) -> int:
    """The smallest possible largest load, by trying all assignments of a few items."""
    return min(max(sum(s for s, o in zip(sizes, pick) if o == k) for k in range(owners)) for pick in product(range(owners), repeat=len(sizes)))


def hash_assign(contig_sizes: DataFrame, owners: int) -> DataFrame:
    """Owners by hash, blind to sizes."""
    return contig_sizes.select("contig_id", F.pmod(F.col("contig_id"), F.lit(owners)).cast("int").alias("owner"))


def round_robin(contig_sizes: DataFrame, owners: int) -> DataFrame:
    """Owners in turn by id, blind to sizes."""
    from pyspark.sql import Window

    rank = F.row_number().over(Window.partitionBy(F.lit(1)).orderBy("contig_id")) - 1
    return contig_sizes.select("contig_id", F.pmod(rank, F.lit(owners)).cast("int").alias("owner"))


def remote_walk(l: DataFrame) -> DataFrame:
    """Every chain one hop a round: a distributed look-up per step, as many rounds as the longest chain.

    Returns ``(v, root, pos)`` from the smaller root of each chain.
    """
    store = Scratch(l.sparkSession, "remote-walk")
    e = store.keep(l.select("u", "v").distinct())
    front = store.keep(roots(l).select(F.col("v").alias("root"), F.col("v"), F.lit(None).cast("long").alias("before"), F.lit(0).alias("pos")))
    seen = front
    while front.limit(1).count():
        step = front.join(e.withColumnRenamed("v", "w"), front["v"] == e["u"]).where("before is null or w <> before")
        front = store.keep(step.select("root", F.col("w").alias("v"), F.col("u").alias("before"), (F.col("pos") + 1).alias("pos")))
        seen = seen.unionByName(front)
    return seen.groupBy("v").agg(F.min(F.struct("root", "pos")).alias("x")).select("v", "x.root", F.col("x.pos").cast("long").alias("pos"))


def all_pairs(reads: DataFrame, k: int) -> DataFrame:
    """Pairs of reads that share a word of ``k`` bases on either strand, every pair compared.  For small inputs only."""
    word = lambda i: F.substring(F.col("seq"), i, F.lit(k))
    both = lambda w: F.least(w, revcomp_col(w))
    words = F.array_distinct(F.transform(F.sequence(F.lit(1), F.length("seq") - k + 1), lambda i: both(word(i))))
    r = reads.where(F.length("seq") >= k).select("read_id", words.alias("words"))
    r = Scratch(reads.sparkSession, "all-pairs").keep(r)
    j = r.toDF("u", "wu").join(r.toDF("v", "wv"), F.col("u") < F.col("v"))
    return j.where(F.arrays_overlap("wu", "wv")).select("u", "v")


def single_node(reads: list[tuple[int, str]], min_overlap: int, corrected: bool = False, budget_s: float | None = None) -> list[str]:
    """A greedy assembler in one process: longest exact overlaps are merged first.

    ``corrected`` first replaces a base if no other read has any of the words around it and the new one makes all of them known.  Returns None-free
    contigs; with ``budget_s`` it stops where time is up and returns what it has.
    """
    began = time.time()
    seqs = {i: s for i, s in reads}
    k = min(min_overlap, 15)
    if corrected:
        count: dict[str, int] = defaultdict(int)
        for s in seqs.values():
            for i in range(len(s) - k + 1):
                w = s[i : i + k]
                count[min(w, revcomp(w))] += 1
        good = lambda w: count.get(min(w, revcomp(w)), 0) > 1
        for r, s in seqs.items():
            weak = [not good(s[i : i + k]) for i in range(len(s) - k + 1)]
            for at in range(k - 1, len(s) - k + 1):  # bases that k words cover; nearer the ends too few words tell
                if not all(weak[at - k + 1 : at + 1]):
                    continue
                for b in "ACGT":
                    t = s[:at] + b + s[at + 1 :]
                    if all(good(t[i : i + k]) for i in range(at - k + 1, at + 1)):
                        s, weak[at - k + 1 : at + 1] = t, [False] * k
                        break
            seqs[r] = s
            if budget_s and time.time() - began > budget_s:
                break
    strands = {(i, d): (s if d == 0 else revcomp(s)) for i, s in seqs.items() for d in (0, 1)}
    heads: dict[str, list] = defaultdict(list)
    for key, s in strands.items():
        heads[s[:min_overlap]].append(key)
    found = []
    for key, s in strands.items():
        for p in range(1, len(s) - min_overlap + 1):
            for other in heads.get(s[p : p + min_overlap], ()):
                t = strands[other]
                if other[0] != key[0] and len(t) >= len(s) - p and t.startswith(s[p:]):
                    found.append((len(s) - p, key, other))
        if budget_s and time.time() - began > budget_s:
            break
    return merged(seqs, found)


def merged(seqs: dict[int, str], found: list[tuple]) -> list[str]:
    """Greedy layout: overlaps ``(bases, (read, strand), (read, strand))`` are taken longest first where both ends are free."""
    strands = {(i, d): (s if d == 0 else revcomp(s)) for i, s in seqs.items() for d in (0, 1)}
    nxt, before, up = {}, {}, {i: i for i in seqs}

    def top(x):
        while up[x] != x:
            x = up[x]
        return x

    for n, a, b in sorted(found, key=lambda x: (-x[0], x[1], x[2])):
        ra, rb = (a[0], 1 - a[1]), (b[0], 1 - b[1])
        if a in nxt or b in before or rb in nxt or ra in before or top(a[0]) == top(b[0]):
            continue
        nxt[a], before[b] = (b, n), a
        nxt[rb], before[ra] = (ra, n), rb
        up[top(a[0])] = top(b[0])
    out, done = [], set()
    for key in strands:
        if key in before or key[0] in done:
            continue
        s, at = strands[key], key
        done.add(key[0])
        while at in nxt:
            at, n = nxt[at]
            s += strands[at][n:]
            done.add(at[0])
        out.append(s)
    return out


def within_budget(reads: list[tuple[int, str]], min_overlap: int, seconds: float) -> tuple[list[str], bool]:
    """The corrected assembler stopped after ``seconds``, and whether it had ended by then."""
    began = time.time()
    made = single_node(reads, min_overlap, True, seconds)
    return made, time.time() - began <= seconds


def minimizers(s: str, k: int, w: int) -> list[tuple[int, int, bool]]:
    """``(code, position, reversed)``: of every ``w`` neighbouring k-mers the one with the smallest hash, strands as one."""
    from stringweave.operators.overlap import packed

    if len(s) < k:
        return []
    f, b = packed(s.encode(), k)
    code = np.minimum(f, b)
    h = (code.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(20)
    n = max(1, len(h) - w + 1)
    at = np.unique([i + int(h[i : i + w].argmin()) for i in range(n)])
    return [(int(code[i]), int(i), bool(code[i] != f[i])) for i in at]


def minimizer_layout(reads: list[tuple[int, str]], k: int = 13, w: int = 4, least: int = 3, drift: int = 60, shortest: int = 60) -> list[str]:
    """A noisy-read assembler in one process, without correction: minimizers shared on one diagonal make an overlap.

    Pairs with ``least`` shared minimizers within ``drift`` of one diagonal overlap as far as that diagonal says; the
    layout takes the longest first and glues raw reads, so errors stay.
    """
    seqs = dict(reads)
    index: dict[int, list] = defaultdict(list)
    for i, s in seqs.items():
        for code, at, rev in minimizers(s, k, w):
            index[code].append((i, at, rev))
    diagonals: dict[tuple, list] = defaultdict(list)
    for hits in index.values():
        for x, (u, pu, ru) in enumerate(hits):
            for v, pv, rv in hits[x + 1 :]:
                if u != v:
                    if u > v:
                        u, pu, ru, v, pv, rv = v, pv, rv, u, pu, ru
                    flip = ru != rv
                    diagonals[u, v, flip].append(pu - (len(seqs[v]) - k - pv if flip else pv))
    found = []
    for (u, v, flip), ds in diagonals.items():
        ds.sort()
        mid = ds[len(ds) // 2]
        if sum(abs(x - mid) <= drift for x in ds) < least:
            continue
        nu, nv = len(seqs[u]), len(seqs[v])
        if mid > 0 and nu - mid >= shortest and nu - mid < nv:  # u, then v
            a, b, n = (u, 0), (v, int(flip)), nu - mid
        elif mid < 0 and nv + mid >= shortest and nv + mid < nu:  # v, then u
            a, b, n = (v, int(flip)), (u, 0), nv + mid
        else:
            continue
        found += [(n, a, b), (n, (b[0], 1 - b[1]), (a[0], 1 - a[1]))]
    return merged(seqs, found)
