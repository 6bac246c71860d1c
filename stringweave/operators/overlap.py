"""From reads to a string graph: k-mers, candidates, alignments, pruning, reduction."""

from __future__ import annotations

import itertools

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from stringweave.functions.dna import revcomp
from stringweave.session import Scratch


_CODE = np.zeros(256, np.int64)
_BASE = np.zeros(256, bool)
for _i, _b in enumerate(b"ACGT"):
    _CODE[_b], _BASE[_b] = _i, True


def packed(seq: bytes, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Two-bit codes of all k-mers of a sequence, and of their reverse complements, by doubling the word."""
    c = _CODE[np.frombuffer(seq, np.uint8)]
    fore = back = None
    unit_f, unit_b, size, at, left = c, 3 - c, 1, 0, k
    while left:
        if left & 1:  # units of the present size stand next in the word
            n = len(c) - at - size + 1
            f, b = unit_f[at : at + n], unit_b[at : at + n]
            fore = f if fore is None else (fore[:n] << (2 * size)) | f
            back = b if back is None else (b << (2 * at)) | back[:n]
            at += size
        left >>= 1
        if left:
            m = len(unit_f) - size
            unit_f, unit_b = (unit_f[:m] << (2 * size)) | unit_f[size:], (unit_b[size:] << (2 * size)) | unit_b[:m]
            size *= 2
    return fore, back


def known(seq: bytes, k: int) -> np.ndarray | None:
    """Marks the windows of ``k`` letters that are all A, C, G or T; None where every window is."""
    ok = _BASE[np.frombuffer(seq, np.uint8)]
    if ok.all():
        return None
    bad = np.concatenate(([0], np.cumsum(~ok)))
    return bad[k:] == bad[: len(bad) - k]


def _codes(seq: bytes, k: int, both_strands: bool):
    """Pieces ``(positions, codes, reversed)`` of a sequence's k-mers; windows with other letters are no k-mers."""
    for a in range(0, len(seq) - k + 1, 1 << 20):  # pieces of long sequences overlap by k - 1
        piece = seq[a : a + (1 << 20) + k - 1]
        f, b = packed(piece, k)
        code, at, some = np.minimum(f, b) if both_strands else f, np.arange(a, a + len(f), dtype=np.int32), known(piece, k)
        yield (at, code, code != f) if some is None else (at[some], code[some], (code != f)[some])


def partial_codes(reads: DataFrame, k: int, both_strands: bool = True) -> DataFrame:
    """``(kmer, n)`` straight from sequences, n to be summed: counts are taken in Python batch by batch, so
    Arrow sees each different k-mer of some millions once."""

    def work(batches):
        held, n = [], 0

        def flush():
            code, times = np.unique(np.concatenate(held), return_counts=True)
            return pa.RecordBatch.from_arrays([pa.array(code, pa.int64()), pa.array(times, pa.int64())], names=["kmer", "n"])

        for batch in batches:
            for s in batch.column(0):
                for _, code, _ in _codes(s.as_py().encode(), k, both_strands):
                    held.append(code)
                    n += len(code)
                    if n >= 1 << 22:
                        yield flush()
                        held, n = [], 0
        if held:
            yield flush()

    return reads.where(F.length("seq") >= k).select("seq").mapInArrow(work, "kmer long, n long")


def count_codes(reads: DataFrame, k: int, both_strands: bool = True) -> DataFrame:
    """``(kmer, n)`` from sequences; the shuffle sees each different k-mer of some millions once."""
    return partial_codes(reads, k, both_strands).groupBy("kmer").agg(F.sum("n").alias("n"))


def _beside(seq: bytes, at: np.ndarray, rev: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Codes of the letters left and right of k-mers, as they lie on the strand that gave the code; 4 for none."""
    begin = max(0, int(at[0]) - 1) if len(at) else 0
    letters = np.frombuffer(seq[begin : int(at[-1]) + k + 1] if len(at) else b"", np.uint8)
    code = np.full(len(letters) + 2, 4, np.int8)
    code[1:-1] = np.where(_BASE[letters], _CODE[letters], 4)
    fore, after = code[at - begin], code[at - begin + k + 1]
    turned = np.array([3, 2, 1, 0, 4], np.int8)
    return np.where(rev, turned[after], fore), np.where(rev, turned[fore], after)


def kmers(reads: DataFrame, k: int, both_strands: bool = True, beside: bool = False) -> DataFrame:
    """``(read_id, pos, kmer, rev)``: packed k-mers, the smaller strand's if ``both_strands``; k up to 31.

    Windows with a letter other than A, C, G and T are no k-mers.  With ``beside`` come ``left`` and
    ``right``, the letters next to the k-mer on its own strand.
    """
    names, more = ["read_id", "pos", "kmer", "rev"], ["left", "right"] if beside else []

    def work(batches):
        for batch in batches:
            for i, s in zip(batch.column(0).to_pylist(), batch.column(1)):
                seq = s.as_py().encode()
                for at, code, rev in _codes(seq, k, both_strands):
                    sides = [pa.array(side) for side in _beside(seq, at, rev, k)] if beside else []
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(code), i, np.int64)), pa.array(at), pa.array(code), pa.array(rev), *sides], names=[*names, *more])

    src = reads.where(F.length("seq") >= k).select(F.col("read_id").cast("long").alias("read_id"), "seq")
    return src.mapInArrow(lambda batches: _merged(work(batches)), "read_id long, pos int, kmer long, rev boolean" + "".join(f", {c} byte" for c in more))


def _merged(batches, rows: int = 1 << 17):
    """Small batches joined to batches of about ``rows`` rows."""
    held, n = [], 0
    for b in batches:
        held.append(b)
        n += b.num_rows
        if n >= rows:
            yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]
            held, n = [], 0
    if n:
        yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]


def minimizers(km: DataFrame, share: int) -> DataFrame:
    """The k-mers whose hash is divisible by ``share``: a column sample that reads agree on."""
    return km.where(F.pmod(F.xxhash64("kmer"), F.lit(share)) == 0)


def count_kmers(km: DataFrame) -> DataFrame:
    """``(kmer, n)``; counts are combined before the shuffle."""
    return km.groupBy("kmer").agg(F.count("*").alias("n"))


def reliable(counts: DataFrame, lo: int = 2, hi: int | None = 8) -> DataFrame:
    """k-mers of a multiplicity that neither an error nor a repeat makes likely; without ``hi`` only errors go."""
    return counts.where(F.col("n") >= lo if hi is None else F.col("n").between(lo, hi))


def build_a(km: DataFrame, counts: DataFrame) -> DataFrame:
    """Reads x k-mers: ``(row, col, val)`` with position, strand and, where ``km`` has them, the letters beside."""
    val = F.struct(*[c for c in km.columns if c not in ("read_id", "kmer")])
    return km.join(counts.select("kmer"), "kmer", "left_semi").select(F.col("read_id").alias("row"), F.col("kmer").alias("col"), val.alias("val"))


#: Rows of a k-mer's column that one task multiplies; longer columns are cut into pieces.
PIECE_ROWS = 512


def _pieces(a: DataFrame) -> DataFrame:
    """``a`` with ``own``, a row's piece of its column, and ``n_pieces``, the pieces of the column."""
    heavy = a.groupBy("col").agg(F.count("*").alias("n")).where(F.col("n") > PIECE_ROWS).select("col", F.ceil(F.col("n") / PIECE_ROWS).cast("int").alias("n_pieces"))
    cut = a.join(heavy, "col", "left").withColumn("n_pieces", F.coalesce("n_pieces", F.lit(1)))
    return cut.withColumn("own", F.pmod(F.xxhash64("row", "val.pos"), F.col("n_pieces")).cast("int"))


def products(a: DataFrame) -> DataFrame:
    """Every two rows u < v of a column with their values: ``(col, u, v, pu, ru, pv, rv)``, and the letters beside if ``a`` has them.

    A column of more than ``PIECE_ROWS`` rows is multiplied piece by piece, every piece with every
    one, so no task holds it whole and no product is left out.
    """
    cut = _pieces(a)
    every = F.explode(F.sequence(F.lit(0), F.col("n_pieces") - 1))
    value = lambda side: [F.col(f"val.{c}").alias(c[0] + side if c in ("pos", "rev") else f"{c}_{side}") for c in a.schema["val"].dataType.names]
    u = cut.select(F.col("row").alias("u"), "col", F.col("own").alias("i"), every.alias("j"), *value("u"))
    v = cut.select(F.col("row").alias("v"), "col", every.alias("i"), F.col("own").alias("j"), *value("v"))
    return u.join(v, ["col", "i", "j"]).where("u < v").drop("i", "j")


def can_chain(k: int, lo: int, hi: int | None, sample: int = 1) -> bool:
    """Whether every k-mer that two reads share is in the matrix, and none is its own reverse complement."""
    return k % 2 == 1 and lo <= 2 and hi is None and sample == 1


def candidates(a: DataFrame, lengths: DataFrame, k: int, min_shared: int = 1, by_diagonal: bool = False) -> DataFrame:
    """A times its transpose, upper triangle: shared k-mers and two seeds of every pair and strand.

    Seeds are positions in ``u`` and in ``v`` as it lies along ``u``; the first and the last in
    ``u`` are kept.  With ``by_diagonal`` each offset between the reads is a row of its own.

    Shared k-mers stand in runs, one next to the other in both reads.  Where ``a`` has the letters
    beside (only with ``can_chain``), a product goes on to the aggregate if a run begins or ends there, and the
    counts and seeds follow from the ends: the same rows, without one aggregated row per shared k-mer.
    """
    rev, made, n = F.col("ru") != F.col("rv"), products(a), F.lit(1)
    if "left" in a.schema["val"].dataType.names:
        open_ = {side: (F.col(f"{side}_u") != F.col(f"{side}_v")) | (F.col(f"{side}_u") == 4) for side in ("left", "right")}
        made = made.where(open_["left"] | open_["right"])
        begins, ends = (F.when(F.col("ru"), open_[x]).otherwise(open_[y]) for x, y in (("right", "left"), ("left", "right")))
        n = F.when(begins, 1 - F.col("pu")).otherwise(0) + F.when(ends, F.col("pu")).otherwise(0)
    pairs = made.withColumn("n", n).join(lengths.select(F.col("read_id").alias("v"), F.col("len").alias("nv")), "v")
    pairs = pairs.select("u", "v", rev.alias("rev"), "pu", F.when(rev, F.col("nv") - k - F.col("pv")).otherwise(F.col("pv")).alias("pv"), "n")
    keys = ["u", "v", "rev"]
    if by_diagonal:
        pairs, keys = pairs.withColumn("diag", F.col("pu") - F.col("pv")), [*keys, "diag"]
    seed = F.struct("pu", "pv")
    c = pairs.groupBy(*keys).agg(F.sum("n").cast("long").alias("n_shared"), F.min(seed).alias("seed1"), F.max(seed).alias("seed2"))
    if by_diagonal and min_shared > 1:  # a gap moves shared k-mers to another diagonal
        return c.withColumn("all", F.sum("n_shared").over(Window.partitionBy("u", "v", "rev"))).where(F.col("all") >= min_shared).drop("all")
    return c.where(F.col("n_shared") >= min_shared)


def _fetched(c: DataFrame, reads: DataFrame) -> DataFrame:
    """Candidates with both sequences, ``v`` as it lies along ``u``."""
    s = reads.select("read_id", "seq", "len")
    j = c.join(s.select(F.col("read_id").alias("u"), F.col("seq").alias("su"), F.col("len").alias("nu")), "u")
    j = j.join(s.select(F.col("read_id").alias("v"), F.col("seq").alias("sv"), F.col("len").alias("nv")), "v")
    return j.withColumn("sv", F.when(F.col("rev"), revcomp("sv")).otherwise(F.col("sv")))


def _stored(j: DataFrame, score, bu, eu, bw, ew) -> DataFrame:
    """Spans along ``u`` to spans in stored coordinates."""
    r = F.col("rev")
    return j.select("u", "v", "rev", "nu", "nv", score.alias("score"), bu.alias("bu"), eu.alias("eu"), F.when(r, F.col("nv") - ew).otherwise(bw).alias("bv"), F.when(r, F.col("nv") - bw).otherwise(ew).alias("ev"))


def align_exact(c: DataFrame, reads: DataFrame) -> DataFrame:
    """Overlaps without a difference; ``c`` by diagonal.  Pure expressions."""
    j = _fetched(c, reads)
    d = F.col("diag")
    bu, eu = F.greatest(F.lit(0), d), F.least(F.col("nu"), F.col("nv") + d)
    same = F.substring("su", bu + 1, eu - bu) == F.substring("sv", bu - d + 1, eu - bu)
    return _stored(j.where(same), (eu - bu).cast("int"), bu, eu, bu - d, eu - d)


def align_ungapped(c: DataFrame, reads: DataFrame, k: int, x: int) -> DataFrame:
    """Seed-and-extend without gaps, stopping where the score falls more than ``x`` below its best.

    Every seed of a row of ``c`` is extended, and gives an alignment.  Scores are running sums over windows of the compared bases; a match is 1, a mismatch -1.
    """
    seeds = c.withColumn("seed", F.explode(F.array_distinct(F.array("seed1", "seed2"))))
    j = _fetched(seeds.select("u", "v", "rev", F.col("seed.pu").alias("pu"), F.col("seed.pv").alias("pv")), reads)
    keys = ["u", "v", "rev", "pu", "pv"]

    def side(right: bool) -> DataFrame:
        n = F.least(F.col("nu") - F.col("pu"), F.col("nv") - F.col("pv")) - k if right else F.least("pu", "pv")
        steps = j.withColumn("n", n).where("n > 0").select(*keys, "su", "sv", F.explode(F.sequence(F.lit(1), F.col("n"))).alias("i"))
        at = (lambda p: F.col(p) + k + F.col("i")) if right else (lambda p: F.col(p) + 1 - F.col("i"))
        same = F.substring("su", at("pu"), F.lit(1)) == F.substring("sv", at("pv"), F.lit(1))
        w = Window.partitionBy(*keys).orderBy("i").rowsBetween(Window.unboundedPreceding, 0)
        s = steps.select(*keys, "i", F.when(same, 1).otherwise(-1).alias("d")).withColumn("s", F.sum("d").over(w))
        s = s.withColumn("best", F.greatest(F.lit(0), F.max("s").over(w))).withColumn("over", F.max(F.when(F.col("best") - F.col("s") > x, 1).otherwise(0)).over(w))
        top = F.max(F.when(F.col("s") > 0, F.struct("s", (-F.col("i")).alias("i"))))
        name = "r" if right else "l"
        return s.where("over = 0").groupBy(*keys).agg(top.alias("t")).select(*keys, F.coalesce("t.s", F.lit(0)).alias(f"{name}s"), F.coalesce(-F.col("t.i"), F.lit(0)).alias(f"{name}n"))

    got = j.join(side(True), keys, "left").join(side(False), keys, "left").fillna(0, ["rs", "rn", "ls", "ln"])
    l, r = F.col("ln"), F.col("rn")
    return _stored(got, (F.col("rs") + F.col("ls") + k).cast("int"), F.col("pu") - l, F.col("pu") + k + r, F.col("pv") - l, F.col("pv") + k + r)


_DEAD = -(1 << 29)


def _common(a: bytes, b: bytes) -> int:
    """Bases that two sequences share from their beginnings."""
    n = min(len(a), len(b))
    if a[:n] == b[:n]:
        return n
    return int((np.frombuffer(a, np.uint8, n) != np.frombuffer(b, np.uint8, n)).argmax())


def _laid(seqs: list[bytes], width: int, before: int, filler: int) -> np.ndarray:
    """Sequences as the rows of a matrix, from column ``before`` on."""
    out = np.full((len(seqs), width), filler, np.uint8)
    for row, s in zip(out, seqs):
        row[before : before + len(s)] = np.frombuffer(s, np.uint8)
    return out


def _extend_group(a: list[bytes], b: list[bytes], x: int, match: int, mismatch: int, gap: int) -> np.ndarray:
    """x-drop of a group of pairs in step: rows ``(score, bases of a, bases of b)``.

    A column of the score table is an offset between the sequences.  An anti-diagonal renews every
    second column, so one table holds the last two of them and every move is a slice.  The table is
    widened where a live cell comes near its border, and pairs without a live cell leave it.
    """
    step, half = 4, 12  # anti-diagonals between looks at the border; offsets on either side at first
    n, m = np.array([len(s) for s in a]), np.array([len(s) for s in b])
    out, ids = np.zeros((len(a), 3), np.int64), np.arange(len(a))
    best, last = np.zeros(len(a), np.int32), n + m
    edge, long = 1 << 10, int(max(n.max(), m.max())) + 2
    s, t = _laid(a, long + 2 * edge, edge, 0), _laid(b, long + 2 * edge, edge, 1)[:, ::-1]
    h = np.full((len(a), 2 * half + 1), _DEAD, np.int32)
    h[:, half] = 0
    for d in range(1, int(last.max()) + 1):
        if d % step == 1:
            live = (h > _DEAD).any(axis=1) & (last >= d)
            if live.sum() < 0.8 * len(live):
                if not live.any():
                    break
                ids, best, last, s, t, h = ids[live], best[live], last[live], s[live], t[live], h[live]
            if (h[:, : step + 1] > _DEAD).any() or (h[:, -step - 1 :] > _DEAD).any():
                h, half = np.pad(h, ((0, 0), (half, half)), constant_values=_DEAD), 2 * half
            if half + 2 > edge:
                more = ((0, 0), (edge, edge))
                s, t, edge = np.pad(s, more), np.pad(t, more, constant_values=1), 2 * edge
        first = 1 + (half + 1 + d) % 2  # the first inner column whose offset has the parity of d
        now, before, after = h[:, first:-1:2], h[:, first - 1 : -2 : 2], h[:, first + 1 :: 2]
        w = now.shape[1]
        i = (d + first - half) // 2  # bases of a in the first column; one more in each next
        j = d - i
        at, back = edge + i - 1, t.shape[1] - (edge + j - 1) - 1
        hit = np.where(s[:, at : at + w] == t[:, back : back + w], np.int32(match), np.int32(mismatch))
        cell = np.maximum(now + hit, np.maximum(before[:, :w], after[:, :w]) + gap)
        cell[cell < (best - x)[:, None]] = _DEAD
        now[:] = cell
        top = cell.max(axis=1)
        up = np.nonzero(top > best)[0]
        if len(up):
            best[up] = top[up]
            gone = i + cell[up].argmax(axis=1)
            out[ids[up]] = np.stack([top[up], gone, d - gone], axis=1)
    return out


def xdrop_many(a: list[bytes], b: list[bytes], x: int, match: int = 1, mismatch: int = -1, gap: int = -1) -> np.ndarray:
    """Best extensions of pairs of sequences from their beginnings: rows ``(score, bases of a, bases of b)``.

    Cells more than ``x`` below a pair's best so far are dropped, and its extension ends when none is
    left.  What two sequences share at their beginnings is taken as it is: some best alignment
    matches it.  Neither sequence is read beyond twice the length of the other, where gaps cost all
    that matches gave.  Pairs of like length go together, some megabytes at a time.
    """
    out = np.zeros((len(a), 3), np.int64)
    left = []
    for i, (s, t) in enumerate(zip(a, b)):
        r = _common(s, t)
        out[i] = (r * match, r, r)
        n = min(len(s), len(t)) - r
        if n:
            left.append((n, i, s[r : r + 2 * n], t[r : r + 2 * n]))
    left.sort(key=lambda e: e[:2])
    while left:
        size = min(len(left), 2048, max(1, (1 << 24) // (4 * left[-1][0] + 4096)))
        group, left = left[-size:], left[:-size]
        got = _extend_group([e[2] for e in group], [e[3] for e in group], x, match, mismatch, gap)
        out[[e[1] for e in group]] += got
    return out


def xdrop_one_side(a: bytes, b: bytes, x: int, match: int = 1, mismatch: int = -1, gap: int = -1) -> tuple[int, int, int]:
    """One pair of ``xdrop_many``."""
    return tuple(xdrop_many([a], [b], x, match, mismatch, gap)[0].tolist())


_ALIGNMENT = "u long, v long, rev boolean, nu int, nv int, score int, bu int, eu int, bv int, ev int"
_ALIGNED, _KINDS = [f.split()[0] for f in _ALIGNMENT.split(", ")], [pa.int64(), pa.int64(), pa.bool_(), *[pa.int32()] * 7]


def align_xdrop(c: DataFrame, reads: DataFrame, k: int, x: int, min_score: int = 0) -> DataFrame:
    """Gapped seed-and-extend, a whole Arrow batch in step; pairs below ``min_score`` never leave the worker.

    Both seeds of a row of ``c`` are extended, the second unless the first one's span covers it on its diagonal.
    """
    j = _fetched(c, reads).select("u", "v", "rev", "nu", "nv", "su", "sv", F.col("seed1.pu").alias("p1"), F.col("seed1.pv").alias("q1"), F.col("seed2.pu").alias("p2"), F.col("seed2.pv").alias("q2"))

    def work(batches):
        for b in batches:
            col = {name: b.column(name).to_numpy(zero_copy_only=False) for name in ("u", "v", "rev", "nu", "nv", "p1", "q1", "p2", "q2")}
            su, sv = ([s.encode() for s in b.column(name).to_pylist()] for name in ("su", "sv"))

            def spans(rows, p, q):
                right = xdrop_many([su[r][i + k :] for r, i in zip(rows, p)], [sv[r][i + k :] for r, i in zip(rows, q)], x)
                left = xdrop_many([su[r][:i][::-1] for r, i in zip(rows, p)], [sv[r][:i][::-1] for r, i in zip(rows, q)], x)
                return right[:, 0] + left[:, 0] + k, p - left[:, 1], p + k + right[:, 1], q - left[:, 2], q + k + right[:, 2]

            p1, q1, p2, q2 = (col[name].astype(np.int64) for name in ("p1", "q1", "p2", "q2"))
            every = np.arange(b.num_rows)
            one = spans(every, p1, q1)
            covered = (p2 - q2 == p1 - q1) & (p2 + k <= one[2]) & (q2 + k <= one[4])
            rest = every[~covered]
            two = spans(rest, p2[rest], q2[rest])
            rows = np.concatenate((every, rest))
            score, bu, eu, bw, ew = (np.concatenate(both) for both in zip(one, two))
            rev, nv = col["rev"][rows].astype(bool), col["nv"][rows]
            bv, ev = np.where(rev, nv - ew, bw), np.where(rev, nv - bw, ew)
            good = score >= min_score
            cols = [col["u"][rows], col["v"][rows], rev, col["nu"][rows], nv, score, bu, eu, bv, ev]
            yield pa.RecordBatch.from_arrays([pa.array(v[good], t) for v, t in zip(cols, _KINDS)], names=_ALIGNED)

    return j.mapInArrow(work, _ALIGNMENT)


def full_overlap(a: bytes, b: bytes, match: int = 1, mismatch: int = -1, gap: int = -1) -> tuple[int, int, int, int, int]:
    """The best overlap of two sequences by the whole dynamic programme: (score, begin and end in a, in b).

    Gaps at either end of either sequence are free, so the alignment runs from a beginning to an end.
    Rows are vectors; a running maximum settles the gaps along a row, and a second table is traced back.
    """
    s, t = np.frombuffer(a, np.uint8), np.frombuffer(b, np.uint8)
    n, m = len(s), len(t)
    if not n or not m:
        return 0, 0, 0, 0, 0
    slope = gap * np.arange(m + 1)
    row, move = np.zeros(m + 1, np.int64), np.zeros((n + 1, m + 1), np.int8)  # 0 stop, 1 both, 2 a only, 3 b only
    side = np.zeros(n + 1, np.int64)
    for i in range(1, n + 1):
        both, up = row[:-1] + np.where(t == s[i - 1], match, mismatch), row[1:] + gap
        best = np.concatenate(([0], np.maximum(both, up)))
        new = np.maximum.accumulate(best - slope) + slope
        move[i, 1:] = np.where(new[1:] > best[1:], 3, np.where(both >= up, 1, 2))
        row, side[i] = new, new[m]
    i, j = (int(side.argmax()), m) if side.max() >= row.max() else (n, int(row.argmax()))
    score, ea, eb = int(max(side.max(), row.max())), i, j
    while i and j:
        step = move[i, j]
        i, j = i - (step != 3), j - (step != 2)
    return score, i, ea, j, eb


def align_full(c: DataFrame, reads: DataFrame, min_score: int = 0) -> DataFrame:
    """Every candidate pair and strand by the whole dynamic programme, seeds aside; for few and short reads."""
    j = _fetched(c.select("u", "v", "rev").distinct(), reads).select("u", "v", "rev", "nu", "nv", "su", "sv")

    def work(batches):
        for b in batches:
            out = []
            for r in b.to_pylist():
                score, bu, eu, bw, ew = full_overlap(r["su"].encode(), r["sv"].encode())
                if score >= min_score:
                    bw, ew = (r["nv"] - ew, r["nv"] - bw) if r["rev"] else (bw, ew)
                    out.append((r["u"], r["v"], r["rev"], r["nu"], r["nv"], score, bu, eu, bw, ew))
            cols = list(zip(*out)) or [[]] * 10
            yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(cols, _KINDS)], names=_ALIGNED)

    return j.mapInArrow(work, _ALIGNMENT)


def best_per_pair(aln: DataFrame) -> DataFrame:
    """The highest score of each pair; ties go to the longer span, then to the forward strand."""
    rank = F.struct("score", F.col("eu") - F.col("bu"), (~F.col("rev")).cast("int"), "bu", "bv")
    return aln.groupBy("u", "v").agg(F.max_by(F.struct("rev", "nu", "nv", "score", "bu", "eu", "bv", "ev"), rank).alias("x")).select("u", "v", "x.*")


def prune_low_score(aln: DataFrame, t: float, relative: bool = False) -> DataFrame:
    """Alignments of a score of ``t`` at least, absolute or per base of the span."""
    return aln.where(F.col("score") >= (t * (F.col("eu") - F.col("bu")) if relative else F.lit(t)))


def _swapped(aln: DataFrame) -> DataFrame:
    return aln.select(F.col("v").alias("u"), F.col("u").alias("v"), "rev", F.col("nv").alias("nu"), F.col("nu").alias("nv"), "score", F.col("bv").alias("bu"), F.col("ev").alias("eu"), F.col("bu").alias("bv"), F.col("eu").alias("ev"))


def equal_reads(reads: DataFrame) -> DataFrame:
    """``(read_id, rep)``: every read and the smallest id among the reads of its very bases."""
    key = F.sha2("seq", 256)
    least = reads.groupBy(key.alias("key")).agg(F.min("read_id").alias("rep"))
    return reads.select("read_id", key.alias("key")).join(least, "key").select("read_id", "rep")


def spread(aln: DataFrame, members: DataFrame, reads: DataFrame, at_least: int) -> DataFrame:
    """Alignments of representatives as those of all their reads; equal reads of ``at_least`` bases align whole."""
    m = members.select("read_id", "rep")
    x = aln.join(m.select(F.col("rep").alias("u"), F.col("read_id").alias("mu")), "u").join(m.select(F.col("rep").alias("v"), F.col("read_id").alias("mv")), "v")
    x = x.withColumns({"u": F.col("mu"), "v": F.col("mv")}).select(*aln.columns)
    twins = products(m.select(F.col("read_id").alias("row"), F.col("rep").alias("col"), F.struct(F.lit(0).alias("pos"), F.lit(False).alias("rev")).alias("val")))
    n, zero = F.col("len"), F.lit(0)
    twins = twins.join(reads.select(F.col("read_id").alias("u"), F.col("len").cast("int").alias("len")).where(n >= at_least), "u")
    twins = twins.select("u", "v", F.lit(False).alias("rev"), n.alias("nu"), n.alias("nv"), n.alias("score"), zero.alias("bu"), n.alias("eu"), zero.alias("bv"), n.alias("ev"))
    return x.where("u < v").unionByName(_swapped(x.where("u > v"))).unionByName(twins)


def _overhangs():
    lv = F.when(F.col("rev"), F.col("nv") - F.col("ev")).otherwise(F.col("bv"))
    rv = F.when(F.col("rev"), F.col("bv")).otherwise(F.col("nv") - F.col("ev"))
    return F.col("bu"), F.col("nu") - F.col("eu"), lv, rv


def _kinds(fuzz: int):
    """``(u contained, v contained, u before v, v before u)`` along ``u``; all false for an internal match.

    An alignment may end up to ``fuzz`` bases before the end that it should reach, so on each side the
    shorter overhang is at most that.  A read is contained if on no side it reaches beyond the other.
    """
    lu, ru, lv, rv = _overhangs()
    whole = (F.least(lu, lv) <= fuzz) & (F.least(ru, rv) <= fuzz)
    return whole & (lu <= lv) & (ru <= rv), whole & (lu >= lv) & (ru >= rv), whole & (lu > lv) & (ru < rv), whole & (lu < lv) & (ru > rv)


def contained(aln: DataFrame, fuzz: int = 0) -> DataFrame:
    """Ids of reads whose whole span lies in another; of equal reads all but the smallest id."""
    u_in, v_in, _, _ = _kinds(fuzz)
    gone = F.when(v_in & (~u_in | (F.col("v") > F.col("u"))), F.col("v")).when(u_in, F.col("u"))
    return aln.select(gone.alias("read_id")).where("read_id is not null").distinct()


def drop_reads(aln: DataFrame, gone: DataFrame) -> DataFrame:
    return aln.join(gone.select(F.col("read_id").alias("u")), "u", "left_anti").join(gone.select(F.col("read_id").alias("v")), "v", "left_anti")


def classify(aln: DataFrame, fuzz: int = 0) -> DataFrame:
    """Both directed edges of every dovetail: ends touched, last and first base, new bases.

    ``u_end`` and ``v_end`` are 0 for a read's beginning and 1 for its end; ``pre`` is the last base
    of ``u`` before the overlap and ``post`` the overlap's first base in ``v``, in walking order.
    Internal matches and containments give no edge.
    """
    both = aln.select(*_swapped(aln).columns).unionByName(_swapped(aln))
    lu, ru, lv, rv = _overhangs()
    r, (_, _, fore, back) = F.col("rev"), _kinds(fuzz)
    pick = lambda f, b: F.when(fore, f).when(back, b)
    e = both.select(
        "u", "v", "rev", "score", pick(F.lit(1), F.lit(0)).alias("u_end"), pick(F.when(r, 1).otherwise(0), F.when(r, 0).otherwise(1)).alias("v_end"),
        pick(F.col("bu") - 1, F.col("eu")).alias("pre"), pick(F.when(r, F.col("ev") - 1).otherwise(F.col("bv")), F.when(r, F.col("bv")).otherwise(F.col("ev") - 1)).alias("post"),
        pick(rv - ru, lv - lu).alias("suffix"),
    )
    return e.where("u_end is not null")


def transitive_reduction(edges: DataFrame, fuzz: int = 0, max_rounds: int | None = None) -> DataFrame:
    """Drop edges that a path over a third read explains, round after round until none goes.

    Every round but the last drops edges, so it ends; a given ``max_rounds`` that is not enough raises.

    A two-step path leaves the middle read by the end it did not enter; it explains an edge with the
    same outer ends if its new bases are no more than the edge's, give or take ``fuzz``.  A min-plus
    product restricted to the pattern; twins go together.
    """
    store = Scratch(edges.sparkSession, "reduction")
    now = store.keep(edges)
    for turn in itertools.count():
        if turn == max_rounds:
            raise RuntimeError(f"edges may still go after {max_rounds} rounds")
        one = now.select("u", "u_end", F.col("v").alias("m"), F.col("v_end").alias("m_in"), F.col("suffix").alias("s1"))
        two = now.select(F.col("u").alias("m"), (1 - F.col("u_end")).alias("m_in"), "v", "v_end", F.col("suffix").alias("s2"))
        path = one.join(two, ["m", "m_in"]).groupBy("u", "u_end", "v", "v_end").agg(F.min(F.col("s1") + F.col("s2")).alias("best"))
        out = now.join(path, ["u", "u_end", "v", "v_end"]).where(F.col("best") <= F.col("suffix") + fuzz).select("u", "u_end", "v", "v_end")
        out = store.keep(out.unionByName(out.select(F.col("v").alias("u"), F.col("v_end").alias("u_end"), F.col("u").alias("v"), F.col("u_end").alias("v_end"))).distinct())
        if not out.limit(1).count():
            break
        then = store.keep(now.join(out, ["u", "u_end", "v", "v_end"], "left_anti"))
        store.drop(now)
        now = then
    return now.select(*edges.columns)


def drop_weaker(edges: DataFrame) -> DataFrame:
    """Without the edges that are beaten at both of their ends: a longer overlap leaves either one.

    What reduction leaves of them are overlaps by a repeat, as neither of the longer ones agrees with
    them.  Edges that are the longest at one end stay, and so do ties.
    """
    best = edges.groupBy("u", "u_end").agg(F.max("score").alias("top_u"))
    other = best.toDF("v", "v_end", "top_v")
    return edges.join(best, ["u", "u_end"]).join(other, ["v", "v_end"]).where(F.col("score") >= F.least("top_u", "top_v")).select(*edges.columns)


def drop_spare(edges: DataFrame) -> DataFrame:
    """Without the edges whose two ends are each the only continuation of another read end.

    Such an edge joins two chains crosswise by a repeat that no read spans: without it every read end
    there goes on in one way, with it in place of the others two read ends would lead nowhere.
    """
    n = edges.groupBy("u", "u_end").agg(F.count("*").alias("n"))
    far = edges.join(n.toDF("v", "v_end", "nv"), ["v", "v_end"])
    ends = far.groupBy("u", "u_end").agg(((F.count("*") > 1) & (F.min("nv") == 1)).alias("need_u"))
    both = edges.join(ends, ["u", "u_end"]).join(ends.toDF("v", "v_end", "need_v"), ["v", "v_end"])
    return both.where(~(F.col("need_u") & F.col("need_v"))).select(*edges.columns)


def best_overlap_graph(edges: DataFrame) -> DataFrame:
    """Each read end keeps its longest overlap only."""
    w = Window.partitionBy("u", "u_end").orderBy(F.desc("score"), "v")
    return edges.withColumn("rank", F.row_number().over(w)).where("rank = 1").drop("rank")
