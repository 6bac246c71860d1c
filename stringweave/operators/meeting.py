"""Candidate pairs without the k-mer matrix: reads meet in stretches of k-mers, and only the ends of shared runs leave.

Every k-mer belongs to one place of the smallest hashed m-mer in it, a strand-free choice, so reads that share a k-mer
hold the same m-mer at matching places.  The k-mers of a place stand in a row and are moved as one stretch: the bases on
either side of the m-mer and a letter beyond.  Stretches alike in all of these are one class, compared once.  Two reads
in a stretch share one run of k-mers there; a row leaves only if the run begins or ends, so whatever
goes on to either side costs nothing, and counts and seeds follow from the ends as in ``overlap.candidates``.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from stringweave.operators import overlap
from stringweave.operators.counting import _numbers, _planes

#: Bases of an m-mer, parts for each shuffle partition, k-mers a step, stretches a flush, products at once, rows a flush, rows summed at once.
M, PARTS, STEP, FLUSH, MOST, ROWS, HELD = 13, 32, 1 << 17, 1 << 19, 1 << 20, 1 << 21, 1 << 23
_LETTER = overlap._CODE.astype(np.uint32)
_NONE = np.int32(1 << 30)


def fits(k: int) -> bool:
    """Odd, so that no k-mer is its own other strand; from the bases that the two words below make up to a long."""
    return k % 2 == 1 and M + 4 <= k <= 31


def _places(data: np.ndarray, n: int, k: int, short: int = M):
    """Stretches of the ``n`` k-mers of ``data``, which has one letter before and one after them; an m-mer has ``short`` bases.

    Gives ``(place, other strand, m-mer, left, right, shape)``: the bases beside the m-mer as it lies on its own strand, the nearest at
    the low end and those to the right complemented; ``shape`` has how many they are and whether a letter beyond is among them.
    """
    base = overlap._BASE[data]
    fore = np.zeros(len(data) + 64, np.uint32)
    fore[32:-32] = _LETTER[data]
    back, size = 3 - fore, 1
    while size < 16:  # words of 16 bases by doubling, of either strand
        m, two = len(fore) - size, np.uint32(2 * size)
        fore, back, size = (fore[:m] << two) | fore[size:], (back[size:] << two) | back[:m], 2 * size
    o, wide = 33, k - short + 1
    one, two = fore[o : o + n + k - short] >> np.uint32(2 * (16 - short)), back[o : o + n + k - short] & np.uint32(4**short - 1)
    low = np.minimum(one, two) * np.uint32(0x9E3779B1)
    at = np.arange(len(low), dtype=np.uint64)
    high, last = low.astype(np.uint64) << np.uint64(32), np.uint64(0xFFFFFFFF)
    sides = []
    for key in (high | at, high | (last - at)):
        size = 1
        while 2 * size <= wide:
            key, size = np.minimum(key[:-size], key[size:]), 2 * size
        sides.append(np.minimum(key[:n], key[wide - size :][:n]) & last)
    place, right = sides[0].astype(np.int64), (last - sides[1]).astype(np.int64)
    ties = np.flatnonzero(place != right)
    if len(ties):  # the first one on the k-mer's own strand
        rest, mask = np.uint64(2 * (k - 16)), np.uint32((1 << (2 * (k - 16))) - 1)
        far = o + ties + k - 16
        turned = ((back[far].astype(np.uint64) << rest) | (back[o + ties] & mask)) < ((fore[o + ties].astype(np.uint64) << rest) | (fore[far] & mask))
        place[ties[turned]] = right[ties[turned]]
    bad = np.concatenate(([0], np.cumsum(~base[1:-1])))
    ok = bad[k:] == bad[:n]
    at = np.concatenate(([0], np.flatnonzero((place[1:] != place[:-1]) | (ok[1:] != ok[:-1])) + 1))
    length = np.diff(at, append=n)
    at, length = at[ok[at]], length[ok[at]]
    p = place[at]
    nl, nr, bl, br = p - at, at + length - 1 + k - p - short, base[at], base[at + length + k]
    word = lambda near, far: (far.astype(np.uint64) << np.uint64(32)) | near
    cut = lambda w, some: w & ((np.uint64(1) << (2 * some).astype(np.uint64)) - np.uint64(1))
    left, right = cut(word(fore[o + p - 16], fore[o + p - 32]), nl + bl), cut(word(back[o + p + short], back[o + p + short + 16]), nr + br)
    turned = two[p] < one[p]
    pick = lambda a, b: np.where(turned, b, a)
    shape = pick(nl, nr) | (pick(nr, nl) << 5) | (pick(bl, br).astype(np.int64) << 10) | (pick(br, bl).astype(np.int64) << 11)
    return p, turned, low[p], pick(left, right), pick(right, left), shape.astype(np.uint16)


def _mixed(z: np.ndarray) -> np.ndarray:
    z = z * np.uint32(0x85EBCA6B)
    z = (z ^ (z >> np.uint32(16))) * np.uint32(0xC2B2AE35)
    return z ^ (z >> np.uint32(13))


def _in_order(z, left, right, shape):
    """An order in which equal m-mers stand together and so do equal stretches; where a class begins in it."""
    mix = (left * np.uint64(0x9E3779B97F4A7C15)) ^ (right * np.uint64(0xC2B2AE3D27D4EB4F)) ^ (shape.astype(np.uint64) * np.uint64(0x165667B19E3779F9))
    mix ^= mix >> np.uint64(29)
    key = (z.astype(np.uint64) << np.uint64(32)) | ((mix * np.uint64(0x27D4EB2F165667C5)) >> np.uint64(32))
    order = np.argsort(key, kind="stable")
    turn = np.ones(len(order), bool)
    turn[1:] = key[order[1:]] != key[order[:-1]]

    def begins(rows):
        found = np.zeros(len(rows), bool)
        for x in (z, left, right, shape):
            x = x[rows]
            found[1:] |= x[1:] != x[:-1]
        return found

    new = begins(order) | turn
    if len(mixed := np.flatnonzero(new & ~turn)):  # different stretches of one mix may stand in turns
        of = np.cumsum(turn)
        some = np.flatnonzero(np.isin(of, of[mixed]))
        own = order[some]
        order[some] = own = own[np.lexsort((shape[own], right[own], left[own], of[some]))]
        new[some] = begins(own) | turn[some]
    return order, np.flatnonzero(new)


def _blob(*columns) -> bytes:
    return pa.compress(b"".join(_planes(c) for c in columns), codec="zstd", asbytes=True)


def _columns(blob: bytes, kinds: list[tuple[type, int]]) -> list[np.ndarray]:
    sizes = [np.dtype(t).itemsize * n for t, n in kinds]
    raw, ends = np.frombuffer(pa.decompress(blob, decompressed_size=sum(sizes), codec="zstd"), np.uint8), np.cumsum(sizes)
    return [_numbers(raw[e - s : e], t) for (t, _), s, e in zip(kinds, sizes, ends)]


def _packed(held: list[tuple], parts: int) -> pa.RecordBatch:
    """A row for each part: its classes, then their stretches as read, place, the read's bases and strand."""
    read, pos, size, turned, z, left, right, shape = (np.concatenate(x) for x in zip(*held))
    order, at = _in_order(z, left, right, shape)
    read, pos, size, turned = read[order], pos[order], size[order], turned[order]
    first = order[at]
    z, left, right, shape, n = z[first], left[first], right[first], shape[first], np.diff(at, append=len(order)).astype(np.uint32)
    part = (z.astype(np.uint64) * np.uint64(parts) >> np.uint64(32)).astype(np.int32)
    ends = np.flatnonzero(np.concatenate((part[1:] != part[:-1], [True]))) + 1
    rows, a = [], 0
    for b in ends.tolist():
        i, j = int(at[a]), int(at[b]) if b < len(at) else len(order)
        rows.append((int(part[a]), _blob(z[a:b], left[a:b], right[a:b], shape[a:b], n[a:b], np.diff(read[i:j], prepend=0), pos[i:j], size[i:j], turned[i:j]), b - a, j - i))
        a = b
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int32(), pa.binary(), pa.int32(), pa.int32()))], names=["part", "stretches", "classes", "n"])


def _unpacked(blobs: list[tuple[bytes, int, int]]):
    """Classes of a part in order, where each one's stretches begin, and these."""
    got = []
    for blob, c, n in blobs:
        x = _columns(blob, [(np.uint32, c), (np.uint64, c), (np.uint64, c), (np.uint16, c), (np.uint32, c), (np.int64, n), (np.uint32, n), (np.uint32, n), (np.uint8, n)])
        x[5] = np.cumsum(x[5])
        got.append(x)
    z, left, right, shape, n, read, pos, size, turned = (np.concatenate(x) for x in zip(*got))
    order, at = _in_order(z, left, right, shape)
    n, first = n.astype(np.int64), order[at]
    begin = (np.cumsum(n) - n)[order]
    rows = _runs(begin, n[order])
    total = np.add.reduceat(n[order], at)
    return (z[first], left[first], right[first], shape[first]), total, (read[rows], pos[rows].astype(np.int32), size[rows].astype(np.int32), turned[rows].astype(bool))


def _runs(begin: np.ndarray, n: np.ndarray) -> np.ndarray:
    """``begin``, ``begin + 1`` and so on, ``n`` numbers for each."""
    return np.arange(n.sum()) + np.repeat(begin - (np.cumsum(n) - n), n)


def _blocks(n: np.ndarray, most: int):
    """Ranges of about ``most`` in sum, one item at least."""
    ends, a = np.cumsum(n), 0
    while a < len(n):
        b = max(a + 1, int(np.searchsorted(ends, (ends[a - 1] if a else 0) + most, "right")))
        yield a, b
        a = b


def _same(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Letters that words share from their low ends; 32 if they are equal."""
    x = a ^ b
    return (np.bitwise_count((x & (~x + np.uint64(1))) - np.uint64(1)) >> 1).astype(np.int32)


def _alike(classes, spare, k: int):
    """Blocks ``(i, j)`` of the classes of one m-mer that may share a k-mer, each two once, a class with itself unless ``spare``.

    The bases that they share beside the m-mer reach half of what a k-mer has there on one side at least, so only
    classes that agree in that half of either side meet.
    """
    z, left, right, shape = classes
    half = (k - M) // 2
    mask, long_l, long_r = np.uint64((1 << 2 * half) - 1), shape & 31 >= half, (shape >> 5) & 31 >= half
    for side, long in ((left, long_l), (right, long_r)):
        some = np.flatnonzero(long)
        key = (z[some].astype(np.uint64) << np.uint64(32)) | (side[some] & mask)
        order = np.argsort(key, kind="stable")
        some, key = some[order], key[order]
        turn = np.flatnonzero(np.concatenate((key[1:] != key[:-1], [True]))) + 1
        me, skip = np.arange(len(some)), spare[some]
        n = np.repeat(turn, np.diff(turn, prepend=0)) - me - skip if len(some) else me
        for a, b in _blocks(n, MOST):
            i, j = np.repeat(some[a:b], n[a:b]), some[_runs(me[a:b] + skip[a:b], n[a:b])]
            if side is right:
                new = ~(long_l[i] & long_l[j] & ((left[i] ^ left[j]) & mask == 0))
                i, j = i[new], j[new]
            yield i, j


def _products(classes, total, stretches, k: int, by_diagonal: bool):
    """``(u, v, shared k-mers as told by ends)``, and with diagonals ``(diagonal and strand, first place or none, last place or -1)``, of the runs that begin or end."""
    left, right, shape = classes[1], classes[2], classes[3].astype(np.int32)
    read, pos, size, turned = stretches
    nl, nr, bl, br = shape & 31, (shape >> 5) & 31, (shape >> 10) & 1, shape >> 11
    bl, br, spare = bl + nl, br + nr, (bl & br == 1) | (total == 1)  # pairs within a class that goes on to both sides have no end here
    start = np.cumsum(total) - total

    def values(e, ml, mr, on_l, on_r):
        """What a run gives if the read of stretch ``e`` is the first one: its place along that read."""
        back = turned[e]
        begins, ends = ~np.where(back, on_r, on_l), ~np.where(back, on_l, on_r)
        first, final = pos[e] - np.where(back, mr, ml), pos[e] - (k - M) + np.where(back, ml, mr)
        n = begins * (1 - first) + ends * final
        return (n, np.where(begins, first, _NONE), np.where(ends, final, np.int32(-1))) if by_diagonal else (n,)

    for i, j in _alike((*classes[:3], shape), spare, k):
        sl, sr = _same(left[i], left[j]), _same(right[i], right[j])
        ml, mr = np.minimum(sl, np.minimum(nl[i], nl[j])), np.minimum(sr, np.minimum(nr[i], nr[j]))
        on_l, on_r = (sl > ml) & (ml < bl[i]) & (ml < bl[j]), (sr > mr) & (mr < br[i]) & (mr < br[j])
        some = np.flatnonzero((ml + mr + M - k >= 0) & ~(on_l & on_r))
        each = np.maximum(1, MOST // total[j[some]])  # stretches of the one class that meet all of the other at once
        pieces = -(-total[i[some]] // each)
        within, some, each = _runs(np.zeros_like(pieces), pieces), np.repeat(some, pieces), np.repeat(each, pieces)
        i, j, run = i[some], j[some], [x[some] for x in (ml, mr, on_l, on_r)]
        begin, n, m = start[i] + within * each, np.minimum(each, total[i] - within * each), total[j]
        for a, b in _blocks(n * m, MOST):
            x, y = _runs(begin[a:b], n[a:b]), _runs(start[j[a:b]], m[a:b])
            at_x, at_y = (values(e, *(np.repeat(r[a:b], c[a:b]) for r in run)) for e, c in ((x, n), (y, m)))
            many = np.repeat(m[a:b], n[a:b])
            far = _runs(np.repeat(np.cumsum(m[a:b]) - m[a:b], n[a:b]), many)
            u, v = np.repeat(read[x], many), read[y][far]
            swap = u > v
            rows = [np.minimum(u, v), np.maximum(u, v), *(np.where(swap, q[far], np.repeat(p, many)) for p, q in zip(at_x, at_y))]
            if by_diagonal:
                x, y = np.repeat(x, many), y[far]
                x, y = np.where(swap, y, x), np.where(swap, x, y)
                rev = turned[x] != turned[y]
                rows.insert(3, 2 * (pos[x] - np.where(rev, size[y] - M - pos[y], pos[y])) + rev)
            gone = u == v
            if (own := i[a:b] == j[a:b]).any():
                gone |= swap & np.repeat(own, n[a:b] * m[a:b])
            yield [r[~gone] for r in rows] if gone.any() else rows


_KINDS = [np.int64, np.int64, np.int32, np.int32, np.int32, np.int32]


def _dealt(held: list[tuple], parts: int) -> pa.RecordBatch:
    """A row for each part of the first reads: its pairs, column by column."""
    cols = [np.concatenate(x) for x in zip(*held)]
    part = ((_mixed((cols[0] >> 12).astype(np.uint32)).astype(np.uint64) * np.uint64(parts)) >> np.uint64(32)).astype(np.int32)
    order = np.argsort(part.astype(np.uint16) if parts <= 1 << 16 else part, kind="stable")
    part, cols = part[order], [c[order] for c in cols]
    rows, a = [], 0
    for b in (np.flatnonzero(np.concatenate((part[1:] != part[:-1], [True]))) + 1).tolist():
        u, v = cols[0][a:b], cols[1][a:b]
        rows.append((int(part[a]), _blob(np.diff(u, prepend=0), v - u, *(c[a:b].astype(np.int32) for c in cols[2:])), b - a))
        a = b
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int32(), pa.binary(), pa.int32()))], names=["part", "pairs", "n"])


def _joined(held: list[tuple]) -> tuple:
    """Each pair, and with diagonals each of its diagonals, once: sums, first and last places."""
    u, v, *more = (np.concatenate(x) for x in zip(*held))
    block = u >> 12
    rank = np.searchsorted(np.unique(block), block)
    own, gap = (rank << 12) | (u & 4095), v - u
    wide = int(gap.max()).bit_length()
    if len(more) == 1 and int(own.max()).bit_length() + wide < 64:
        order = np.argsort((own << wide) | gap)
    else:
        order = np.lexsort((*more[1:2], gap, own))
    u, v, more = u[order], v[order], [c[order] for c in more]
    new = (u[1:] != u[:-1]) | (v[1:] != v[:-1])
    if len(more) > 1:
        new |= more[1][1:] != more[1][:-1]
    at = np.flatnonzero(np.concatenate(([True], new)))
    out = [u[at], v[at], np.add.reduceat(more[0].astype(np.int64), at)]
    if len(more) > 1:
        out += [more[1][at], np.minimum.reduceat(more[2], at), np.maximum.reduceat(more[3], at)]
    return tuple(out)


def _chunks(batch: pa.RecordBatch, k: int, short: int = M):
    """Stretches of a batch of reads, step by step; reads stand in one row of letters with a stop between them."""
    ids, col = batch.column(0).to_numpy(), batch.column(1).cast(pa.string())
    ends = np.frombuffer(col.buffers()[1], np.int32)[col.offset : col.offset + len(col) + 1].astype(np.int64)
    data = np.frombuffer(col.buffers()[2] or b"", np.uint8)[ends[0] : ends[-1]]
    size = np.diff(ends)
    starts = ends[:-1] - ends[0] + np.arange(len(size)) + 1
    line = np.insert(data, np.append(ends[:-1], ends[-1]) - ends[0], 0)
    for a in range(1, len(line) - k, STEP):
        n = min(STEP, len(line) - k - a)
        p, turned, low, *word = _places(line[a - 1 : a + n + k], n, k, short)
        of = np.searchsorted(starts, p + a, "right") - 1
        yield ids[of], (p + a - starts[of]).astype(np.uint32), size[of].astype(np.uint32), turned.astype(np.uint8), _mixed(low), *word


def _by_part(batches):
    """The rows of each part, which stand together, without its number."""
    now, held = None, []
    for batch in batches:
        for i in range(batch.num_rows):  # a batch is large, so no second copy of it is made
            part, *row = (c[i].as_py() for c in batch.columns)
            if part != now and held:
                yield held
                held = []
            now = part
            held.append(row)
    if held:
        yield held


def pairs(reads: DataFrame, k: int, by_diagonal: bool = False) -> DataFrame:
    """Reads u < v that share k-mers of either strand, and how many: ``(u, v, n_shared)``, or with diagonals the rows of ``overlap.candidates``."""
    parts, width = PARTS * int(reads.sparkSession.conf.get("spark.sql.shuffle.partitions", "200")), 6 if by_diagonal else 3

    def cut(batches):
        held, n = [], 0
        for batch in batches:
            for got in _chunks(batch, k):
                held.append(got)
                n += len(got[0])
                if n >= FLUSH:
                    yield _packed(held, parts)
                    held, n = [], 0
        if n:
            yield _packed(held, parts)

    def meet(batches):
        held, n = [], 0
        for blobs in _by_part(batches):
            for got in _products(*_unpacked(blobs), k, by_diagonal):
                if len(got[0]):
                    held.append(got)
                    n += len(got[0])
                if n >= ROWS:
                    yield _dealt(held, parts)
                    held, n = [], 0
        if n:
            yield _dealt(held, parts)

    def total(batches):
        for rows in _by_part(batches):
            held, n, done = [], 0, 0
            for blob, size in rows:
                x = _columns(blob, [(t, size) for t in _KINDS[:width]])
                x[0] = np.cumsum(x[0])
                x[1] += x[0]
                held.append(tuple(x))
                n += size
                if n >= HELD + 2 * done:
                    held = [_joined(held)]
                    n = done = len(held[0][0])
            u, v, shared, *more = _joined(held)
            for a in range(0, len(u), 1 << 16):
                cols = [pa.array(c[a : a + (1 << 16)]) for c in (u, v, shared)]
                if by_diagonal:
                    line, first, final = (c[a : a + (1 << 16)] for c in more)
                    diag = line >> 1
                    cols[2:2] = [pa.array((line & 1).astype(bool)), pa.array(diag)]
                    cols += [pa.array(c) for c in (first, first - diag, final, final - diag)]
                yield pa.RecordBatch.from_arrays(cols, names=names)

    schema = "u long, v long, rev boolean, diag int, n_shared long, p1 int, q1 int, p2 int, q2 int" if by_diagonal else "u long, v long, n_shared long"
    names = [f.split()[0] for f in schema.split(", ")]
    one = reads.where(f"length(seq) >= {k}").selectExpr("cast(read_id as long) as read_id", "seq").mapInArrow(cut, "part int, stretches binary, classes int, n int")
    two = one.repartition("part").sortWithinPartitions("part").mapInArrow(meet, "part int, pairs binary, n int")
    out = two.repartition("part").sortWithinPartitions("part").mapInArrow(total, schema)
    if not by_diagonal:
        return out
    return out.selectExpr("u", "v", "rev", "diag", "n_shared", "named_struct('pu', p1, 'pv', q1) as seed1", "named_struct('pu', p2, 'pv', q2) as seed2")
