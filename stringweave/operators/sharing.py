"""Which reads share k-mers, as classes of equal stretches and the k-mers that each shares: linear in the reads, and no link is lost.

Every two reads that share a k-mer are far more rows than reads, as texts repeat phrases and mark-up.  Here each
stretch of k-mers (see ``meeting``) belongs to one class, and a row has a class's reads and those of its k-mers that
are found more than once.  Two reads share k-mers if classes of theirs have a k-mer in common; ``expanded`` gives these pairs.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stringweave.operators.meeting import M, _blob, _blocks, _by_part, _chunks, _columns, _in_order, _mixed, _runs

#: Parts for each shuffle partition, stretches a flush, stretches and k-mers looked at at once, reads a row, reads and k-mers a batch; bases beside an m-mer that one class has in common with what tells it.
PARTS, FLUSH, HELD, MOST, PIECE, BATCH, NEAR = 16, 1 << 20, 1 << 19, 1 << 19, 4096, 1 << 16, 6
_ONE, _WORD = np.uint64(1), np.uint64(64)


def _short(k: int) -> int:
    """Bases of an m-mer: the fewer, the more k-mers a stretch has."""
    return min(M, k - 6)


def _mmer(z: np.ndarray) -> np.ndarray:
    """The m-mer behind the number that ``meeting`` has for it; every step of the mixing is undone."""
    turned = lambda p: np.uint32(pow(p, -1, 1 << 32))
    z = (z ^ (z >> np.uint32(13)) ^ (z >> np.uint32(26))) * turned(0xC2B2AE35)
    return (z ^ (z >> np.uint32(16))) * turned(0x85EBCA6B) * turned(0x9E3779B1)


def _forward(right: np.ndarray) -> np.ndarray:
    """Bases right of an m-mer as they lie on its strand, the nearest at the high end."""
    x = ~right
    for bits, mask in ((2, 0x3333333333333333), (4, 0x0F0F0F0F0F0F0F0F)):
        b, m = np.uint64(bits), np.uint64(mask)
        x = ((x >> b) & m) | ((x & m) << b)
    return x.byteswap()


def _cut(word: np.ndarray, some: np.ndarray) -> np.ndarray:
    return word & ((_ONE << (2 * some).astype(np.uint64)) - _ONE)


def _largest(key: np.ndarray, n: np.ndarray) -> np.ndarray:
    """For each class the largest one of its key."""
    order = np.lexsort((-n, key))
    new = np.concatenate(([True], key[order][1:] != key[order][:-1]))
    out = np.empty(len(key), np.int64)
    out[order] = order[np.flatnonzero(new)[np.cumsum(new) - 1]]
    return out


def _leads(z: np.ndarray, left: np.ndarray, right: np.ndarray, shape: np.ndarray, n: np.ndarray) -> np.ndarray:
    """For each class the one by which it is told, often itself: the largest of its m-mer that has the same ``NEAR`` bases left or right of it."""
    own, high = np.arange(len(z)), z.astype(np.uint64) << np.uint64(32)

    def beside(side, some):
        known = some >= NEAR
        return np.where(known, _largest(np.where(known, high | (_cut(side, np.full(1, NEAR)) << _ONE) | _ONE, high), n), own)

    lead, other = beside(left, shape & 31), beside(right, shape >> 5)
    more = (lead == own) & (n[other] > n)  # what leads is larger each time, so this ends
    lead[more] = other[more]
    while not np.array_equal(lead, further := lead[lead]):
        lead = further
    return lead


def _bits(values: np.ndarray, n: np.ndarray) -> bytes:
    """The lowest bits of numbers, ``n`` of each, one after the other."""
    wide = -(-int(n.max(initial=0)) // 8)
    some = np.unpackbits(values.view(np.uint8).reshape(-1, 8)[:, :wide], axis=1, bitorder="little")
    return np.packbits(some[np.arange(8 * wide) < n[:, None]], bitorder="little").tobytes()


def _from_bits(raw: bytes, n: np.ndarray) -> np.ndarray:
    wide = -(-int(n.max(initial=0)) // 8)
    held = np.arange(8 * wide) < n[:, None]
    some, out = np.zeros(held.shape, np.uint8), np.zeros((len(n), 8), np.uint8)
    some[held] = np.unpackbits(np.frombuffer(raw, np.uint8), count=int(n.sum()), bitorder="little")
    out[:, :wide] = np.packbits(some, axis=1, bitorder="little")
    return out.view(np.uint64).reshape(-1)


def _framed(*parts: bytes) -> bytes:
    """Parts behind the lengths of all but the last."""
    return np.array([len(p) for p in parts[:-1]], np.int32).tobytes() + b"".join(parts)


def _parts(blob: bytes, n: int) -> list[bytes]:
    ends = 4 * (n - 1) + np.cumsum([0, *np.frombuffer(blob, np.int32, n - 1)])
    return [blob[i:j] for i, j in zip(ends.tolist(), [*ends[1:].tolist(), len(blob)])]


def _widths(shape: np.ndarray, far: np.ndarray, few: int) -> np.ndarray:
    """Bits of the bases left and right of each class that is told by none, then of each class's first read."""
    own = shape[~far].astype(np.int64)
    return np.concatenate((2 * (own & 31), 2 * (own >> 5), np.full(len(shape), (few - 1).bit_length())))


def _told(z, left, right, shape, far, n, read) -> tuple[bytes, bytes, int]:
    """Classes, their reads, and how many reads these are.

    Bases and first reads go bit by bit, as they hardly repeat; the bases of a class that another one tells are what differs from it.
    """
    few = np.unique(read)
    place = np.searchsorted(few, read)
    first = np.cumsum(n) - n
    rest = np.ones(len(read), bool)
    rest[first] = False
    bits = _bits(np.concatenate((left[~far], right[~far], place[first].astype(np.uint64))), _widths(shape, far, len(few)))
    differ = _blob(left[far], right[far]) if far.any() else b""
    more = _blob(np.diff(place, prepend=0)[rest].astype(np.int32)) if rest.any() else b""
    classes = _blob(np.diff(z, prepend=np.uint32(0)), shape | (far.astype(np.uint16) << np.uint16(10)), n.astype(np.uint32))
    return _framed(classes, differ), _framed(_blob(np.diff(few, prepend=0)), more, bits), len(few)


def _back(classes: bytes, reads: bytes, c: int, n: int, few: int) -> tuple:
    """What ``_told`` was given, each class with all its bases."""
    (own, differ), (table, more, bits) = _parts(classes, 2), _parts(reads, 3)
    z, shape, each = _columns(own, [(np.uint32, c), (np.uint16, c), (np.uint32, c)])
    far, shape = shape >> np.uint16(10) == 1, shape & np.uint16(1023)
    values, alone = _from_bits(bits, _widths(shape, far, few)), c - int(far.sum())
    left, right = np.empty(c, np.uint64), np.empty(c, np.uint64)
    left[~far], right[~far] = values[:alone], values[alone : 2 * alone]
    if alone < c:
        lead = np.maximum.accumulate(np.where(far, 0, np.arange(c)))[far]
        for side, some, x in zip((left, right), (shape[far] & np.uint16(31), shape[far] >> np.uint16(5)), _columns(differ, [(np.uint64, c - alone)] * 2)):
            side[far] = x ^ _cut(side[lead], some)
    step, first = np.empty(n, np.int64), np.cumsum(each, dtype=np.int64) - each
    rest = np.ones(n, bool)
    rest[first] = False
    if c < n:
        step[rest] = _columns(more, [(np.int32, n - c)])[0]
    step[first] = 0
    sums, place = np.cumsum(step), values[2 * alone :].astype(np.int64)
    at = sums + np.repeat(place - sums[first], each)
    return np.cumsum(z, dtype=np.uint32), left, right, shape, each, np.cumsum(_columns(table, [(np.int64, few)])[0])[at]


def _packed(held: list[tuple], parts: int) -> pa.RecordBatch:
    """A row for each part: its classes, and the reads of each; a class stands behind the one by which it is told.  ``held`` is empty then."""
    read, z, left, right, shape = (np.concatenate(x) for x in zip(*held))
    held.clear()  # these are large
    order, at = _in_order(z, left, right, shape)
    first, n = order[at], np.diff(at, append=len(order))
    z, left, right, shape = z[first], left[first], right[first], shape[first]
    del first
    lead = _leads(z, left, right, shape, n)
    far = lead != np.arange(len(z))
    left, right = (np.where(far, x ^ _cut(x[lead], some), x) for x, some in ((left, shape & np.uint16(31)), (right, shape >> np.uint16(5))))
    by = np.lexsort((far, lead, z))
    read, n = read[order[_runs(at[by], n[by])]], n[by]
    z, left, right, shape, far = z[by], left[by], right[by], shape[by], far[by]
    part, start = (z.astype(np.uint64) * np.uint64(parts) >> np.uint64(32)).astype(np.int32), np.concatenate(([0], np.cumsum(n)))
    rows, a = [], 0
    for b in (np.flatnonzero(np.concatenate((part[1:] != part[:-1], [True]))) + 1).tolist():
        i, j = int(start[a]), int(start[b])
        classes, reads, few = _told(*(x[a:b] for x in (z, left, right, shape, far, n)), read[i:j])
        rows.append((int(part[a]), classes, reads, b - a, j - i, few))
        a = b
    kinds = (pa.int32(), pa.binary(), pa.binary(), pa.int32(), pa.int32(), pa.int32())
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names=["part", "classes", "reads", "c", "n", "few"])


def _unpacked(blobs: list):
    """Classes of a part, those of an m-mer together, how many reads each has, and these; a range of m-mers after the other."""
    got = [_back(*blob) for blob in blobs]
    low, high = min(int(x[0][0]) for x in got), max(int(x[0][-1]) for x in got) + 1
    slices = -(-sum(len(x[-1]) for x in got) // HELD)
    ends = np.array([low + (high - low) * i // slices for i in range(slices + 1)], np.uint64)
    cuts = [np.searchsorted(x[0], ends) for x in got]
    starts = [np.concatenate(([0], np.cumsum(x[4], dtype=np.int64))) for x in got]
    for i in range(slices):
        some = [(*(c[e[i] : e[i + 1]] for c in x[:5]), x[5][s[e[i]] : s[e[i + 1]]]) for x, e, s in zip(got, cuts, starts) if e[i] < e[i + 1]]
        if not some:
            continue
        z, left, right, shape, each, read = (np.concatenate(x) for x in zip(*some))
        order, at = _in_order(z, left, right, shape)
        each, first = each.astype(np.int64), order[at]
        begin = (np.cumsum(each) - each)[order]
        yield (z[first], left[first], right[first], shape[first].astype(np.int64)), np.add.reduceat(each[order], at), read[_runs(begin, each[order])]


def _shared(classes, total, read, k: int, short: int):
    """Batches of ``(class, reads, k-mers)`` of the classes that have k-mers found more than once."""
    z, left, right, shape = classes
    nl, nr, start = shape & 31, shape >> 5, np.cumsum(total) - total
    lo, many = k - short - nr, nl + nr - (k - short) + 1
    mmer, fore = _mmer(z).astype(np.uint64), _forward(right)
    ids = ((left * np.uint64(0x9E3779B97F4A7C15)) ^ (right * np.uint64(0xC2B2AE3D27D4EB4F)) ^ (((z.astype(np.uint64) << np.uint64(10)) | shape.astype(np.uint64)) * np.uint64(0x165667B19E3779F9))).view(np.int64)
    heads = np.flatnonzero(np.concatenate(([True], z[1:] != z[:-1])))
    heads_end = np.append(heads, len(z))
    for x, y in _blocks(np.add.reduceat(many, heads), MOST):
        a, b = heads_end[x], heads_end[y]
        own = np.repeat(np.arange(a, b), many[a:b])
        some = _runs(lo[a:b], many[a:b])
        rest = k - short - some
        tail = np.where(rest > 0, fore[own] >> (_WORD - 2 * np.maximum(rest, 1).astype(np.uint64)), np.uint64(0))
        code = (((_cut(left[own], some) << np.uint64(2 * short)) | mmer[own]) << (2 * rest).astype(np.uint64)) | tail
        order = np.argsort(code)
        at = np.flatnonzero(np.concatenate(([True], np.diff(code[order]) != 0)))
        keep = np.empty(len(code), bool)
        keep[order] = np.repeat(np.add.reduceat(total[own[order]], at) > 1, np.diff(at, append=len(order)))
        n = np.bincount(own[keep] - a, minlength=b - a)
        kmers, begin, here = code[keep].view(np.int64), np.cumsum(n) - n, np.flatnonzero(n)
        pieces = -(-total[here + a] // PIECE)
        within, here = _runs(np.zeros_like(pieces), pieces), np.repeat(here, pieces)
        first = start[here + a] + within * PIECE
        size = np.minimum(PIECE, total[here + a] - within * PIECE)
        for i, j in _blocks(size + n[here], BATCH):
            h, f, s = here[i:j], first[i:j], size[i:j]
            listed = lambda values, n: pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(n))).astype(np.int32)), pa.array(values))
            yield pa.RecordBatch.from_arrays([pa.array(ids[h + a]), listed(read[_runs(f, s)], s), listed(kmers[_runs(begin[h], n[h])], n[h])], names=["class_id", "reads", "kmers"])


def classes(reads: DataFrame, k: int) -> DataFrame:
    """Classes of equal stretches of k-mers: ``(class_id, reads, kmers)``; no k-mer that is found twice is left out.

    ``reads`` has the ids of the reads with the stretch, as often as it stands in them, in rows of ``PIECE`` at
    most; ``kmers`` the stretch's k-mers that the reads hold more than once in all, two bits a base, in the strand of their m-mer.
    """
    tasks, short = int(reads.sparkSession.conf.get("spark.sql.shuffle.partitions", "200")), _short(k)
    parts = PARTS * tasks

    def cut(batches):
        held, n = [], 0
        for batch in batches:
            for read, _, _, _, z, left, right, shape in _chunks(batch, k, short):
                shape = shape & np.uint16(1023)  # the letters beyond decide nothing here
                held.append((read, z, _cut(left, shape & np.uint16(31)), _cut(right, shape >> np.uint16(5)), shape))
                n += len(read)
                if n >= FLUSH:
                    yield _packed(held, parts)
                    held, n = [], 0
        if n:
            yield _packed(held, parts)

    def meet(batches):
        for blobs in _by_part(batches):
            for some in _unpacked(blobs):
                yield from _shared(*some, k, short)

    one = reads.where(f"length(seq) >= {k}").selectExpr("cast(read_id as long) as read_id", "seq").mapInArrow(cut, "part int, classes binary, reads binary, c int, n int, few int")
    return one.repartitionById(tasks, F.col("part") % tasks).sortWithinPartitions("part").mapInArrow(meet, "class_id long, reads array<long>, kmers array<long>")


def expanded(found: DataFrame) -> DataFrame:
    """The pairs that classes stand for, as ``meeting.pairs`` has them: ``(u, v, n_shared)``."""
    each = found.select(F.explode("kmers").alias("kmer"), "reads").select("kmer", F.explode("reads").alias("u"))
    return each.join(each.select("kmer", F.col("u").alias("v")), "kmer").where("u < v").groupBy("u", "v").agg(F.count("*").alias("n_shared"))
