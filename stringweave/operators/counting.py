"""Counts of long k-mers by minimizers: neighbouring k-mers travel together, as one stretch of bases.

Every k-mer belongs to the smallest hashed m-mer in it, a strand-free choice.  k-mers that stand in a row and share
it are moved as one stretch (first k-mer, bases after it), so a k-mer costs about a byte of shuffle in place
of sixteen.  All occurrences of a k-mer meet in the part of its minimizer, where they are spread out and counted exactly.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from stringweave.operators import overlap

#: Bases of a minimizer, parts for each shuffle partition, bases a step, stretches a flush, k-mers counted at once.
M, PARTS, STEP, FLUSH, HELD = 13, 16, 1 << 17, 1 << 19, 1 << 22
#: Most k-mers of a stretch: the bases after the first one fill a long.
LONGEST = 32


def _two_bases(text: np.ndarray) -> np.ndarray:
    """The bases of bytes as ``dna.hex2`` gives them, as numbers."""
    out = np.empty(2 * len(text), np.uint8)
    out[0::2], out[1::2] = (text >> 4) & 3, text & 3
    return out


def _stretches(bases: np.ndarray, ok: np.ndarray | None, k: int, both_strands: bool):
    """``(minimizer, first k-mer, bases after it, k-mers)`` of the runs of k-mers that share a minimizer.

    ``ok`` marks windows that are k-mers.  The bases after the first k-mer stand at the high end of a number of 62 bits.
    """
    n = len(bases) - k + 1
    fore = np.zeros(len(bases) + 16, np.uint32)
    fore[: len(bases)] = bases
    back, size = 3 - fore, 1
    while size < 16:  # words of 16 bases by doubling, of either strand
        m, two = len(fore) - size, np.uint32(2 * size)
        fore, back, size = (fore[:m] << two) | fore[size:], (back[size:] << two) | back[:m], 2 * size
    word = fore[: n + k - M] >> np.uint32(2 * (16 - M))
    if both_strands:
        word = np.minimum(word, back[: n + k - M] & np.uint32(4**M - 1))
    low, size = word * np.uint32(0x9E3779B1), 1
    while 2 * size <= k - M + 1:
        low, size = np.minimum(low[:-size], low[size:]), 2 * size
    low = np.minimum(low[:n], low[k - M + 1 - size :][:n])
    turn = low[1:] != low[:-1]
    if ok is not None:
        turn |= ok[1:] != ok[:-1]
    at = np.concatenate(([0], np.flatnonzero(turn) + 1))
    length = np.diff(at, append=n)
    if ok is not None:
        at, length = at[ok[at]], length[ok[at]]
    most = min(LONGEST, k + 1)
    if len(length) and length.max() > most:
        cut = -(-length // most)
        within = np.arange(cut.sum()) - np.repeat(np.cumsum(cut) - cut, cut)
        at, length = np.repeat(at, cut) + most * within, np.minimum(np.repeat(length, cut) - most * within, most)
    rest = 2 * (k - 16)
    code = lambda i: (fore[i].astype(np.uint64) << np.uint64(rest)) | (fore[i + k - 16] & np.uint32((1 << rest) - 1))
    after = (code(at + length - 1) << (64 - 2 * (length - 1)).clip(max=63).astype(np.uint64)) >> np.uint64(2)
    return low[at], code(at), np.where(length > 1, after, np.uint64(0)), length.astype(np.uint8)


def _planes(values: np.ndarray) -> bytes:
    """Numbers byte by byte, all first bytes first; near numbers then pack well."""
    return np.ascontiguousarray(values.view(np.uint8).reshape(len(values), -1).T).tobytes()


def _numbers(raw: np.ndarray, kind: type) -> np.ndarray:
    return np.ascontiguousarray(raw.reshape(np.dtype(kind).itemsize, -1).T).reshape(-1).view(kind)


def _packed_parts(held: list[tuple], parts: int) -> pa.RecordBatch:
    """A row for each part: its stretches, equal ones once with the times they occur."""
    low, head, after, length = (np.concatenate(x) for x in zip(*held))
    z = low * np.uint32(0x85EBCA6B)
    z = (z ^ (z >> np.uint32(16))) * np.uint32(0xC2B2AE35)
    part = ((z ^ (z >> np.uint32(13))).astype(np.uint64) * np.uint64(parts) >> np.uint64(32)).astype(np.int32)
    order = np.lexsort((length, after, head, part))
    part, head, after, length = part[order], head[order], after[order], length[order]
    new = np.concatenate(([True], (part[1:] != part[:-1]) | (head[1:] != head[:-1]) | (after[1:] != after[:-1]) | (length[1:] != length[:-1])))
    at = np.flatnonzero(new)
    times = np.diff(at, append=len(new)).astype(np.uint32)
    part, head, after, length = part[at], head[at], after[at], length[at]
    ends = np.flatnonzero(np.concatenate((part[1:] != part[:-1], [True]))) + 1
    ids, blobs, sizes, a = [], [], [], 0
    for b in ends.tolist():
        raw = _planes(head[a:b]) + _planes(after[a:b]) + length[a:b].tobytes() + _planes(times[a:b])
        ids.append(part[a])
        blobs.append(pa.compress(raw, codec="zstd", asbytes=True))
        sizes.append(b - a)
        a = b
    return pa.RecordBatch.from_arrays([pa.array(ids, pa.int32()), pa.array(blobs, pa.binary()), pa.array(sizes, pa.int32())], names=["part", "stretches", "n"])


def _turned(code: np.ndarray, k: int) -> np.ndarray:
    """The other strand of k-mers."""
    x = ~code
    for s, mask in ((2, 0x3333333333333333), (4, 0x0F0F0F0F0F0F0F0F), (8, 0x00FF00FF00FF00FF), (16, 0x0000FFFF0000FFFF)):
        x = ((x >> np.uint64(s)) & np.uint64(mask)) | ((x & np.uint64(mask)) << np.uint64(s))
    return ((x >> np.uint64(32)) | (x << np.uint64(32))) >> np.uint64(64 - 2 * k)


def _spread(blob: bytes, n: int, k: int, both_strands: bool):
    """The k-mers of stretches and the times they occur, a piece for each place in the stretch."""
    raw = np.frombuffer(pa.decompress(blob, decompressed_size=21 * n, codec="zstd"), np.uint8)
    fore, after, length, times = _numbers(raw[: 8 * n], np.uint64), _numbers(raw[8 * n : 16 * n], np.uint64), raw[16 * n : 17 * n], _numbers(raw[17 * n :], np.uint32)
    order = np.argsort(length)[::-1]  # those that go on stand first
    fore, after, times = fore[order], after[order], times[order]
    going = n - np.cumsum(np.bincount(length, minlength=LONGEST + 1))
    back, mask = _turned(fore, k), np.uint64((1 << (2 * k)) - 1)
    for j in range(1, LONGEST + 1):
        yield (np.minimum(fore, back) if both_strands else fore), times
        m = int(going[j])
        if not m:
            return
        base = after[:m] >> np.uint64(60)
        after, times = (after[:m] << np.uint64(2)) & np.uint64((1 << 62) - 1), times[:m]
        fore, back = ((fore[:m] << np.uint64(2)) | base) & mask, (back[:m] >> np.uint64(2)) | ((np.uint64(3) - base) << np.uint64(2 * k - 2))


def _summed(codes: list[np.ndarray], times: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Each k-mer once, in order, with the sum of its times."""
    code, n = np.concatenate(codes), np.concatenate(times)
    many = n > 1
    if not many.any():
        code = np.sort(code)
        at = np.flatnonzero(np.concatenate(([True], code[1:] != code[:-1])))
        return code[at], np.diff(at, append=len(code))
    if many.mean() < 0.25:  # a plain sort is faster than one that carries times along
        return _merged(_summed([code[~many]], [n[~many]]), _summed([code[many]], [n[many]]))
    order = np.argsort(code)
    code = code[order]
    at = np.flatnonzero(np.concatenate(([True], code[1:] != code[:-1])))
    return code[at], np.add.reduceat(n[order].astype(np.int64), at)


def _merged(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Two results of ``_summed`` as one."""
    at = np.searchsorted(a[0], b[0])
    there = at < len(a[0])
    there[there] = a[0][at[there]] == b[0][there]
    a[1][at[there]] += b[1][there]
    return np.insert(a[0], at[~there], b[0][~there]), np.insert(a[1], at[~there], b[1][~there])


#: Four bases of every byte.
_FOUR = np.frombuffer("".join("ACGT"[b >> 6] + "ACGT"[b >> 4 & 3] + "ACGT"[b >> 2 & 3] + "ACGT"[b & 3] for b in range(256)).encode(), np.uint32)


def _words(code: np.ndarray, k: int) -> pa.Array:
    """k-mers as strings."""
    letters = _FOUR[(code << np.uint64(64 - 2 * k)).byteswap().view(np.uint8).reshape(len(code), 8)].view(np.uint8).reshape(len(code), 32)
    return pa.Array.from_buffers(pa.string(), len(code), [None, pa.py_buffer(np.arange(0, k * len(code) + 1, k, dtype=np.int32)), pa.py_buffer(np.ascontiguousarray(letters[:, :k]))])


def _counted(texts: DataFrame, k: int, both_strands: bool, hex2: bool, give, schema: str) -> DataFrame:
    parts = PARTS * int(texts.sparkSession.conf.get("spark.sql.shuffle.partitions", "200"))

    def cut(batches):
        held, n = [], 0
        for batch in batches:
            col = batch.column(0).cast(pa.string())
            ends = np.frombuffer(col.buffers()[1], np.int32)[col.offset : col.offset + len(col) + 1].astype(np.int64)
            data = np.frombuffer(col.buffers()[2] or b"", np.uint8)[ends[0] : ends[-1]] if len(col) else np.zeros(0, np.uint8)
            ends = (ends[1:] - ends[0]) * (2 if hex2 else 1)  # where a sequence ends in the whole
            total, each = len(data) * (2 if hex2 else 1), 2 if hex2 else 1
            for a in range(0, total - k + 1, STEP):
                b = min(total, a + STEP + k - 1)
                piece = data[a // each : -(-b // each)]
                bases = _two_bases(piece)[: b - a] if hex2 else overlap._CODE[piece].astype(np.uint8)
                ok = None if hex2 else overlap.known(piece.tobytes(), k)
                inside = ends[np.searchsorted(ends, a, "right") : np.searchsorted(ends, b)] - a
                if len(inside):  # windows over an end are no k-mers
                    ok = np.ones(len(bases) - k + 1, bool) if ok is None else ok
                    over = (inside[:, None] - np.arange(1, k)).ravel()
                    ok[over[(over >= 0) & (over < len(ok))]] = False
                held.append(_stretches(bases, ok, k, both_strands))
                n += len(held[-1][0])
                if n >= FLUSH:
                    yield _packed_parts(held, parts)
                    held, n = [], 0
        if n:
            yield _packed_parts(held, parts)

    def count(batches):
        codes, times, n, now, done = [], [], 0, None, None

        def total():
            return _summed(codes, times) if done is None else _merged(done, _summed(codes, times)) if n else done

        for batch in batches:
            for part, blob, size in zip(*(batch.column(i).to_pylist() for i in range(3))):
                if part != now and now is not None:
                    yield from give(*total())
                    codes, times, n, done = [], [], 0, None
                now = part
                for c, t in _spread(blob, size, k, both_strands):
                    codes.append(c)
                    times.append(t)
                    n += len(c)
                if n >= max(HELD, 0 if done is None else len(done[0]) // 2):  # what is done grows by shares, so a large part is not gone through at every step
                    codes, times, n, done = [], [], 0, total()
        if now is not None:
            yield from give(*total())

    one = texts.mapInArrow(cut, "part int, stretches binary, n int")
    return one.repartition("part").sortWithinPartitions("part").mapInArrow(count, schema)


def _pieces(code: np.ndarray, n: np.ndarray, size: int = 1 << 16):
    for a in range(0, len(code), size):
        yield code[a : a + size], n[a : a + size]


def fits(k: int) -> bool:
    """k-mers long enough for stretches to be shorter than their k-mers, short enough for a long."""
    return M + 9 <= k <= 31


def words(texts: DataFrame, k: int, both_strands: bool = True, hex2: bool = False) -> DataFrame:
    """``(kmer, n)`` with the k-mers as strings, of one column of sequences, or with ``hex2`` of texts whose bytes are two bases each."""

    def give(code, n):
        for c, m in _pieces(code, n):
            yield pa.RecordBatch.from_arrays([_words(c, k), pa.array(m, pa.int64())], names=["kmer", "n"])

    return _counted(texts, k, both_strands, hex2, give, "kmer string, n long")


def histogram(texts: DataFrame, k: int, both_strands: bool = True, hex2: bool = False) -> DataFrame:
    """``(n, kmers)``, to be summed by n: how many k-mers occur how often in each part."""

    def give(_, n):
        times, kmers = np.unique(n, return_counts=True)
        yield pa.RecordBatch.from_arrays([pa.array(times, pa.int64()), pa.array(kmers, pa.int64())], names=["n", "kmers"])

    return _counted(texts, k, both_strands, hex2, give, "n long, kmers long")
