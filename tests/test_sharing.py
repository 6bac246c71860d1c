"""Classes of stretches stand for the pairs of reads that share k-mers, all of them and no others."""

import tracemalloc

import numpy as np
import pytest

import __spark_entry__ as entry
from stringweave.operators import meeting, sharing
from stringweave.plans import workloads
from test_meeting import odd_reads  # noqa: F401

SMALL = "/root/testdata/sf0.001"


@pytest.mark.parametrize("k", [17, 31])
def test_classes_expand_to_the_pairs(odd_reads, k):  # noqa: F811
    want = sorted(map(tuple, meeting.pairs(odd_reads, k).collect()))
    assert sorted(map(tuple, sharing.expanded(sharing.classes(odd_reads, k)).collect())) == want and len(want) > 600


def test_pieces_and_blocks_change_nothing(monkeypatch, odd_reads):  # noqa: F811
    import pyarrow as pa

    rows = odd_reads.where("length(seq) >= 17").collect()
    batch = pa.RecordBatch.from_arrays([pa.array([r.read_id for r in rows]), pa.array([r.seq for r in rows])], names=["read_id", "seq"])

    def found(flushes):
        held = []
        for read, _, _, _, z, left, right, shape in meeting._chunks(batch, 17, 11):
            shape = shape & np.uint16(1023)
            held.append((read, z, sharing._cut(left, shape & np.uint16(31)), sharing._cut(right, shape >> np.uint16(5)), shape))
        blobs = [row for part in np.array_split(np.arange(len(held)), flushes) for b in [sharing._packed([held[i] for i in part], 1)] for row in zip(*(b.column(i).to_pylist() for i in range(1, 6)))]
        out, most, widest = {}, 0, 0
        for b in (b for some in sharing._unpacked(blobs) for b in sharing._shared(*some, 17, 11)):
            widest = max(widest, sum(len(x.flatten()) for x in b.columns[1:]))
            for c, reads, kmers in zip(*(x.to_pylist() for x in b.columns)):
                most = max(most, len(reads))
                one = out.setdefault(c, ([], sorted(kmers)))
                one[0].extend(reads)
                assert one[1] == sorted(kmers)
        return {c: (sorted(reads), kmers) for c, (reads, kmers) in out.items()}, most, widest

    monkeypatch.setattr(meeting, "STEP", 500)
    want, most, _ = found(1)
    for name, value in (("MOST", 7), ("PIECE", 3), ("BATCH", 5), ("HELD", 40)):
        monkeypatch.setattr(sharing, name, value)
    got, least, widest = found(5)
    assert got == want and len(want) > 200 and most > 3 >= least and widest <= 3 + 17  # at the least a row, with all its k-mers


@pytest.mark.parametrize("name", ["w02", "w03"])
def test_candidates_are_rows_in_proportion_to_the_reads(spark, name):
    reads = workloads.workload_reads(spark, SMALL, name)
    got = entry.queries()[f"candidates_{name}"](spark, SMALL)
    assert got.columns == ["class_id", "reads", "kmers"]
    n, held = got.selectExpr("count(*)", "sum(size(reads))").first()
    assert 0 < n <= held <= reads.selectExpr("sum(length(seq))").first()[0]
    some = got.where("exists(reads, r -> r % 20 = 0)").selectExpr("explode(reads) as r", "kmers").where("r % 20 = 0").count()
    assert some > 0


def test_stretches_of_one_mix_stand_together():
    few = np.random.default_rng(2).integers(0, 1 << 36, 300_000, dtype=np.uint64)  # some ten of them have the mix of another
    left = np.tile(few, 3)
    none = np.zeros(len(left), np.uint32)
    order, at = meeting._in_order(none, left, none.astype(np.uint64), none.astype(np.uint16))
    assert np.array_equal(np.sort(left[order[at]]), np.unique(few)) and np.array_equal(np.sort(order), np.arange(len(left)))


def test_rows_of_a_part_are_taken_one_by_one():
    import pyarrow as pa

    blob = b"x" * (1 << 20)
    batch = pa.RecordBatch.from_arrays([pa.array([1, 1, 2, 3, 3] + list(range(4, 60))), pa.array([blob] * 61, pa.binary())], names=["part", "b"])
    tracemalloc.start()
    sizes = [len(held) for held in meeting._by_part([batch])]
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert sizes == [2, 1, 2] + [1] * 56 and most < 8 << 20


def packed_stretches(n, seed=3):
    """Reads of a long string in steps, one base in a hundred replaced, as stretches."""
    import pyarrow as pa

    rng = np.random.default_rng(seed)
    letters, text = np.frombuffer(b"ACGT", np.uint8), rng.integers(0, 4, 13 * n + 390)
    rows = []
    for i in range(n):
        one = text[13 * i : 13 * i + 390].copy()
        one[rng.random(390) < 0.005] += 1
        rows.append(letters[one % 4].tobytes().decode())
    batch = pa.RecordBatch.from_arrays([pa.array(np.arange(n) * 13 + 5_000_000_000), pa.array(rows)], names=["read_id", "seq"])
    return [(read, z, sharing._cut(left, shape & np.uint16(31)), sharing._cut(right, (shape & np.uint16(1023)) >> np.uint16(5)), shape & np.uint16(1023)) for read, _, _, _, z, left, right, shape in meeting._chunks(batch, 31, 13)]


def test_stretches_come_back_as_they_were_packed():
    held = packed_stretches(700)
    rows = sharing._packed(list(held), 7)
    assert rows.column(0).to_pylist() == list(range(7))
    got = []
    for blob in zip(*(rows.column(i).to_pylist() for i in range(1, 6))):
        z, left, right, shape, each, read = sharing._back(*blob)
        got += zip(read.tolist(), *(np.repeat(x, each).tolist() for x in (z, left, right, shape)))
    assert sorted(got) == sorted(zip(*(np.concatenate(x).tolist() for x in zip(*held))))


def test_stretches_with_errors_take_little_room():
    held = packed_stretches(4000)
    rows, n = sharing._packed(list(held), 64), sum(len(h[0]) for h in held)
    assert sum(len(b) for i in (1, 2) for b in rows.column(i).to_pylist()) < 2.9 * n  # 3.3 with bases in whole bytes


def test_bits_come_back():
    rng = np.random.default_rng(5)
    n = rng.integers(0, 65, 1000)
    values = rng.integers(0, 1 << 63, 1000, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    want = np.array([v & ((1 << b) - 1) for v, b in zip(values.tolist(), n.tolist())], np.uint64)
    assert np.array_equal(sharing._from_bits(sharing._bits(values, n), n), want)
    none = np.zeros(3, np.int64)
    assert sharing._bits(values[:3], none) == b"" and sharing._from_bits(b"", none).tolist() == [0, 0, 0]


def test_noisy_stretches_take_little_room():
    import pyarrow as pa

    rng = np.random.default_rng(4)
    letters = np.frombuffer(b"ACGT", np.uint8)
    batch = pa.RecordBatch.from_arrays([pa.array(np.arange(300) * 200), pa.array([letters[rng.integers(0, 4, 2000)].tobytes().decode() for _ in range(300)])], names=["read_id", "seq"])
    held = []
    for read, _, _, _, z, left, right, shape in meeting._chunks(batch, 17, 11):
        shape = shape & np.uint16(1023)
        held.append((read, z, sharing._cut(left, shape & np.uint16(31)), sharing._cut(right, shape >> np.uint16(5)), shape))
    rows, n = sharing._packed(list(held), 16), sum(len(h[0]) for h in held)
    taken = sum(len(b) for i in (1, 2) for b in rows.column(i).to_pylist()) / n
    assert taken < 6.8, taken  # 7.4 with bases in whole bytes
