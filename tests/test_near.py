"""Near copies against all pairs."""

import random
import re

import pytest

from stringweave.operators import near


def by_all_pairs(rows, k=5, t=0.8):
    sets = []
    for _, text in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", text or "")
        sets.append({" ".join(w[i : i + k]) for i in range(max(1, len(w) - k + 1))} if w else set())
    link = [[i != j and bool(a) and bool(b) and len(a & b) * 10 >= 8 * len(a | b) for j, b in enumerate(sets)] for i, a in enumerate(sets)]
    out = []
    for i, (doc_id, _) in enumerate(rows):
        seen, todo = {i}, [i]
        while todo:
            new = [j for j, x in enumerate(link[todo.pop()]) if x and j not in seen]
            seen.update(new)
            todo += new
        out.append((doc_id, min(rows[j][0] for j in seen), sum(link[i])))
    return sorted(out)


def texts():
    r, words = random.Random(4), [f"w{i}" for i in range(300)]
    out = [None, "", " \t\n", "one two", "one  two", "one\ttwo three four", " ", "a " * 9, "a " * 20, "Z", "Z"]
    for _ in range(12):
        base = [r.choice(words) for _ in range(r.randint(5, 90))]
        out.append(" ".join(base))
        for _ in range(r.randint(0, 6)):
            other = list(base)
            for _ in range(r.randint(0, 3)):
                other[r.randrange(len(other))] = r.choice(words)
            out.append(r.choice([" ", "  ", "\n"]).join(other) + " tail" * r.randint(0, 2))
    return [(i * 37 % 997, x) for i, x in enumerate(out)]


@pytest.mark.parametrize("piece", [512, 2])
def test_classes_and_links_are_those_of_all_pairs(spark, monkeypatch, piece):
    monkeypatch.setattr(near, "PIECE", piece)
    rows = texts()
    got = near.near_copies(spark.createDataFrame(rows, "doc_id long, text string"))
    want = by_all_pairs(rows)
    assert sorted(map(tuple, got.collect())) == want
    assert sum(x[2] for x in want) > 40


def test_no_rows_and_other_columns(spark):
    assert near.near_copies(spark.createDataFrame([], "doc_id long, text string")).count() == 0
    odd = spark.createDataFrame([(2, "a b c d e f", 1, 2), (1, "a b c d e f", 3, 4), (None, "q", 5, 6)], "doc_id long, text string, h int, cls int")
    assert {tuple(r) for r in near.near_copies(odd).collect()} == {(1, 1, 1), (2, 1, 1), (None, None, 0)}
