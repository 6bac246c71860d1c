import random

from stringweave.operators.contraction import contract_components


def union_find(edges):
    up = {}

    def top(x):
        while up.setdefault(x, x) != x:
            x = up[x]
        return x

    for a, b in edges:
        up[top(a)] = top(b)
    out = {}
    for v in list(up):
        out.setdefault(top(v), set()).add(v)
    return sorted(map(sorted, out.values()))


def test_components_of_paths_stars_cycles_and_noise(spark):
    rng = random.Random(1)
    edges = [(i, i + 1) for i in range(300)] + [(1000, 1000 + i) for i in range(1, 200)] + [(3000, 3001), (3001, 3002), (3002, 3000)]
    edges += [(rng.randrange(5000, 5400), rng.randrange(5000, 5400)) for _ in range(250)]
    edges += edges[:5] + [(b, a) for a, b in edges[:5]] + [(7, 7)]
    trace = []
    got = contract_components(spark, spark.createDataFrame(edges, "a long, b long"), trace=trace).collect()
    groups = {}
    for r in got:
        groups.setdefault(r.root, set()).add(r.v)
    assert sorted(map(sorted, groups.values())) == union_find([e for e in edges if e[0] != e[1]])
    assert len(trace) < 16


def test_components_of_nothing_and_nulls(spark):
    none = spark.createDataFrame([], "a long, b long")
    assert contract_components(spark, none).count() == 0
    odd = spark.createDataFrame([(None, 1), (2, None), (3, 3)], "a long, b long")
    assert contract_components(spark, odd).count() == 0
