"""Near-duplicate vectors by navigable small-world graphs, one per shard of a label.

Equal vectors of a label are one node with a count, so copies never meet.  The nodes of
a label are dealt to shards by hash; each shard gets a hierarchical navigable
small-world graph.  Every shard is then queried by every vector of the label: a task
holds two shards, searches each one's graph for the other's vectors (or its own), and
verifies what it finds by cosine in double precision.  A beam that holds links widens
through their neighbours; then an audit compares some queries with brute force, and
while links are missing the beam is widened for all; where it would be as wide as the shard,
all nodes are compared.  A task reports link counts, a spanning forest, both as long as its
vectors, and what its audits saw; components are joined over all tasks.

Vectors that are null, zero or hold null or non-finite components, and rows with a null
label or id, link with nothing: no links, a component of their own, kept.  Repeated rows
count as vectors of their own.
"""

from __future__ import annotations

import pickle

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from stringweave.llm.simhash import forest
from stringweave.operators.contraction import contract_components
from stringweave.session import Scratch

THRESHOLD = 0.98
#: Vectors per shard, on average.
SHARD_ROWS = 8192
DEGREE = 16
BEAM = 64
AUDIT_EVERY = 20
#: Queries audited at least; a shard queried by no more is audited whole.
AUDIT_LEAST = 64
AUDIT_RECALL = 0.995


class Graph:
    """A hierarchical navigable small-world graph over unit vectors, built and searched in batches."""

    def __init__(self, vectors: np.ndarray, degree: int = DEGREE, beam: int = BEAM, seed: int = 1):
        self.v, n = vectors.astype(np.float32), len(vectors)
        rng = np.random.default_rng(seed)
        level = np.minimum(rng.geometric(1 - 1 / degree, n) - 1, 4) if n else np.empty(0, np.int64)
        order = np.lexsort((rng.random(n), -level))
        self.layers: list[np.ndarray] = []  # neighbours by node, -1 where none; the top layer first
        self.entry = order[:1]
        for l in range(int(level.max()) if n else 0, -1, -1):
            members = order[: int((level >= l).sum())]
            self.layers.append(self._layer(members, degree * (2 if l == 0 else 1), degree, beam))

    def _layer(self, members: np.ndarray, room: int, degree: int, beam: int) -> np.ndarray:
        near = np.full((len(self.v), room), -1, np.int32)
        at, size = 0, 32
        while at < len(members):
            new = members[at : at + size]
            mates = self._rank(new, np.broadcast_to(new, (len(new), len(new))), self.v[new] @ self.v[new].T, min(len(new), beam // 2))
            if at:
                entry = self._descend(self.v[new]) if self.layers else np.broadcast_to(members[:1], (len(new), 1))
                entry = np.concatenate([entry, np.broadcast_to(members[:1], (len(new), 1))], axis=1)
                ids, _ = self._beam(near, self.v[new], entry, beam)
                mates = np.concatenate([mates, ids], axis=1)
            chosen = self._choose(new, mates, degree)
            near[new, :degree] = chosen
            # the links back: each target chooses anew among its old and its new neighbours
            src, dst = np.repeat(new, degree), chosen.ravel()
            src, dst = src[dst >= 0], dst[dst >= 0]
            by = np.lexsort((src, dst))
            src, dst = src[by], dst[by]
            targets, first, count = np.unique(dst, return_index=True, return_counts=True)
            for lo in range(0, len(targets), 512):
                t, f, c = targets[lo : lo + 512], first[lo : lo + 512], count[lo : lo + 512]
                back = np.full((len(t), min(int(c.max()), 4 * room)), -1, np.int64)
                for j in range(back.shape[1]):
                    some = c > j
                    back[some, j] = src[f[some] + j]
                near[t] = self._choose(t, np.concatenate([near[t], back], axis=1), room)
            at += len(new)
            size = min(512, max(32, at // 2))
        return near

    def _rank(self, of: np.ndarray, ids: np.ndarray, sims: np.ndarray, k: int) -> np.ndarray:
        """The ``k`` most similar ids of each row, without the row's own node."""
        sims = np.where((ids == of[:, None]) | (ids < 0), -np.inf, sims)
        top = np.argsort(-sims, axis=1, kind="stable")[:, :k]
        return np.where(np.take_along_axis(sims, top, 1) > -np.inf, np.take_along_axis(ids, top, 1), -1)

    def _choose(self, of: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
        """Up to ``k`` neighbours: those nearer to the node than to any chosen before, then the nearest of the rest."""
        ids = np.sort(ids, axis=1)
        ids[:, 1:][ids[:, 1:] == ids[:, :-1]] = -1
        ids = self._rank(of, ids, np.einsum("qkd,qd->qk", self.v[ids], self.v[of]), min(ids.shape[1], 4 * k))
        vec = self.v[ids]
        sims = np.where(ids >= 0, np.einsum("qkd,qd->qk", vec, self.v[of]), -np.inf)
        pair = np.einsum("qkd,qjd->qkj", vec, vec)
        taken = np.zeros(ids.shape, bool)
        for c in range(ids.shape[1]):
            close = np.where(taken, pair[:, c], -np.inf).max(axis=1)
            taken[:, c] = (ids[:, c] >= 0) & (close < sims[:, c]) & (taken.sum(axis=1) < k)
        score = np.where(taken, 2.0, 0.0) + np.where(ids >= 0, sims, -np.inf)
        top = np.argsort(-score, axis=1, kind="stable")[:, :k]
        out = np.where(np.take_along_axis(score, top, 1) > -np.inf, np.take_along_axis(ids, top, 1), -1)
        return np.pad(out, ((0, 0), (0, k - out.shape[1])), constant_values=-1)

    def _descend(self, q: np.ndarray) -> np.ndarray:
        """An entry for each query, from the upper layers."""
        entry = np.broadcast_to(self.entry, (len(q), 1))
        for near in self.layers:
            entry = self._beam(near, q, entry, 4)[0][:, :1]
        return entry

    def _beam(self, near: np.ndarray, q: np.ndarray, entry: np.ndarray, beam: int) -> tuple[np.ndarray, np.ndarray]:
        """The ``beam`` best nodes found for each query, best first (-1 where there are none), with similarities."""
        n = len(q)
        seen = np.zeros((n, len(self.v)), bool)
        entry = np.sort(entry, axis=1)
        entry = np.where(np.concatenate([np.zeros((n, 1), bool), entry[:, 1:] == entry[:, :-1]], axis=1), -1, entry)
        ids = np.concatenate([entry, np.full((n, beam), -1)], axis=1)[:, : max(beam, entry.shape[1])].astype(np.int64)
        sims = np.where(ids >= 0, np.einsum("qkd,qd->qk", self.v[ids], q), -np.inf)
        at, c = np.nonzero(ids >= 0)
        seen[at, ids[at, c]] = True
        fresh = ids >= 0
        wide = max(2, beam // 16)
        live = np.arange(n)
        while len(live):
            s = np.where(fresh[live], sims[live], -np.inf)
            k = min(wide, s.shape[1])
            pick = np.argpartition(-s, k - 1, axis=1)[:, :k]
            ok = np.take_along_axis(s, pick, 1) > -np.inf
            some = ok.any(axis=1)
            live, pick, ok = live[some], pick[some], ok[some]
            if not len(live):
                break
            fresh[live[:, None], pick] &= ~ok
            nb = near[np.take_along_axis(ids[live], pick, 1)]
            nb = np.where(ok[:, :, None], nb, -1).reshape(len(live), -1)
            nb = np.sort(nb, axis=1)
            new = nb >= 0
            new[:, 1:] &= nb[:, 1:] != nb[:, :-1]
            new &= ~seen[live[:, None], nb]
            at, c = np.nonzero(new)  # a node that stands twice in a row is new once only
            seen[live[at], nb[at, c]] = True
            sim = np.where(new, np.einsum("qkd,qd->qk", self.v[nb], q[live]), -np.inf)
            all_s = np.concatenate([sims[live], sim], axis=1)
            keep = np.argpartition(-all_s, ids.shape[1] - 1, axis=1)[:, : ids.shape[1]]
            sims[live] = np.take_along_axis(all_s, keep, 1)
            ids[live] = np.take_along_axis(np.concatenate([ids[live], np.where(new, nb, -1)], axis=1), keep, 1)
            fresh[live] = np.take_along_axis(np.concatenate([fresh[live], new], axis=1), keep, 1)
        top = np.argsort(-sims, axis=1, kind="stable")[:, :beam]
        return np.take_along_axis(ids, top, 1), np.take_along_axis(sims, top, 1)

    def within(self, q: np.ndarray, at_least: float, beam: int, own: bool = False) -> tuple[np.ndarray, np.ndarray]:
        """(query, node) pairs of similarity ``at_least``.

        A beam that holds such nodes widens without bound: their neighbours are looked at
        until no new node is similar enough.  With ``own`` the queries are the graph's nodes
        and start from themselves.
        """
        q, n = q.astype(np.float32), len(self.v)
        found_q, found_v = [np.empty(0, np.int64)], [np.empty(0, np.int64)]
        step = max(1, min(512, 100_000_000 // max(n, 2000 * beam)))
        near = self.layers[-1] if n else None
        for a in range(0, len(q) if n else 0, step):
            mine = q[a : a + step]
            if beam >= n:
                i, v = np.nonzero(mine @ self.v.T >= at_least)
                found_q.append(i + a)
                found_v.append(v)
                continue
            entry = np.broadcast_to(self.entry, (len(mine), 1))
            for layer in self.layers[:-1]:
                entry = self._beam(layer, mine, entry, 4)[0][:, :1]
            if own:
                entry = np.concatenate([entry, np.arange(a, a + len(mine))[:, None]], axis=1)
            ids, sims = self._beam(near, mine, entry, beam)
            seen = np.zeros(len(mine) * n, bool)
            i, r = np.nonzero(sims >= at_least)
            new_q, new_v = i, ids[i, r]
            i, r = np.nonzero(ids >= 0)
            seen[i * n + ids[i, r]] = True
            while len(new_q):
                found_q.append(new_q + a)
                found_v.append(new_v)
                nb = near[new_v]
                i, r = np.nonzero(nb >= 0)
                flat = np.unique(new_q[i] * n + nb[i, r])
                flat = flat[~seen[flat]]
                seen[flat] = True
                new_q, new_v = flat // n, flat % n
                ok = np.concatenate([np.einsum("nd,nd->n", mine[new_q[c : c + 65536]], self.v[new_v[c : c + 65536]]) for c in range(0, len(flat), 65536)] or [np.empty(0)]) >= at_least
                new_q, new_v = new_q[ok], new_v[ok]
        return np.concatenate(found_q), np.concatenate(found_v)


def search(graph: Graph, raw: np.ndarray, queries: np.ndarray, threshold: float = THRESHOLD, beam: int = BEAM, own: bool = False) -> tuple[np.ndarray, np.ndarray, tuple[int, int, int]]:
    """Verified (query, node) links, and the audit: links of the audited queries, those found, the last beam.

    The beam starts at a quarter of a small shard, and is widened until the audit finds nearly all.
    """
    beam = min(beam, max(4, len(raw) // 4))
    unit = lambda x: x / np.linalg.norm(x, axis=1, keepdims=True)
    q, v = unit(queries), unit(raw)
    probe = np.arange(0, len(q), max(1, min(AUDIT_EVERY, len(q) // AUDIT_LEAST)))
    truth = int(sum((q[probe[a : a + 64]] @ v.T >= threshold).sum() for a in range(0, len(probe), 64)))
    if own:  # a vector's match with itself is no link
        truth -= int((np.einsum("nd,nd->n", q[probe], v[probe]) >= threshold).sum())
    while True:
        i, j = graph.within(q, threshold - 1e-5, beam, own)
        # verified in double precision, as dot product over both norms
        ok = np.concatenate([np.einsum("nd,nd->n", queries[i[a : a + 65536]], raw[j[a : a + 65536]]) / (np.linalg.norm(queries[i[a : a + 65536]], axis=1) * np.linalg.norm(raw[j[a : a + 65536]], axis=1)) for a in range(0, len(i), 65536)] or [np.empty(0)]) >= threshold
        each = np.unique(i[ok] * max(1, len(v)) + j[ok])
        i, j = each // max(1, len(v)), each % max(1, len(v))
        found = int((np.isin(i, probe) & ~(own & (i == j))).sum())
        if beam >= len(v) or found >= AUDIT_RECALL * truth:
            return i, j, (truth, found, beam)
        beam *= 2


_SHARD = "label string, shard int, keys array<string>, counts array<long>, vectors binary, graph binary"


def _build(table: pa.Table) -> pa.Table:
    """One shard's rows to one row with its graph."""
    vectors = np.array([scaled(v) for v in table["vector"].to_pylist()], np.float64)
    unit = vectors / np.linalg.norm(vectors, axis=1, keepdims=True)
    graph = Graph(unit)
    made = {"entry": graph.entry, "layers": graph.layers}
    return pa.table({
        "label": pa.array([table["label"][0].as_py()], pa.string()), "shard": pa.array([table["shard"][0].as_py()], pa.int32()),
        "keys": pa.array([table["key"].to_pylist()], pa.list_(pa.string())), "counts": pa.array([table["n"].to_pylist()], pa.list_(pa.int64())),
        "vectors": pa.array([vectors.tobytes()], pa.binary()), "graph": pa.array([pickle.dumps(made)], pa.binary()),
    })


def _load(row: dict) -> tuple[list, np.ndarray, np.ndarray, Graph]:
    keys = row["keys"]
    raw = np.frombuffer(row["vectors"], np.float64).reshape(len(keys), -1)
    graph = Graph.__new__(Graph)
    graph.v = (raw / np.linalg.norm(raw, axis=1, keepdims=True)).astype(np.float32)
    graph.__dict__.update(pickle.loads(row["graph"]))
    return keys, np.array(row["counts"], np.int64), raw, graph


def _meet(table: pa.Table) -> pa.Table:
    """One shard, or two: link counts and a spanning forest of their nodes, and a row without a key with the audit."""
    rows = sorted(table.to_pylist(), key=lambda r: r["shard"])
    keys, counts, raw, graph = _load(rows[0])
    audit = np.zeros(3, np.int64)
    if len(rows) == 1 and rows[0]["lo"] == rows[0]["hi"]:
        i, j, audit = search(graph, raw, raw, own=True)
        n = len(keys)
    elif len(rows) == 1:
        i = j = np.empty(0, np.int64)
        n = len(keys)
    else:
        keys2, counts2, raw2, graph2 = _load(rows[1])
        n1 = len(keys)
        if raw.shape[1] == raw2.shape[1]:
            a, b, one = search(graph, raw, raw2)
            c, d, two = search(graph2, raw2, raw)
            audit = (one[0] + two[0], one[1] + two[1], max(one[2], two[2]))
            i, j = np.concatenate([a + n1, c]), np.concatenate([b, d + n1])
        else:
            i = j = np.empty(0, np.int64)
        keys, counts, n = keys + keys2, np.concatenate([counts, counts2]), n1 + len(keys2)
    low, high = np.minimum(i, j), np.maximum(i, j)
    pairs = np.unique(low[low != high] * n + high[low != high])
    i, j = pairs // max(n, 1), pairs % max(n, 1)
    links = np.bincount(i, counts[j], n) + np.bincount(j, counts[i], n)
    root = forest(n, i, j)
    some = np.nonzero(links > 0)[0]
    told = [pa.array([None] * len(some) + [int(x)], pa.int64()) for x in audit]
    return pa.table({
        "key": pa.array([*[keys[x] for x in some], None], pa.string()), "links": pa.array([*links[some].astype(np.int64).tolist(), None], pa.int64()),
        "root": pa.array([*[keys[x] for x in root[some]], None], pa.string()), "probed": told[0], "caught": told[1], "beam": told[2],
    })


def scaled(vector: list) -> list:
    """A vector times a power of two that brings its largest component near 1: same cosines, no overflow."""
    v = np.asarray(vector, np.float64)
    return np.ldexp(v, -int(np.frexp(np.abs(v).max())[1]))


def _linked(df: DataFrame, store: Scratch, vec: str, vec_id: str, label: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Rows with the key of their class, classes of equal vectors of a label, and what the shards' graphs found."""
    e = F.transform(F.col(vec), lambda x: x.cast("double") + F.lit(0.0))
    good = (
        F.col(vec).isNotNull() & F.col(label).isNotNull() & F.col(vec_id).isNotNull()
        & F.forall(F.col(vec), lambda x: x.isNotNull() & ~F.isnan(x.cast("double")) & (F.abs(x.cast("double")) < float("inf")))
        & F.exists(F.col(vec), lambda x: x != 0)
    )
    kind = df.schema[label].dataType
    mark = F.col(label) + F.lit(0).cast(kind) if isinstance(kind, (T.FloatType, T.DoubleType)) else F.col(label)  # -0.0 equals 0.0
    rows = df.select(F.col(vec_id).alias("vec_id"), mark.cast("string").alias("label"), e.alias("vector"), F.coalesce(good, F.lit(False)).alias("good"))
    rows = rows.withColumn("key", F.when(F.col("good"), F.concat(*[F.lpad(F.hex(F.xxhash64("label", "vector", F.lit(s))), 16, "0") for s in (0, 1)])))
    classes = store.keep(
        rows.where("good").withColumn("size", F.size("vector")).groupBy("label", "size", "key").agg(F.first("vector").alias("vector"), F.count("*").alias("n"), F.min("vec_id").alias("least"))
    )
    shards = classes.groupBy("label", "size").agg(F.ceil(F.count("*") / SHARD_ROWS).cast("int").alias("shards"))
    dealt = classes.join(shards, ["label", "size"]).withColumn("shard", F.pmod(F.xxhash64("key"), F.col("shards")).cast("int"))
    built = store.keep(dealt.select("label", "size", "shard", "shards", "key", "n", "vector").groupBy("label", "size", "shard", "shards").applyInArrow(_sized, "size int, shards int, " + _SHARD))
    meet = (
        built.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("shards") - 1)))
        .withColumn("lo", F.least("shard", "other"))
        .withColumn("hi", F.greatest("shard", "other"))
        .groupBy("label", "size", "lo", "hi")
        .applyInArrow(_meet, "key string, links long, root string, probed long, caught long, beam long")
    )
    return rows, classes, store.keep(meet)


def recall(df: DataFrame, vec: str = "embedding", vec_id: str = "vec_id", label: str = "label") -> DataFrame:
    """What the audits saw: ``(shard_pairs, probed, caught, recall, widest_beam)``; recall is 1 where there was no link."""
    found = _linked(df, Scratch(df.sparkSession, "recall"), vec, vec_id, label)[2].where("probed is not null")
    total = found.agg(F.count("*").alias("shard_pairs"), F.coalesce(F.sum("probed"), F.lit(0)).alias("probed"), F.coalesce(F.sum("caught"), F.lit(0)).alias("caught"), F.coalesce(F.max("beam"), F.lit(0)).alias("widest_beam"))
    return total.select("shard_pairs", "probed", "caught", F.coalesce(F.try_divide("caught", "probed"), F.lit(1.0)).alias("recall"), "widest_beam")


def near_duplicates(df: DataFrame, vec: str = "embedding", vec_id: str = "vec_id", label: str = "label") -> DataFrame:
    """``(vec_id, n_links, component_id, kept)``, a row per row of ``df``; labels may be of any type that casts to a string.

    Vectors of a label with other lengths than most link only with their own length's, as each
    length is sharded apart.
    """
    store = Scratch(df.sparkSession, "embeddings")
    rows, classes, found = _linked(df, store, vec, vec_id, label)
    found = found.where("key is not null")
    roots = contract_components(df.sparkSession, found.select("key", "root")).select(F.col("v").alias("key"), "root")
    joined = store.keep(
        classes.select("key", "n", "least").join(roots, "key", "left").join(found.groupBy("key").agg(F.sum("links").alias("links")), "key", "left")
        .select("key", "least", (F.col("n") - 1 + F.coalesce("links", F.lit(0))).alias("n_links"), F.coalesce("root", "key").alias("root"))
    )
    least = store.keep(joined.groupBy("root").agg(F.min("least").alias("component_id")))
    verdict = store.keep(joined.join(least, "root").select("key", "n_links", "component_id"))
    # rows without a key spread over keys of their own that no class has
    out = rows.select("vec_id", F.coalesce("key", F.concat(F.lit("-"), F.coalesce(F.col("vec_id").cast("string"), F.lit("")))).alias("key")).join(verdict, "key", "left")
    component = F.coalesce("component_id", "vec_id")
    return out.select("vec_id", F.coalesce("n_links", F.lit(0)).alias("n_links"), component.alias("component_id"), F.coalesce(F.col("vec_id") == component, F.lit(True)).alias("kept"))


def _sized(table: pa.Table) -> pa.Table:
    made = _build(table)
    return pa.table({"size": pa.array([table["size"][0].as_py()], pa.int32()), "shards": pa.array([table["shards"][0].as_py()], pa.int32())} | {c: made[c] for c in made.column_names})
