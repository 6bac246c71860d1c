"""Connected components by repeated random contraction.

Every round maps each vertex to the member of its closed neighbourhood with the
smallest per-round hash, renames the edges and drops loops and repeats.  A
constant share of the vertices disappears per round on any graph, paths
included, so the rounds grow with the logarithm of the largest component and
every round works on a smaller graph.  Nothing is collected: per round the driver
only learns whether edges are left.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stringweave.session import Scratch


def _renamed(edges: DataFrame, mapping: DataFrame) -> DataFrame:
    """Edges with both ends replaced; hot ends are left to the adaptive skew join."""
    left = edges.join(mapping.select(F.col("v").alias("a"), F.col("m").alias("x")), "a")
    both = left.join(mapping.select(F.col("v").alias("b"), F.col("m").alias("y")), "b")
    return (
        both.where("x <> y")
        .select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"))
        .distinct()
    )


def contract_components(spark: SparkSession, edges: DataFrame, max_rounds: int = 64, trace: list | None = None) -> DataFrame:
    """Label the vertices of an undirected edge list.

    ``edges`` has two columns of one comparable type, the ends.  Returns ``(v, root)``
    for every vertex with an edge to another vertex; ``root`` is some vertex of the
    component.  Loops, repeats and either direction are allowed; rows with a null end
    are ignored; no edges give an empty table.  ``trace`` receives the edges left per round.
    """
    a, b = edges.columns[:2]
    store = Scratch(spark, "components")
    now = store.keep(
        edges.select(F.col(a).alias("a"), F.col(b).alias("b"))
        .where("a is not null and b is not null and a <> b")
        .select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
        .distinct()
    )
    labels: DataFrame | None = None
    for turn in range(max_rounds):
        left = now.count()
        if trace is not None:
            trace.append(left)
        if not left:
            break
        both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        ranked = lambda c: F.struct(F.xxhash64(c, F.lit(turn)).alias("h"), F.col(c).alias("w"))
        mapping = store.keep(
            both.groupBy(F.col("a").alias("v"))
            .agg(F.min(ranked("b")).alias("best"))
            .select("v", F.least("best", ranked("v"))["w"].alias("m"))
        )
        then = store.keep(_renamed(now, mapping))
        if labels is None:
            fresh = mapping.select("v", F.col("m").alias("root"))
            labels = fresh
            labels._scratch_path = mapping._scratch_path
        else:
            moved = store.keep(
                labels.join(mapping.select(F.col("v").alias("root"), "m"), "root", "left").select(
                    "v", F.coalesce("m", "root").alias("root")
                )
            )
            store.drop(labels)
            store.drop(mapping)
            labels = moved
        store.drop(now)
        now = then
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    if labels is None:
        return now.select(F.col("a").alias("v"), F.col("b").alias("root"))
    return labels.select("v", "root")
