"""Near copies among whole texts, by the product of the document x shingle matrix with its transpose.

Texts that are equal are one row of the matrix.  Two rows of similarity t share a shingle
among the rarest ``n - ceil(t n) + 1`` of each, so only those columns enter the product; rows
whose sizes differ too much are no pair.  Columns above PIECE rows are multiplied in pieces.
The pairs found are verified on their whole sets, so nothing is missed and nothing is estimated
but for equal 64-bit hashes of different shingles.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stringweave.operators.contraction import contract_components
from stringweave.session import Scratch

#: Rows of a column that meet in one piece.
PIECE = 512
SPACE = r"[ \t\n\x0B\f\r]+"


def shingled(docs: DataFrame, text: str, doc_id: str, k: int) -> DataFrame:
    """``(id, cls, h)``: a digest of the text and the hashes of its distinct shingles of ``k`` words; shorter texts are one shingle."""
    whole = F.coalesce(F.col(text), F.lit(""))
    words = F.filter(F.split(whole, SPACE), lambda w: w != "")
    d = docs.select(F.col(doc_id).alias("id"), F.sha2(whole, 256).alias("cls"), words.alias("words"))
    n = F.size("words")
    runs = F.transform(F.sequence(F.lit(1), n - (k - 1)), lambda i: F.array_join(F.slice("words", i, k), " "))
    made = F.when(n == 0, F.array().cast("array<string>")).when(n < k, F.array(F.array_join("words", " "))).otherwise(runs)
    return d.select("id", "cls", F.array_distinct(F.transform(made, lambda x: F.xxhash64(x))).alias("h"))


def rare_columns(classes: DataFrame, num: int, den: int) -> DataFrame:
    """``(s, cls, n)``: of every class the shingles that a pair must share one of, ``n`` being the size of its set."""
    each = classes.select("cls", F.size("h").alias("n"), F.explode("h").alias("s"))
    often = each.groupBy("s").agg(F.count("*").alias("often"))
    line = each.join(often, "s").groupBy("cls", "n").agg(F.array_sort(F.collect_list(F.struct("often", "s"))).alias("line"))
    held = F.expr(f"cast(n - ({num} * n + {den - 1}) div {den} + 1 as int)")
    return line.select("cls", "n", F.explode(F.slice("line", 1, held)).alias("x")).where("x.often > 1").select("x.s", "cls", "n")


def similar_classes(store: Scratch, classes: DataFrame, num: int, den: int) -> DataFrame:
    """``(a, b)``, ``a < b``: classes ``(cls, h)`` whose sets share ``num / den`` of their union or more."""
    rare = store.keep(rare_columns(classes, num, den))
    tall = rare.groupBy("s").agg(F.count("*").alias("rows")).where("rows > 1").select("s", F.ceil(F.col("rows") / PIECE).cast("int").alias("pieces"))
    cut = store.keep(rare.join(tall, "s").withColumn("own", F.pmod(F.xxhash64("cls"), F.col("pieces")).cast("int")))
    left = cut.select("s", F.col("cls").alias("x"), F.col("n").alias("nx"), F.col("own").alias("lo"), F.explode(F.sequence("own", F.col("pieces") - 1)).alias("hi"))
    right = cut.select("s", F.col("cls").alias("y"), F.col("n").alias("ny"), F.col("own").alias("hi"), F.explode(F.sequence(F.lit(0), F.col("own"))).alias("lo"))
    near = (F.greatest("nx", "ny") * num <= F.least("nx", "ny") * den) & ((F.col("lo") < F.col("hi")) | (F.col("x") < F.col("y")))
    pairs = store.keep(left.join(right, ["s", "lo", "hi"]).where(near).select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct())
    whole = pairs.join(classes.select(F.col("cls").alias("a"), F.col("h").alias("ha")), "a").join(classes.select(F.col("cls").alias("b"), F.col("h").alias("hb")), "b")
    shared = whole.select("a", "b", F.size(F.array_intersect("ha", "hb")).alias("both"), (F.size("ha") + F.size("hb")).alias("sizes"))
    return shared.where(f"both * {num + den} >= sizes * {num}").select("a", "b")


def near_copies(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", k: int = 5, at_least: tuple[int, int] = (4, 5)) -> DataFrame:
    """``(doc_id, class_id, n_links)``, a row per document.

    Two documents are linked if their shingles of ``k`` words have at least the fraction ``at_least``
    of their union in common.  ``class_id`` is the smallest id reachable over links, ``n_links`` the
    number of other documents linked directly, copies included.  Null texts and those without a word
    are linked with nothing and are classes of their own.  Repeated rows count as documents each.
    """
    num, den = at_least
    store = Scratch(docs.sparkSession, "near-copies")
    rows = store.keep(shingled(docs, text, doc_id, k))
    classes = store.keep(rows.where("size(h) > 0").groupBy("cls").agg(F.min("id").alias("rep"), F.count("*").alias("held"), F.first("h").alias("h")))
    links = store.keep(similar_classes(store, classes, num, den))
    ends = links.unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
    more = ends.join(classes.select(F.col("cls").alias("b"), "held"), "b").groupBy(F.col("a").alias("cls")).agg(F.sum("held").alias("more"))
    roots = contract_components(docs.sparkSession, links).withColumnRenamed("v", "cls")
    tagged = store.keep(classes.drop("h").join(roots, "cls", "left").withColumn("root", F.coalesce("root", "cls")))
    least = tagged.groupBy("root").agg(F.min("rep").alias("class_id"))
    named = tagged.join(least, "root").join(more, "cls", "left").select("cls", "class_id", (F.col("held") - 1 + F.coalesce("more", F.lit(0))).alias("n_links"))
    out = rows.select("id", "cls").join(named, "cls", "left")
    alone = F.col("n_links").isNull()
    return out.select(F.col("id").alias("doc_id"), F.when(alone, F.col("id")).otherwise(F.col("class_id")).alias("class_id"), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"))
