"""Quality rules with verdicts by host.

A document's rule counts are taken from its whole text.  It fails hard (``base_failed``)
or soft (``soft_failed``: many symbols for its words, or words of unlikely length).
Failures of either kind are summed by host (one partial aggregate per task, so a host
with a third of all rows is one row per task), each host's rate is shrunk towards the
corpus by a beta prior whose two parameters are fitted to the hosts' rates by moments,
and the verdict of a host, a table of one row per host, is joined back to its documents:
a trusted host's soft failures stay, a strict host's go, and of a blocked host all go.

A null text has no words and fails; a null host is a host of its own; repeated rows count
as documents of their own.
"""

from __future__ import annotations


import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stringweave.llm._common import fields, per_text
from stringweave.session import Scratch

WINDOW = 8
MIN_WORDS = 20
REPEAT_PERCENT = 30
#: Soft rules: symbols for every hundred words, and letters of a word on average, least and most.
SYMBOL_PERCENT = 10
WORD_LETTERS = (2, 12)
#: A host goes when its shrunken failure rate is above this.
MAX_HOST_RATE = 0.5
#: A host is trusted up to this shrunken failure rate; above it, soft failures go.
TRUSTED_HOST_RATE = 0.05
SYMBOLS = "#*$%&|<>"
_SPACE = " \t\n\r\x0b\x0c"


def repeated_words(ids: np.ndarray, doc: np.ndarray, k: int = WINDOW) -> np.ndarray:
    """Marks each word inside a ``k``-word window that its document holds twice or more.

    Windows get exact ranks by doubling (pairs of ranks are ranked again), so no hash
    can collide; ``k`` is a power of two.  ``ids`` are word numbers, ``doc`` ascends.
    """
    n = len(ids)
    out = np.zeros(n, bool)
    if n < k:
        return out
    rank, span = ids.astype(np.int64), 1
    while span < k:
        pair = rank[: len(rank) - span] * (int(rank.max()) + 1) + rank[span:]
        rank = np.unique(pair, return_inverse=True)[1]
        span *= 2
    inside = np.nonzero(doc[: n - k + 1] == doc[k - 1 :])[0]
    key = rank[inside].astype(np.int64) * (int(doc[-1]) + 1) + doc[inside]
    _, back, count = np.unique(key, return_inverse=True, return_counts=True)
    hit = inside[count[back] > 1]
    edge = np.zeros(n + 1, np.int64)
    np.add.at(edge, hit, 1)
    np.add.at(edge, hit + k, -1)
    return np.cumsum(edge[:-1]) > 0


def rule_counts(df: DataFrame, text: str = "text", keep: list[str] | None = None) -> DataFrame:
    """Append n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed and soft_failed."""
    names = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")

    def make():
        def work(texts):
            words = [(t or b"").split() for t in texts]
            count = np.fromiter(map(len, words), np.int64, len(words))
            doc = np.repeat(np.arange(len(words)), count)
            flat = [w for ws in words for w in ws]
            ids = pd.factorize(np.array(flat, dtype=object))[0] if flat else np.empty(0, np.int64)
            repeat = np.bincount(doc[repeated_words(ids, doc)], minlength=len(words)) if flat else np.zeros(len(words), np.int64)
            chars, marks, lines = [], [], []
            for t in texts:
                s = (t or b"").decode("utf-8", "replace")
                chars.append(len(s) - sum(map(s.count, _SPACE)))
                marks.append(sum(map(s.count, SYMBOLS)))
                rows = [x for x in s.split("\n") if x.strip(_SPACE)]
                lines.append(len(rows) - len(set(rows)))
            failed = (count < MIN_WORDS) | (100 * repeat > REPEAT_PERCENT * count)
            size, low, high = np.array(chars, np.int64), *(n * count for n in WORD_LETTERS)
            soft = (100 * np.array(marks, np.int64) > SYMBOL_PERCENT * count) | (size < low) | (size > high)
            return dict(zip(names, (count, chars, marks, lines, repeat.astype(np.int64)))) | {"base_failed": failed, "soft_failed": soft}

        return work

    return per_text(df, make, fields(", ".join(f"{n} long" for n in names) + ", base_failed boolean, soft_failed boolean"), text, keep)


def host_rates(rows: DataFrame, host: str = "source") -> DataFrame:
    """Per host: documents, failures of any kind and the shrunken failure rate.

    The prior's mean is the corpus's rate m.  Its strength s comes from the spread of the
    hosts' rates beyond what chance gives: with variance v between hosts, s = m(1-m)/v - 1,
    at least 1; no spread beyond chance means a strength of a million, so that every host is
    judged by the corpus.
    """
    hosts = rows.groupBy(F.col(host).alias("host")).agg(F.count("*").alias("n"), F.sum((F.col("base_failed") | F.col("soft_failed")).cast("long")).alias("failed"))
    total = hosts.agg(
        F.sum("n").alias("docs"), F.sum("failed").alias("bad"), F.count("*").alias("hosts"), F.sum(F.col("failed") * F.col("failed") / F.col("n")).alias("squares")
    ).first()
    mean = (total.bad or 0) / max(1, total.docs or 0)
    # variance of the rates, documents as weights, less what chance alone gives
    spread = (total.squares or 0) / max(1, total.docs or 0) - mean * mean - mean * (1 - mean) * total.hosts / max(1, total.docs or 0)
    strength = max(1.0, min(1e6, mean * (1 - mean) / spread - 1)) if spread > 0 else 1e6
    return hosts.select("host", "n", "failed", ((F.col("failed") + mean * strength) / (F.col("n") + strength)).alias("rate"))


def judge(
    df: DataFrame, text: str = "text", host: str = "source", keep: list[str] | None = None, max_rate: float = MAX_HOST_RATE, trusted_rate: float = TRUSTED_HOST_RATE
) -> DataFrame:
    """Append the rule counts, ``base_failed``, ``soft_failed`` and ``kept``.

    ``kept`` is false for a hard failure, for every document of a host whose shrunken failure rate
    is above ``max_rate``, and for a soft failure of a host above ``trusted_rate``.
    """
    store = Scratch(df.sparkSession, "quality")
    cols = keep if keep is not None else df.columns
    rows = store.keep(rule_counts(df.withColumn("__host", F.col(host)), text, [*cols, "__host"]))
    rates = host_rates(rows, "__host")
    watched = rates.where(F.col("rate") > min(trusted_rate, max_rate)).select(F.col("host").alias("__watched"), (F.col("rate") > max_rate).alias("__all"), (F.col("rate") > trusted_rate).alias("__soft"))
    out = rows.join(watched, rows["__host"].eqNullSafe(watched["__watched"]), "left")
    goes = F.col("base_failed") | F.coalesce("__all", F.lit(False)) | F.coalesce("__soft", F.lit(False)) & F.col("soft_failed")
    return out.withColumn("kept", ~goes).drop("__host", "__watched", "__all", "__soft")
