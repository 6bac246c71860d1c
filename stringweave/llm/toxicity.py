"""Toxicity by a subsequence string-kernel SVM with Nystroem landmarks.

The kernel compares two words by the subsequences of three and four letters they
share.  A subsequence may skip letters inside a span of five, at a discount per
skipped letter, so inserted or dropped letters cost little; marks between letters are
left out, and runs of single letters set apart by blanks are read as one more word.  Landmarks are words that stand out in
labelled toxic documents, and words of clean ones.  An L2 support vector machine is
fitted in the Nystroem space of the landmarks by finite Newton steps, with the
multiple-instance rule that a toxic document has some toxic word and a clean one has
none: each round picks the words that speak for their documents anew.  A document's
score comes from its two strongest different words by a logistic fit.

As the machine is linear in subsequences, landmarks and weights fold into one table of
subsequence weights, and scoring reads that table for all different words of a block
at once.

A null or empty text has no words and gets the score of a text without a sign of
toxicity.  Labels, language, source and id are no inputs of a score.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stringweave.llm._common import fields, held_out, per_text

SPAN = 5
DISCOUNT = 0.6
BUCKETS = 1 << 20
LANDMARKS = 256
THRESHOLD = 0.7
#: Labelled documents used for training at most, of either class.
TRAIN_TOXIC = 800
TRAIN_CLEAN = 1600
#: Longest text used for training, in bytes; with the numbers above it bounds what the driver holds.
TRAIN_BYTES = 1 << 16
ROUNDS = 4
_SHAPES = [(0, *c) for size in (2, 3) for c in combinations(range(1, SPAN), size)]


def pieces(text: bytes | None) -> list[str]:
    """Lower-cased words of a text; four or more lone letters in a row also make one word."""
    words = (text or b"").decode("utf-8", "replace").lower().split()
    lone, extra = [], []
    for w in words:
        if len(w) == 1:
            lone.append(w)
        elif lone:
            if len(lone) > 3:
                extra.append("".join(lone))
            lone = []
    if len(lone) > 3:
        extra.append("".join(lone))
    return words + extra


def subsequences(words: list[str]) -> tuple[np.ndarray, np.ndarray, list[tuple[np.ndarray, np.ndarray, float]]]:
    """For words: the word of each position, each word's scale, and per shape (positions, buckets, weight)."""
    words = ["\x02" + (w if w.isalnum() else "".join(filter(str.isalnum, w)) or w) + "\x03" for w in words]
    size = np.fromiter(map(len, words), np.int64, len(words))
    codes = np.frombuffer("".join(words).encode("utf-32-le", "replace"), np.uint32).astype(np.uint64)
    ends = np.cumsum(size)
    owner = np.repeat(np.arange(len(words)), size)
    room = ends[owner] - np.arange(len(codes))
    out, scale = [], np.zeros(len(words))
    for shape in _SHAPES:
        at = np.nonzero(room > shape[-1])[0]
        h = codes[at]
        for step in shape[1:]:
            h = h * np.uint64(0x9E3779B97F4A7C15) + codes[at + step]
        h = (h * np.uint64(0xD6E8FEB86659FD93)) >> np.uint64(44)
        weight = DISCOUNT ** (shape[-1] + 1 - len(shape)) * (1.0 if len(shape) == 3 else 1.5)
        out.append((at, h.astype(np.int64), weight))
        scale += weight * weight * np.maximum(0, size - shape[-1])
    return owner, np.sqrt(np.maximum(scale, 1e-12)), out


def word_scores(words: list[str], table: np.ndarray, bias: float) -> np.ndarray:
    """The machine's value for each word, from the table of subsequence weights."""
    if not words:
        return np.empty(0)
    owner, scale, shapes = subsequences(words)
    total = np.zeros(len(owner))
    for at, h, weight in shapes:
        total[at] += weight * table[h]
    return np.bincount(owner, total, len(words)) / scale + bias


class _Features:
    """Sparse kernel features of some words, for training."""

    def __init__(self, words: list[str]):
        owner, scale, shapes = subsequences(words)
        self.n = len(words)
        self.row = np.concatenate([owner[at] for at, _, _ in shapes]).astype(np.int32)
        self.col = np.concatenate([h for _, h, _ in shapes]).astype(np.int32)
        self.val = (np.concatenate([np.full(len(at), w) for at, _, w in shapes]) / scale[self.row]).astype(np.float32)

    def gram(self, marks: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Kernel of all words with the words at ``marks``; the marks' features as (buckets, dense rows)."""
        place = np.full(self.n, -1, np.int32)
        place[marks] = np.arange(len(marks))
        own = place[self.row] >= 0
        cols = np.unique(self.col[own])
        dense = np.zeros((len(marks), len(cols)), np.float32)
        np.add.at(dense, (place[self.row[own]], np.searchsorted(cols, self.col[own])), self.val[own])
        at = np.minimum(np.searchsorted(cols, self.col), len(cols) - 1)
        hit = cols[at] == self.col
        row, at, val = self.row[hit], at[hit], self.val[hit]
        return np.stack([np.bincount(row, val * d[at], self.n) for d in dense], axis=1), cols, dense


def _newton_svm(x: np.ndarray, y: np.ndarray, c: np.ndarray, steps: int = 20) -> np.ndarray:
    """L2 SVM in the primal: ridge solutions over the points inside the margin until these stay the same."""
    w, active = np.zeros(x.shape[1]), np.ones(len(y), bool)
    for _ in range(steps):
        xa, ca = x[active], c[active]
        w = np.linalg.solve(xa.T @ (xa * ca[:, None]) + np.eye(x.shape[1]), xa.T @ (ca * y[active]))
        now = y * (x @ w) < 1
        if np.array_equal(now, active):
            break
        active = now
    return w


def train(toxic: list, clean: list, seed: int = 3) -> dict:
    """Fit on whole texts of both classes; returns the folded table and the calibration."""
    none = {"table": np.zeros(BUCKETS, np.float32), "bias": -1.0, "logit": [0.0, 0.0, -4.0], "landmarks": []}
    docs = [list(dict.fromkeys(pieces(t))) for t in (*toxic, *clean)]
    y = np.array([1] * len(toxic) + [0] * len(clean))
    if not toxic or not clean:
        return none
    ids, words = pd.factorize(np.array([w for d in docs for w in d], dtype=object))
    owner = np.repeat(np.arange(len(docs)), [len(d) for d in docs])
    if not len(words):
        return none
    words = list(words)
    starts = np.cumsum([0, *[len(d) for d in docs]])
    n1, n0 = len(toxic), len(clean)
    value = _stand_out(words, ids, starts, n1)
    in_clean = np.unique(ids[starts[n1] :])
    share0 = np.bincount(ids[starts[n1] :], minlength=len(words)) / n0
    rng = np.random.default_rng(seed)
    table, bias, marks = none["table"], -1.0, np.empty(0, np.int64)
    for turn in range(ROUNDS):
        witness = []
        for d in range(n1):
            mine = ids[starts[d] : starts[d + 1]]
            best = mine[np.argsort(-value[mine], kind="stable")[:2]]
            witness += [w for k, w in enumerate(best) if k == 0 or turn == 0 or value[w] > 0]
        pos, times = np.unique(np.array(witness, np.int64), return_counts=True)
        more = times / n1 > share0[pos]  # a word that speaks for toxicity is more frequent there
        pos, times = pos[more], times[more]
        if not len(pos):
            return none
        hard = in_clean[np.argsort(-value[in_clean], kind="stable")[:3000]] if turn else in_clean[:0]
        neg = np.setdiff1d(np.concatenate([rng.choice(in_clean, min(len(in_clean), 9000), replace=False), hard]), pos)
        if turn < 2:  # landmarks: the words that speak for most documents, and clean words
            marks = np.concatenate([pos[np.argsort(-times, kind="stable")[: LANDMARKS * 3 // 4]], rng.choice(neg, min(len(neg), LANDMARKS // 4), replace=False)])
        use = np.concatenate([pos, neg, np.setdiff1d(marks, np.concatenate([pos, neg]))])
        at = {w: i for i, w in enumerate(use.tolist())}
        k, cols, dense = _Features([words[w] for w in use]).gram(np.array([at[w] for w in marks.tolist()]))
        lam, vec = np.linalg.eigh(k[[at[w] for w in marks.tolist()]] + 1e-6 * np.eye(len(marks)))
        root = vec / np.sqrt(np.maximum(lam, 1e-6))  # the Nystroem map is k @ root
        n = len(pos) + len(neg)
        x = np.concatenate([k[:n] @ root, np.ones((n, 1))], axis=1)
        label = np.concatenate([np.ones(len(pos)), -np.ones(len(neg))])
        weight = np.concatenate([4.0 * times / times.mean() * min(10.0, len(neg) / len(pos)) ** 0.5, np.full(len(neg), 4.0)])
        w = _newton_svm(x, label, weight)
        table, bias = np.zeros(BUCKETS), float(w[-1])
        table[cols] = (root @ w[:-1]) @ dense
        value = np.concatenate([word_scores(words[a : a + 20_000], table, bias) for a in range(0, len(words), 20_000)])
    top = np.full((len(docs), 2), -3.0)
    for d in range(len(docs)):
        mine = np.sort(value[ids[starts[d] : starts[d + 1]]])[::-1][:2]
        top[d, : len(mine)] = np.maximum(mine, -3.0)
    x = np.concatenate([top, np.ones((len(docs), 1))], axis=1)
    logit = np.array([1.0, 0.0, 0.0])
    sample = np.where(y == 1, 0.2 / n1, 0.8 / n0) * len(y)
    for _ in range(30):  # logistic fit by Newton; a fifth of the weight is toxic
        p = 1 / (1 + np.exp(-np.clip(x @ logit, -30, 30)))
        h = (x * (sample * p * (1 - p))[:, None]).T @ x + 1e-2 * np.eye(3)
        logit = logit - np.linalg.solve(h, x.T @ (sample * (p - y)) + 1e-2 * logit)
    return {"table": table.astype(np.float32), "bias": bias, "logit": logit.tolist(), "landmarks": [words[i] for i in marks]}


def _stand_out(words: list[str], ids: np.ndarray, starts: np.ndarray, n_toxic: int) -> np.ndarray:
    """Per word the largest z value of its contiguous four-letter subsequences: how much more often toxic documents hold them."""
    grams, owners = [], []
    for a in range(0, len(words), 20_000):
        owner, _, shapes = subsequences(words[a : a + 20_000])
        at, h, _ = shapes[_SHAPES.index((0, 1, 2, 3))]
        owners.append(owner[at] + a)
        grams.append(h)
    owner, grams = np.concatenate(owners), np.concatenate(grams)
    cuts = np.searchsorted(owner, np.arange(len(words) + 1))
    seen = np.zeros((2, BUCKETS), np.int32)
    for d in range(len(starts) - 1):
        mine = ids[starts[d] : starts[d + 1]]
        if len(mine):
            seen[int(d < n_toxic), np.unique(np.concatenate([grams[cuts[w] : cuts[w + 1]] for w in mine]))] += 1
    n1, n0 = n_toxic, len(starts) - 1 - n_toxic
    p1, p0 = (seen[1] + 0.1) / (n1 + 1), (seen[0] + 0.5) / (n0 + 1)
    z = (p1 - p0) / np.sqrt(p0 * (1 - np.minimum(p0, 0.999)) / n1 + p0 / n0 + 1e-9)
    out = np.full(len(words), z.min())
    np.maximum.at(out, owner, z[grams])
    return out


def score_texts(texts: list, model: dict) -> np.ndarray:
    """Scores of whole texts."""
    found = [pieces(t) for t in texts]
    count = np.fromiter(map(len, found), np.int64, len(found))
    flat = [w for ws in found for w in ws]
    top = np.full((len(texts), 2), -3.0)
    if flat:
        ids, words = pd.factorize(np.array(flat, dtype=object))
        value = np.maximum(word_scores(list(words), model["table"], model["bias"]), -3.0)
        owner = np.repeat(np.arange(len(texts)), count)
        each = value[ids]
        np.maximum.at(top[:, 0], owner, each)
        first = np.full(len(texts), -1, np.int64)
        best = each == top[owner, 0]
        first[owner[best][::-1]] = ids[best][::-1]
        rest = ids != first[owner]
        np.maximum.at(top[:, 1], owner[rest], each[rest])
    a, b, c = model["logit"]
    return 1 / (1 + np.exp(-np.clip(a * top[:, 0] + b * top[:, 1] + c, -30, 30)))


def labelled(documents: DataFrame, labels: DataFrame, label: str = "toxic", n_toxic: int = TRAIN_TOXIC, n_clean: int = TRAIN_CLEAN) -> tuple[list, list]:
    """Whole texts of labelled documents that aren't held out, first by a hash of their id, up to the bounds.

    An id labelled both ways counts as toxic; of documents with one id the first text by code point is
    taken.  Texts above TRAIN_BYTES are scored like any other but teach nothing.
    """
    known = labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull() & ~held_out("doc_id")).groupBy("doc_id").agg(F.max(label).alias("y"))
    pick = lambda y, n: known.where(F.col("y") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(n)
    chosen = pick(1, n_toxic).unionByName(pick(0, n_clean))
    rows = (
        documents.select("doc_id", F.col("text").cast("binary").alias("text"))
        .join(F.broadcast(chosen), "doc_id")  # n_toxic + n_clean rows at most
        .where(F.octet_length("text") <= TRAIN_BYTES)
        .groupBy("doc_id", "y").agg(F.min("text").alias("text"))
        .collect()
    )
    rows.sort(key=lambda r: r.doc_id)
    return [r.text for r in rows if r.y == 1], [r.text for r in rows if r.y != 1]


def score(df: DataFrame, model: dict, text: str = "text", keep: list[str] | None = None, threshold: float = THRESHOLD) -> DataFrame:
    """Append ``score`` (0 to 1) and ``predicted`` (1 from ``threshold`` on)."""
    shared = df.sparkSession.sparkContext.broadcast(model)

    def make():
        m = shared.value

        def work(texts):
            s = score_texts(texts, m)
            return {"score": s, "predicted": (s >= threshold).astype(np.int32)}

        return work

    return per_text(df, make, fields("score double, predicted int"), text, keep)
