"""Language identification by a byte-level convolutional network.

Bytes are embedded, filters of several widths slide over a window of fixed length,
each filter keeps its maximum, and a softmax layer names the language.  It is
trained in numpy on windows of labelled texts; the sample's size is a documented
bound.  A text is cut into windows from its first byte to its last, and the class
probabilities are averaged over them, so the whole text counts.

For scoring, a filter's answer to two neighbouring bytes is read from a table of all
65,536 pairs; wider filters add two such tables.  That is the same sum as the
convolution, without the arithmetic.

A text that is null or has no letter is ``und`` with score 0.  Training takes the labelled
documents first by a hash of their id, then by id, label and bytes, so reruns learn the same
from repeated ids too.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stringweave.llm._common import fields, held_out, per_text

WINDOW = 256
WIDTHS = (2, 3, 4)
FILTERS = 12
EMBED = 12
#: Labelled documents used for training at most, and the windows taken of each.
TRAIN_DOCS = 3000
WINDOWS_PER_DOC = 3
EPOCHS = 6


def training_windows(df: DataFrame, text: str = "text", lang: str = "lang", doc_id: str = "doc_id", n: int = TRAIN_DOCS) -> tuple[np.ndarray, list[str]]:
    """Windows (uint8) and labels of the ``n`` documents first by a hash of their id, no held-out one among them."""
    body = F.col(text).cast("binary")
    size = F.octet_length(F.col(text))
    cuts = [F.substring(body, (1 + F.greatest(F.lit(0), size - WINDOW) * i / max(1, WINDOWS_PER_DOC - 1)).cast("int"), WINDOW) for i in range(WINDOWS_PER_DOC)]
    able = df.where(~held_out(doc_id) & F.col(lang).isNotNull() & (size > 0)).withColumn("h", F.xxhash64(doc_id))
    # twice as many as needed by a bound on the hash, so that tasks send the driver no more as the corpus grows
    limit = able.select("h").count() / (2 * n)
    if limit > 1:
        able = able.where(F.col("h") < int(-(2.0**63) + 2.0**64 / limit))
    rows = able.select("h", F.col(doc_id).alias("id"), F.col(lang).alias("lang"), F.array(*cuts).alias("cuts")).orderBy("h", "id", "lang", "cuts").limit(n).collect()
    found, labels = [], []
    for r in rows:
        for c in dict.fromkeys(map(bytes, r.cuts)):
            found.append(np.frombuffer(c[:WINDOW].ljust(WINDOW, b"\0"), np.uint8))
            labels.append(r.lang)
    return (np.stack(found) if found else np.zeros((0, WINDOW), np.uint8)), labels


def train(windows: np.ndarray, labels: list[str], epochs: int = EPOCHS, seed: int = 5, batch: int = 64) -> dict:
    """Fit the network with Adam; returns its arrays and class names."""
    classes = sorted(set(labels)) or ["und"]
    y = np.array([classes.index(x) for x in labels], np.int64)
    rng = np.random.default_rng(seed)
    normal = lambda *s: (rng.standard_normal(s) / np.sqrt(np.prod(s[:-1]))).astype(np.float32)
    p = {"emb": rng.standard_normal((256, EMBED)).astype(np.float32)} | {f"k{w}": normal(w * EMBED, FILTERS) for w in WIDTHS}
    p |= {"out": normal(len(WIDTHS) * FILTERS, len(classes)), "bias": np.zeros(len(classes), np.float32)}
    m, v = ({k: np.zeros_like(a) for k, a in p.items()} for _ in range(2))
    step = 0
    for _ in range(epochs if len(y) else 0):
        order = rng.permutation(len(y))
        for at in range(0, len(order), batch):
            pick = order[at : at + batch]
            x, n = windows[pick], len(pick)
            e = p["emb"][x]
            pooled, memory = [], []
            for w in WIDTHS:
                cols = np.concatenate([e[:, j : WINDOW - w + 1 + j] for j in range(w)], axis=2)
                a = cols @ p[f"k{w}"]
                top = a.argmax(axis=1)
                pooled.append(np.take_along_axis(a, top[:, None], 1)[:, 0])
                memory.append((cols, top))
            h = np.concatenate(pooled, axis=1)
            act = np.tanh(h)
            z = act @ p["out"] + p["bias"]
            z = np.exp(z - z.max(axis=1, keepdims=True))
            dz = z / z.sum(axis=1, keepdims=True)
            dz[np.arange(n), y[pick]] -= 1
            dz /= n
            g = {"out": act.T @ dz, "bias": dz.sum(axis=0), "emb": np.zeros_like(p["emb"])}
            dh = (dz @ p["out"].T) * (1 - act * act)
            for i, w in enumerate(WIDTHS):
                cols, top = memory[i]
                d = dh[:, i * FILTERS : (i + 1) * FILTERS]
                seen = np.take_along_axis(cols, top[:, :, None], 1)  # document, filter, bytes x embedding
                g[f"k{w}"] = np.einsum("nfe,nf->ef", seen, d)
                back = (p[f"k{w}"].T[None] * d[:, :, None]).reshape(n, FILTERS, w, EMBED)
                where = x[np.arange(n)[:, None, None], top[:, :, None] + np.arange(w)]
                np.add.at(g["emb"], where.ravel(), back.reshape(-1, EMBED))
            step += 1
            rate = 0.01 * np.sqrt(1 - 0.999**step) / (1 - 0.9**step)
            for k in p:
                m[k] += 0.1 * (g[k] - m[k])
                v[k] += 0.001 * (g[k] * g[k] - v[k])
                p[k] -= rate * m[k] / (np.sqrt(v[k]) + 1e-8)
    return p | {"classes": classes}


class Scorer:
    """Applies a trained network to whole texts."""

    def __init__(self, model: dict):
        self.classes, self.out, self.bias = model["classes"], model["out"], model["bias"]
        e = model["emb"]
        lone = {w: [e @ model[f"k{w}"][j * EMBED : (j + 1) * EMBED] for j in range(w)] for w in WIDTHS}
        pair = lambda a, b: (a[None, :, :] + b[:, None, :]).reshape(65536, FILTERS)  # noqa: E731  low byte first
        self.tables = {w: [pair(t[j], t[j + 1]) if j + 1 < w else t[j] for j in range(0, w, 2)] for w, t in lone.items()}

    def windows(self, x: np.ndarray) -> np.ndarray:
        """Class probabilities of windows."""
        pooled = []
        flat = x.ravel()
        twos = flat[:-1].astype(np.int32) | flat[1:].astype(np.int32) << 8
        for w in WIDTHS:
            a = np.take(self.tables[w][0], twos[: len(flat) - w + 1], axis=0)
            for j, t in enumerate(self.tables[w][1:], 1):
                at = 2 * j
                a += np.take(t, twos[at : at + len(a)] if len(t) == 65536 else flat[at : at + len(a)], axis=0)
            full = np.empty((x.size, FILTERS), np.float32)
            full[: len(a)] = a
            pooled.append(full.reshape(*x.shape, FILTERS)[:, : WINDOW - w + 1].max(axis=1))
        z = np.tanh(np.concatenate(pooled, axis=1)) @ self.out + self.bias
        z = np.exp(z - z.max(axis=1, keepdims=True))
        return z / z.sum(axis=1, keepdims=True)

    def score(self, texts: list) -> tuple[list[str], np.ndarray]:
        """Language and mean probability of each text; probabilities are weighed by the windows' bytes."""
        count = np.array([-(-len(t or b"") // WINDOW) for t in texts], np.int64)
        raw = b"".join((t or b"").ljust(c * WINDOW, b"\0") for t, c in zip(texts, count.tolist()))
        x = np.frombuffer(raw, np.uint8).reshape(-1, WINDOW)
        probs = np.concatenate([self.windows(x[a : a + 512]) for a in range(0, len(x), 512)] or [np.zeros((0, len(self.classes)), np.float32)])
        owner = np.repeat(np.arange(len(texts)), count)
        weight = np.full(len(x), float(WINDOW))
        ends = np.cumsum(count)[count > 0] - 1
        sizes = np.array([len(t) for t in texts if t], np.int64)
        weight[ends] = sizes - (count[count > 0] - 1) * WINDOW
        total = np.stack([np.bincount(owner, probs[:, k] * weight, len(texts)).astype(float) for k in range(len(self.classes))], axis=1)
        total /= np.maximum(1, np.bincount(owner, weight, len(texts)))[:, None]
        best, score = total.argmax(axis=1), np.clip(total.max(axis=1), 0, 1)
        langs = []
        for i, t in enumerate(texts):
            if t and any(map(str.isalpha, t.decode("utf-8", "replace"))):
                langs.append(self.classes[best[i]])
            else:
                langs.append("und")
                score[i] = 0.0
        return langs, score


def identify(df: DataFrame, learn_from: DataFrame | None = None, text: str = "text", lang: str = "lang", doc_id: str = "doc_id", keep: list[str] | None = None) -> DataFrame:
    """Append ``lang_pred`` and ``score``; the network learns from ``learn_from``, by default ``df`` itself.

    Without a labelled document every text with a letter is ``und`` too.
    """
    model = train(*training_windows(df if learn_from is None else learn_from, text, lang, doc_id))
    shared = df.sparkSession.sparkContext.broadcast(model)

    def make():
        scorer = Scorer(shared.value)

        def work(texts):
            langs, score = scorer.score(texts)
            return {"lang_pred": langs, "score": score}

        return work

    return per_text(df, make, fields("lang_pred string, score double"), text, keep)
