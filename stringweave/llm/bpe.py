"""Byte-level BPE with a minimal acyclic transducer as its lexicon.

The corpus's most frequent words are compiled, with their token ids as outputs,
into one acyclic automaton whose equal suffixes are shared.  Each arc carries a
number; their sum along a word is the word's place in a table of outputs.  Workers
map the automaton from a file of their own (unlinked at once, so nothing stays
behind) and walk it for all different words of a block in step, one byte a time.
Words that it lacks are merged by rank, exactly; so the lexicon decides speed
only, never ids.

A null text is an empty text: no tokens.  The empty text decodes to itself.  The
vocabulary's special tokens, where they stand in a text, become their ids.
"""

from __future__ import annotations

import hashlib
import json
import tempfile
from collections.abc import Iterator
from heapq import heapify, heappop, heappush
from itertools import chain

import numpy as np
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stringweave.llm._common import fields, per_text

#: Words compiled into the lexicon at most; the rest is merged when met.
LEXICON_WORDS = 1 << 15
PER_DOCS = 2000
#: Bytes from which a word is merged with a heap.
LONG_WORD = 200
#: Different words whose ids a worker remembers.
MEMO_WORDS = 400_000
#: The encoder that this worker used last, by the digest of its lexicon and vocabulary; the lexicon is mapped once per worker.
_LAST: dict[str, tuple] = {}

# Fixed value: the split pattern of the byte-level vocabulary, with the white-space class spelled out.
_WS = r"\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
PATTERN = rf"'s|'t|'re|'ve|'m|'ll|'d| ?\p{{L}}+| ?\p{{N}}+| ?[^{_WS}\p{{L}}\p{{N}}]+|[{_WS}]+(?![^{_WS}])|[{_WS}]+"


def byte_letters() -> dict[str, int]:
    """The printable letter that stands for each byte in the vocabulary file."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


class Vocabulary:
    """Token bytes, merges and special tokens of a byte-level BPE file."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            data = json.load(f)
        letters = byte_letters()
        spell = lambda s: bytes(letters[c] for c in s)
        vocab = data["model"]["vocab"]
        self.specials = {t["content"]: t["id"] for t in data["added_tokens"]}
        self.tokens: dict[int, bytes] = {i: spell(s) for s, i in vocab.items() if s not in self.specials}
        self.tokens |= {i: s.encode() for s, i in self.specials.items()}
        self.single = [vocab[c] for c, _ in sorted(letters.items(), key=lambda x: x[1])]
        self.ranks: dict[int, int] = {}  # by both ids, in one number
        self.joined: list[int] = []  # by rank
        for rank, pair in enumerate(data["model"]["merges"]):
            a, b = pair if isinstance(pair, list) else pair.split(" ")
            self.ranks.setdefault(vocab[a] << 20 | vocab[b], rank)
            self.joined.append(vocab[a + b])

    def merge(self, word: bytes) -> tuple[int, ...]:
        """Ids of one word: the neighbours of the best rank are joined, leftmost first, until none can be."""
        if len(word) > LONG_WORD:
            return self._merge_long(word)
        ids, get, none = [self.single[b] for b in word], self.ranks.get, len(self.joined)
        ranks = [get(a << 20 | b, none) for a, b in zip(ids, ids[1:])]
        while ranks and (best := min(ranks)) < none:
            i = ranks.index(best)
            new = ids[i] = self.joined[best]
            del ids[i + 1], ranks[i]
            if i:
                ranks[i - 1] = get(ids[i - 1] << 20 | new, none)
            if i < len(ranks):
                ranks[i] = get(new << 20 | ids[i + 1], none)
        return tuple(ids)


    def _merge_long(self, word: bytes) -> tuple[int, ...]:
        """The same over a linked list and a heap: n log n steps for a word of n bytes."""
        ids, get, n = [self.single[b] for b in word], self.ranks.get, len(word)
        left, right = list(range(-1, n - 1)), list(range(1, n + 1))
        heap = [(r, i, a, b) for i, (a, b) in enumerate(zip(ids, ids[1:])) if (r := get(a << 20 | b)) is not None]
        heapify(heap)
        while heap:
            rank, i, a, b = heappop(heap)
            j = right[i]
            if ids[i] != a or j >= n or ids[j] != b:
                continue
            ids[i], ids[j] = self.joined[rank], -1
            right[i] = k = right[j]
            if k < n:
                left[k] = i
                if (r := get(ids[i] << 20 | ids[k])) is not None:
                    heappush(heap, (r, i, ids[i], ids[k]))
            if (h := left[i]) >= 0 and (r := get(ids[h] << 20 | ids[i])) is not None:
                heappush(heap, (r, h, ids[h], ids[i]))
        return tuple(x for x in ids if x >= 0)


class Lexicon:
    """The transducer as flat arrays; see ``build``, ``dump`` and ``load``."""

    NAMES = ("arc_key", "arc_to", "arc_out", "final", "start", "ids")

    def __init__(self, arrays: dict[str, np.ndarray]):
        for k in self.NAMES:
            setattr(self, k, arrays[k])

    @classmethod
    def build(cls, entries: dict[bytes, tuple[int, ...]]) -> Lexicon:
        """Compile words with their ids.  States with equal futures are one state."""
        words = sorted(w for w in entries if w)
        states: list[tuple[bool, tuple]] = []
        known: dict[tuple, int] = {}
        path: list[list] = [[False, []]]  # the states of the last word that may still change

        def close(depth: int) -> None:
            while len(path) > depth + 1:
                last, arcs = path.pop()
                shape = (last, tuple(arcs))
                at = known.get(shape)
                if at is None:
                    at = known[shape] = len(states)
                    states.append(shape)
                path[-1][1][-1] = (path[-1][1][-1][0], at)

        before = b""
        for w in words:
            same = 0
            while same < min(len(w), len(before)) and w[same] == before[same]:
                same += 1
            close(same)
            for c in w[same:]:
                path[-1][1].append((c, -1))
                path.append([False, []])
            path[-1][0] = True
            before = w
        close(0)
        states.append((path[0][0], tuple(path[0][1])))
        below = [0] * len(states)  # words that end at or after each state; children come first
        key, to, out = [], [], []
        for s, (last, arcs) in enumerate(states):
            seen = int(last)
            for c, t in arcs:
                key.append((s << 8) | c)
                to.append(t)
                out.append(seen)
                seen += below[t]
            below[s] = seen
        root = len(states) - 1
        order = np.argsort(np.array(key, np.int64), kind="stable")
        flat = [entries[w] for w in words]
        return cls({
            "arc_key": np.array(key, np.int64)[order], "arc_to": np.array(to, np.int32)[order], "arc_out": np.array(out, np.int32)[order],
            "final": np.array([s[0] for s in states] or [False], np.bool_), "ids": np.array([*chain.from_iterable(flat)], np.int32),
            "start": np.concatenate(([root], np.cumsum([0, *map(len, flat)]))).astype(np.int64),
        })

    def dump(self) -> bytes:
        """One block of bytes: a line of JSON with the layout, then the arrays, aligned to eight."""
        layout, body, at = {}, [], 0
        for k in self.NAMES:
            raw = np.ascontiguousarray(getattr(self, k))
            data = raw.tobytes()
            layout[k] = [raw.dtype.str, at, len(raw)]
            pad = -len(data) % 8
            body.append(data + b"\0" * pad)
            at += len(data) + pad
        head = json.dumps(layout).encode()
        head += b" " * (-(len(head) + 1) % 8) + b"\n"
        return head + b"".join(body)

    @classmethod
    def load(cls, data: bytes) -> Lexicon:
        """Map a dumped lexicon from a nameless file, so that its pages can be dropped under pressure."""
        with tempfile.TemporaryFile() as f:
            f.write(data)
            f.flush()
            whole = np.memmap(f, np.uint8, "r")
        head = bytes(whole[: data.index(b"\n")])
        at = len(head) + 1
        return cls({k: whole[at + a : at + a + n * np.dtype(t).itemsize].view(t) for k, (t, a, n) in json.loads(head).items()})

    def find(self, words: list[bytes]) -> np.ndarray:
        """The place of each word, -1 where it is not compiled; all words walk in step."""
        n = len(words)
        lengths = np.fromiter(map(len, words), np.int64, n)
        begin = np.cumsum(lengths) - lengths
        letters = np.frombuffer(b"".join(words), np.uint8).astype(np.int64)
        state, number = np.full(n, int(self.start[0]), np.int64), np.zeros(n, np.int64)
        alive = np.nonzero(lengths > 0)[0] if len(self.arc_key) else np.empty(0, np.int64)
        place = np.full(n, -1, np.int64)
        depth = 0
        while len(alive):
            want = (state[alive] << 8) | letters[begin[alive] + depth]
            at = np.minimum(np.searchsorted(self.arc_key, want), len(self.arc_key) - 1)
            ok = self.arc_key[at] == want
            alive, at = alive[ok], at[ok]
            state[alive] = self.arc_to[at]
            number[alive] += self.arc_out[at]
            depth += 1
            ended = lengths[alive] == depth
            done = alive[ended]
            done = done[self.final[state[done]]]
            place[done] = number[done]
            alive = alive[~ended]
        return place

    def output(self, place: int) -> tuple[int, ...]:
        return tuple(self.ids[self.start[place + 1] : self.start[place + 2]].tolist())


class Encoder:
    """Encodes and decodes whole texts with a vocabulary and a lexicon."""

    def __init__(self, vocabulary: Vocabulary, lexicon: Lexicon):
        self.v, self.lexicon, self.memo = vocabulary, lexicon, {}
        self.split = regex.compile(PATTERN).findall
        self.marks = {s[0] for s in vocabulary.specials if s}
        self.special = regex.compile("(" + "|".join(map(regex.escape, sorted(vocabulary.specials, key=len, reverse=True))) + ")") if vocabulary.specials else None

    def _learn(self, new: list[str]) -> None:
        if len(self.memo) + len(new) > MEMO_WORDS:
            self.memo.clear()
        raw = [w.encode("utf-8", "replace") for w in new]
        places = self.lexicon.find(raw).tolist()
        output, merge = self.lexicon.output, self.v.merge
        self.memo.update((w, output(p) if p >= 0 else merge(r)) for w, r, p in zip(new, raw, places))

    def encode(self, texts: list[str]) -> Iterator[list[int]]:
        """Ids of each text."""
        pieces = []
        for t in texts:
            if self.special is not None and any(c in t for c in self.marks):
                pieces.append([x for i, part in enumerate(self.special.split(t)) for x in ([self.v.specials[part]] if i % 2 else self.split(part))])
            else:
                pieces.append(self.split(t))
        words = {w for p in pieces for w in p if isinstance(w, str)} if self.special is not None else set().union(*pieces)
        new = [w for w in words if w not in self.memo]
        if len(self.memo) + len(new) > MEMO_WORDS:
            self.memo.clear()
            new = list(words)
        self._learn(new)
        memo = self.memo
        for p in pieces:
            try:
                yield list(chain.from_iterable(map(memo.__getitem__, p)))
            except KeyError:  # a special token stands among the words
                yield list(chain.from_iterable(memo[w] if isinstance(w, str) else (w,) for w in p))

    def decode(self, ids: list[int]) -> str:
        """The text of some ids; bytes that are no UTF-8 become replacement characters."""
        return b"".join(map(self.v.tokens.__getitem__, ids)).decode("utf-8", "replace")


def frequent_words(df: DataFrame, text: str = "text", n: int = LEXICON_WORDS) -> list[str]:
    """The most frequent runs between spaces of the whole corpus, ``n`` at most, ties by code point.

    A frequent word occurs once in PER_DOCS documents on average, so the words that compete
    are at most PER_DOCS times the mean words of a document, however large the corpus.
    """
    least = max(2, df.count() // PER_DOCS)
    words = df.select(F.explode(F.split(F.col(f"`{text}`"), " ", -1)).alias("w")).where("w <> ''")
    top = words.groupBy("w").count().where(F.col("count") >= least).orderBy(F.desc("count"), "w").limit(n)
    return [r.w for r in top.collect()]


def compile_lexicon(vocabulary: Vocabulary, words: list[str]) -> Lexicon:
    """The transducer of the words' pieces, with and without the space before them."""
    split = regex.compile(PATTERN).findall
    pieces = {p.encode("utf-8", "replace") for w in words for p in (*split(w), *split(" " + w))}
    return Lexicon.build({p: vocabulary.merge(p) for p in pieces})


def encode_corpus(df: DataFrame, tokenizer_path: str, text: str = "text", keep: list[str] | None = None, ids: bool = True) -> DataFrame:
    """Append ``n_tokens``, ``ids_sha256``, ``decoded_sha256`` and, if asked for, ``ids``.

    The digests are of the decimal ids joined by commas and of the decoded text in UTF-8.
    """
    spark = df.sparkSession
    vocabulary = Vocabulary(tokenizer_path)
    dumped = compile_lexicon(vocabulary, frequent_words(df, text)).dump()
    shared, name = spark.sparkContext.broadcast((vocabulary, dumped)), hashlib.sha256(repr(tokenizer_path).encode() + dumped).hexdigest()

    def make():
        if name not in _LAST:
            voc, data = shared.value
            _LAST.clear()
            _LAST[name] = Encoder(voc, Lexicon.load(data)), {i: str(i) for i in voc.tokens}
        coder, digits = _LAST[name]
        sha = hashlib.sha256

        def work(texts):
            out = {"n_tokens": [], "ids_sha256": [], "decoded_sha256": []} | ({"ids": []} if ids else {})
            for got in coder.encode([(t or b"").decode("utf-8", "replace") for t in texts]):
                out["n_tokens"].append(len(got))
                out["ids_sha256"].append(sha(",".join(map(digits.__getitem__, got)).encode()).hexdigest())
                out["decoded_sha256"].append(sha(coder.decode(got).encode()).hexdigest())
                if ids:
                    out["ids"].append(got)
            return out

        return work

    schema = "n_tokens long, ids_sha256 string, decoded_sha256 string" + (", ids array<int>" if ids else "")
    return per_text(df, make, fields(schema), text, keep)
