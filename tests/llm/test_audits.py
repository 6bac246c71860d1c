"""Audits and bounds that must not pass in silence."""

import numpy as np
import pytest

from stringweave.llm import chat, embeddings


class _Narrow:
    """A search that finds nothing but the vectors themselves until its beam is wide."""

    def __init__(self, unit, links):
        self.unit, self.links = unit, links

    def within(self, q, at_least, beam, own):
        self_ = np.arange(len(q))
        more = np.array(self.links).T if beam >= 256 else np.empty((2, 0), np.int64)
        return np.concatenate([self_, more[0]]), np.concatenate([self_, more[1]])


def test_own_matches_do_not_carry_the_audit():
    raw = np.random.default_rng(1).normal(size=(8192, 16))
    raw[1] = raw[0] * 2
    i, j, (truth, found, beam) = embeddings.search(_Narrow(raw, [(0, 1), (1, 0)]), raw, raw, own=True)
    assert {(0, 1), (1, 0)} <= set(zip(i.tolist(), j.tolist()))
    assert (truth, found) == (1, 1) and beam >= 256


def test_reversed_chain_is_peeled_whole_or_raises(spark, monkeypatch):
    monkeypatch.setattr(chat, "ROUNDS_APART", 2)
    ev = [(1, i, "call", "f", f"c{i}", [f"c{i + 1}"] if i < 5 else [], "{}") for i in range(6)]
    e = spark.createDataFrame(ev, chat.EVENTS)
    assert {r.call_id: r.depth for r in chat.depths(e, max_rounds=0).collect()} == {f"c{i}": 5 - i for i in range(6)}
    monkeypatch.setattr(chat, "GROUP_CALLS", 2)
    assert {r.call_id: r.depth for r in chat.depths(e).collect()} == {f"c{i}": 5 - i for i in range(6)}
    with pytest.raises(RuntimeError):
        chat.depths(e, max_rounds=3)
