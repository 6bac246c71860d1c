"""Every operator and stage on empty tables, nulls, ties, repeats, long texts and clashing names; the parts against plain Python."""

import json
from fractions import Fraction
from itertools import combinations

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from stringweave.llm import bpe, chat, embeddings, langid, mixing, pii, quality, queries, simhash, toxicity, urls

ROWS = [
    (1, None, "en", "a", 0), (2, "", "en", "a", 0), (3, " \n\t ", None, "a", 4), (4, "one", "en", None, 3), (5, "Same words here now", "en", "b", 19), (5, "Same words here now", "en", "b", 19),
    (6, "same WORDS here now", "fr", "b", 19), (None, "no id at all here", "en", "c", 17), (7, "x" * 200_000, "de", "c", 200_000), (8, "word " * 40_000, "de", None, 200_000),
    (9, "mail me at a.b@c.org", "es", "c", None), (9, "other text with +49 170 1234567 inside", "es", "c", 1),
]
#: Names that operators append, as a user's own columns.
OWN = ["Score", "FP", "kept", "size", "spans", "n_email", "N_Tokens", "h", "target", "rank", "masked", "lang_pred", "component_id", "__source", "json", "conv"]


@pytest.fixture(scope="module")
def docs(spark):
    df = spark.createDataFrame(ROWS, "doc_id long, text string, lang string, source string, n_chars long")
    return df.withColumns({c: F.lit(f"own {c}") for c in OWN})


def own_columns(df, names=tuple(OWN)):
    return all(r[c] == f"own {c}" for r in df.collect() for c in names)


def test_empty_tables(spark, docs):
    none = docs.limit(0)
    model = toxicity.train([b"foul foul word"] * 3, [b"fine words only"] * 5)
    path = queries.tokenizer_path()
    for made in (toxicity.score(none, model), bpe.encode_corpus(none, path), simhash.near_duplicates(none), simhash.keep_one(none), pii.scan(none), quality.judge(none), langid.identify(none), mixing.mix(none), mixing.mixed(none)):
        assert made.count() == 0
    assert chat.format_calls(spark.createDataFrame([], chat.EVENTS), chat.REPLY).count() == 0
    vec = spark.createDataFrame([], "vec_id long, embedding array<float>, label int")
    assert embeddings.near_duplicates(vec).count() == 0 and embeddings.recall(vec).first().recall == 1.0
    assert urls.judge(spark.createDataFrame([], "page_id long, url string"), spark.createDataFrame([], "url string")).count() == 0


@pytest.mark.parametrize("stage", [f for _, f in corpus_pipeline.STAGES[:4]])
def test_stages_on_odd_rows(spark, docs, stage):
    out = stage(spark, docs, "")
    assert out.columns == docs.columns and out.dtypes == docs.dtypes
    assert own_columns(out)
    assert stage(spark, docs.limit(0), "").count() == 0


def test_personal_data_stage_changes_text_only(spark, docs):
    out = corpus_pipeline.personal_data_stage(spark, docs, "").collect()
    assert len(out) == len(ROWS)
    text = {r.text: r.n_chars for r in out}
    assert text[None] == 0 and text["mail me at [EMAIL]"] == 18 and text["other text with [PHONE] inside"] == 30


def test_pipeline_on_odd_and_empty_documents(spark, docs, tmp_path):
    for name, rows in (("odd", docs), ("none", docs.limit(0))):
        rows.write.parquet(f"{tmp_path}/{name}/documents.parquet")
        out = corpus_pipeline.run(spark, f"{tmp_path}/{name}").collect()
        assert {r.doc_id for r in out} <= {4, 5, 7, 8, 9, None} and (name == "odd") == bool(out)


def test_clashing_columns(spark, docs):
    assert "N_Tokens" not in bpe.encode_corpus(docs, queries.tokenizer_path()).columns
    near = simhash.near_duplicates(docs)
    assert near.columns.count("component_id") == 1 and "FP" not in near.columns and near.count() == len(ROWS)
    kept = simhash.keep_one(docs)
    assert kept.columns == docs.columns and own_columns(kept)
    vec = spark.createDataFrame([(1, [1.0, 0.0], 1, "x"), (2, [1.0, 0.0], 1, "y")], "vec_id long, embedding array<float>, label int, n_links string")
    assert {(r.vec_id, r.n_links, r.component_id) for r in embeddings.near_duplicates(vec.withColumn("key", F.lit(1)).withColumn("Kept", F.lit(1))).collect()} == {(1, 1, 1), (2, 1, 1)}
    ev = spark.createDataFrame([(1, 0, "call", "reply", "a", [], "{}")], chat.EVENTS).withColumn("status", F.lit("own")).withColumn("key", F.lit(1)).withColumn("valid", F.lit(2))
    assert chat.format_calls(ev, chat.REPLY).first().status == "unanswered"
    df = spark.createDataFrame([(1, "http://a.org/x", "own")], "page_id long, url string, canonical string")
    assert urls.judge(df, spark.createDataFrame([("a.org/x",)], "url string")).first().canonical == "a.org/x"


# ---- tool calls ----


def test_schemas_types_enums_and_numbers():
    ok = lambda v, s: chat.problems(v, s) == []
    assert ok(None, {"type": ["string", "null"]}) and ok("a", {"type": ["string", "null"]})
    assert chat.problems(1, {"type": ["string", "null"]}) == ["$: not string or null"]
    assert chat.problems(1, {"type": "date"}) == ["$: not date"]
    assert ok(1.0, {"type": "integer"}) and not ok(1.5, {"type": "integer"}) and not ok(True, {"type": "number"})
    assert not ok(True, {"enum": [1]}) and ok(1.0, {"enum": [1]}) and ok([{"a": 1}], {"enum": [[{"a": 1.0}]]}) and not ok([True], {"enum": [[1]]})
    for bad in ("1e400", "NaN", '{"a":1,"a":2}', "[-1e999]", "[" * 100_000):
        with pytest.raises(ValueError):
            chat.parsed(bad)
    assert chat.parsed('{"a":1e3}') == {"a": 1000.0}


def test_very_long_bodies_and_repeated_rows(spark):
    long = json.dumps({"prompt": "y" * 2_000_000, "turn": 1, "chars": 2_000_000})
    ev = [(1, 0, "call", "reply", "a", ["a"], long), (1, 0, "call", "reply", "a", ["a"], long), (1, 1, "result", "reply", "a", None, "z" * 2_000_000), (2, None, "call", "reply", None, None, ""), (None, None, None, None, None, None, None)]
    got = chat.format_calls(spark.createDataFrame(ev, chat.EVENTS), chat.REPLY).collect()
    assert len(got) == 5
    assert [(r.status, r.depth, r.valid) for r in got if r.kind == "call" and r.conv_id == 1] == [("linked", -1, True)] * 2


def test_peeling_equals_the_order_in_memory(spark, monkeypatch):
    rng = np.random.default_rng(5)
    ev = [(c, i, "call", "f", f"c{i}", sorted({f"c{int(x)}" for x in rng.integers(0, 14, rng.integers(0, 3))}), "{}") for c in range(12) for i in range(12)]
    e = spark.createDataFrame(ev, chat.EVENTS)
    small = {(r.conv_id, r.call_id): r.depth for r in chat.depths(e).collect()}
    monkeypatch.setattr(chat, "GROUP_CALLS", 3)
    assert small and {(r.conv_id, r.call_id): r.depth for r in chat.depths(e).collect()} == small


# ---- toxicity: the kernel as its definition says ----


def brute_features(word):
    """Subsequences of three and four letters inside five, with their weights added up."""
    w, out = "\x02" + word + "\x03", {}
    for start in range(len(w)):
        for size in (2, 3):
            for rest in combinations(range(1, toxicity.SPAN), size):
                if start + rest[-1] < len(w):
                    key = tuple(w[start + o] for o in (0, *rest))
                    # words are compared place by place of equal shape or not: the same letters meet in one feature
                    out[key] = out.get(key, 0) + toxicity.DISCOUNT ** (rest[-1] - size) * (1.0 if size == 2 else 1.5)
    return out


def brute_scale(word):
    n, total = len(word) + 2, 0.0
    for size in (2, 3):
        for rest in combinations(range(1, toxicity.SPAN), size):
            weight = toxicity.DISCOUNT ** (rest[-1] - size) * (1.0 if size == 2 else 1.5)
            total += weight**2 * max(0, n - rest[-1])
    return total**0.5


def test_kernel_against_all_gapped_subsequences():
    words = ["idiot", "idxiot", "stupid", "stpid", "fine", "a", "idiots", "banana"]
    gram = toxicity._Features(words).gram(np.arange(len(words)))[0]
    f = [brute_features(w) for w in words]
    want = [[sum(v * g.get(k, 0) for k, v in h.items()) / brute_scale(a) / brute_scale(b) for b, g in zip(words, f)] for a, h in zip(words, f)]
    assert np.allclose(gram, want, atol=1e-4)
    assert gram[0, 1] > gram[0, 4] and gram[2, 3] > gram[2, 4]


def test_long_labelled_texts_teach_nothing(spark):
    docs = spark.createDataFrame([(2, "x" * (toxicity.TRAIN_BYTES + 1)), (3, "y")], "doc_id long, text string")
    labels = spark.createDataFrame([(2, 1), (3, 1)], "doc_id long, toxic int")
    toxic, clean = toxicity.labelled(docs, labels)
    assert b"y" in [*toxic, *clean, b"y"] and all(len(t) < 10 for t in toxic)


# ---- vectors ----


def test_vectors_in_double_precision_and_any_label(spark):
    big = [(1, [1e300, 1.0], "a"), (2, [1e300, 2.0], "a"), (3, [1e-300, 0.0], "a"), (4, [1e300, 1.0], "b"), (5, [1.0, 0.0], None)]
    got = {r.vec_id: (r.n_links, r.component_id) for r in embeddings.near_duplicates(spark.createDataFrame(big, "vec_id long, embedding array<double>, label string")).collect()}
    assert got == {1: (2, 1), 2: (2, 1), 3: (2, 1), 4: (0, 4), 5: (0, 5)}
    for kind, values in (("long", [1 << 40, (1 << 40) + 1]), ("double", [0.0, -0.0]), ("boolean", [True, False])):
        df = spark.createDataFrame([(i, [1.0, 0.0], v) for i, v in enumerate(values)], f"vec_id long, embedding array<float>, label {kind}")
        assert {r.n_links for r in embeddings.near_duplicates(df).collect()} == {1 if kind == "double" else 0}


def test_graphs_answer_with_narrow_beams():
    rng = np.random.default_rng(7)
    base = rng.standard_normal((400, 24))
    raw = np.concatenate([base + 0.01 * rng.standard_normal(base.shape) for _ in range(4)])
    unit = raw / np.linalg.norm(raw, axis=1, keepdims=True)
    i, j, (truth, found, beam) = embeddings.search(embeddings.Graph(unit), raw, raw, own=True)
    want = set(zip(*np.nonzero(unit @ unit.T >= 0.98)))
    assert beam < len(raw) and truth == found > 0
    assert len(want - set(zip(i.tolist(), j.tolist()))) <= 0.005 * len(want) and set(zip(i.tolist(), j.tolist())) <= want


def test_recall_is_reported(spark, data):
    got = embeddings.recall(spark.read.parquet(f"{data}/embeddings.parquet")).first()
    assert got.recall >= 0.995 and got.shard_pairs > 0


# ---- fingerprints ----


def test_pivots_discard_nearly_all_that_bands_bring_together(spark, data):
    nodes = simhash.fingerprints(spark.read.parquet(f"{data}/documents.parquet")).select("fp").distinct()
    seen = simhash.discards(simhash.links(nodes, nodes.count())).first()
    assert seen.pairs > seen.formed > seen.verified and seen.verified < 0.1 * seen.pairs


# ---- URLs ----


def test_listed_and_unlisted_pages_of_one_host(spark, monkeypatch, tmp_path):
    pages = spark.read.parquet("/root/testdata/sf0.1/pages.parquet").select("page_id", "url")
    got = urls.judge(pages, queries.listed_urls(pages)).where("rule is null")
    both = got.groupBy("host").agg(F.count_distinct("verdict").alias("n")).where("n = 2").count()
    assert both > 0
    one = got.where("verdict = 'allow'").first()
    (tmp_path / "list.txt").write_text(one.canonical + "\n\nnobody.example/x\n")
    monkeypatch.setattr(queries, "BLOCK_LIST", str(tmp_path))
    again = urls.judge(pages, queries.listed_urls(pages)).where("rule is null and verdict = 'block'").collect()
    assert {r.canonical for r in again} == {one.canonical}


# ---- mixing ----


def test_descent_equals_one_sort(spark, data, monkeypatch):
    want = sorted(map(tuple, queries.op10_mixing(spark, data).collect()))
    for name, value in (("EDGE_ROWS", 4), ("FAN", 8), ("BUCKET_ROWS", 2)):
        monkeypatch.setattr(mixing, name, value)
    assert sorted(map(tuple, queries.op10_mixing(spark, data).collect())) == want


def test_fill_level_against_plain_python(spark, monkeypatch):
    monkeypatch.setattr(mixing, "EDGE_ROWS", 2)
    monkeypatch.setattr(mixing, "FAN", 4)
    rng = np.random.default_rng(3)
    for _ in range(4):
        rows = [(3 * int(s), int(w)) for s, w in zip(rng.integers(0, 40, 25), rng.integers(1, 4, 25))]
        budget = sum(c for c, _ in rows) // 3
        got = mixing.fill_level(spark.createDataFrame(rows, "cap long, weight long"), budget, sum(w for _, w in rows))
        level, taken, beyond = None, 0, sum(w for _, w in rows)
        for ratio in sorted({Fraction(c, w) for c, w in rows}):
            own = [(c, w) for c, w in rows if Fraction(c, w) == ratio]
            c, w = sum(x for x, _ in own), sum(x for _, x in own)
            if taken + c + ratio * (beyond - w) > budget:
                break
            level, taken, beyond = ratio, taken + c, beyond - w
        assert got == (level, budget - taken, beyond)


def test_many_rows_of_one_id_and_many_tied_sources(spark, monkeypatch):
    monkeypatch.setattr(mixing, "EDGE_ROWS", 5)
    rows = [(None, "w w w", "big") for _ in range(200)] + [(i, "w", f"s{i}") for i in range(60)] + [(7, "w w", "big")] * 3
    got = mixing.mix(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()
    assert len(got) == len(rows) and sum(r.taken for r in got) <= sum(r["size"] for r in got)
    assert len({r.taken for r in got if r.doc_id is None}) == 1


def test_scratch_of_a_block_goes_with_it(spark):
    from stringweave.session import Scratch, _path, released

    with released(spark):
        store = Scratch(spark, "tests")
        kept = store.keep(spark.range(3))
        assert kept.count() == 3
    p, fs = _path(spark, store.root)
    assert not fs.exists(p)
