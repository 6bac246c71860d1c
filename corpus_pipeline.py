"""The corpus pipeline: language, near duplicates, personal data, mix, token ids.

Every stage takes ``(spark, docs, sf_dir)`` and returns a DataFrame that is written as
Parquet and read again as the next stage's documents.  All but the last return the
columns of the documents they were given.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stringweave.llm import bpe, langid, mixing, pii, simhash
from stringweave.llm.queries import tokenizer_path
from stringweave.session import Scratch, released

#: Language networks, random order and tokens have no SQL; tests/llm compares the rows with plain Python.
ORACLE_SQL = None
#: Share of the probability that the best language of a text must have.
LEAST_SCORE = 0.4


def _numbered(docs: DataFrame) -> DataFrame:
    """The columns but the text under numbers, so that none clashes with what an operator appends."""
    return docs.select(*[F.col(f"`{c}`").alias(c if c == "text" else f"__{i}") for i, c in enumerate(docs.columns)])


def language_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language the network tells, with that language as their ``lang``.

    Texts that are null or without a letter go, and those whose best language has less than
    LEAST_SCORE of the probability.  Repeated rows keep their number; other columns, whatever their
    names, pass unchanged.
    """
    own = _numbered(docs)
    tagged = langid.identify(own, learn_from=docs)
    told = tagged.where((F.col("lang_pred") != "und") & (F.col("score") >= LEAST_SCORE))
    return told.select(*[F.col("lang_pred" if c == "lang" else own.columns[i]).alias(c) for i, c in enumerate(docs.columns)])


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies, the one with the smallest id.

    Rows without an id stay; of repeated rows of an id one stays.
    """
    return simhash.keep_one(docs)


def personal_data_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data replaced by its kind in brackets; ``n_chars``, where there is one, follows the text.

    A null text stays null and keeps its ``n_chars``.  Other columns, whatever their names, pass unchanged.
    """
    own = _numbered(docs)
    found = pii.scan(own, keep=[c for c in own.columns if c != "text"], mask=True)
    out = []
    for i, c in enumerate(docs.columns):
        if c == "text":
            out.append(F.col("masked").alias(c))
        elif c == "n_chars":
            out.append(F.when(F.col("masked").isNull(), F.col(f"__{i}")).otherwise(F.length("masked")).cast(docs.schema[c].dataType).alias(c))
        else:
            out.append(F.col(f"__{i}").alias(c))
    return found.select(*out)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents as the mix serves them; those served again repeat, those without a word go.

    A null source is a source like any other, the last.
    """
    return mixing.mixed(docs)


def token_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every document of the mix, with the digests of ids and decoded text.

    A null text has no ids.  Returns ``doc_id, lang, source, n_tokens, ids_sha256, decoded_sha256, ids``.
    """
    return bpe.encode_corpus(docs.select("doc_id", "text", "lang", "source"), tokenizer_path(), keep=["doc_id", "lang", "source"])


STAGES = [
    ("language", language_stage),
    ("near duplicates", near_duplicate_stage),
    ("personal data", personal_data_stage),
    ("mixing", mixing_stage),
    ("tokens", token_stage),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written to the shared folder and read again."""
    docs, store = spark.read.parquet(f"{sf_dir}/documents.parquet"), Scratch(spark, "pipeline")
    before = None
    for _, stage in STAGES:
        with released(spark):
            after = store.keep(stage(spark, docs, sf_dir))
        store.drop(before)
        docs = before = after
    return docs
