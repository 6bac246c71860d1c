"""What the corpus operators share: Arrow plumbing, word rules, the held-out split."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Bytes of text that a worker unpacks at once; a longer text makes a block of its own.
BLOCK_BYTES = 2_000_000


def held_out(doc_id: Column | str = "doc_id") -> Column:
    """True where crc32 of the id as text leaves 1 modulo 3; a null id counts as held out."""
    c = F.col(doc_id) if isinstance(doc_id, str) else doc_id
    return F.coalesce(F.pmod(F.crc32(c.cast("string").cast("binary")), F.lit(3)) == 1, F.lit(True))


def blocks(texts: list, limit: int = BLOCK_BYTES) -> Iterator[tuple[int, int]]:
    """Ranges of consecutive texts of about ``limit`` bytes in all."""
    start = total = 0
    for i, t in enumerate(texts):
        total += len(t or b"")
        if total >= limit:
            yield start, i + 1
            start, total = i + 1, 0
    if start < len(texts):
        yield start, len(texts)


def per_text(df: DataFrame, make: Callable[[], Callable], out: T.StructType, text: str = "text", keep: list[str] | None = None) -> DataFrame:
    """Append columns computed from whole texts, in one narrow pass.

    ``make`` runs once per task and returns a function from a list of texts (bytes or
    None) to a dict of columns.  ``keep`` names the columns carried along, all by
    default; a carried column whose name clashes with a new one (whatever the case of
    its letters) gives way to the new one.  A text that is carried along is sent once.
    """
    new = {f.name.lower() for f in out}
    names = [c for c in (df.columns if keep is None else keep) if c.lower() not in new]
    once = text in names and isinstance(df.schema[text].dataType, T.StringType)
    src = df.select(*[F.col(f"`{c}`") for c in names], *([] if once else [F.col(f"`{text}`").cast("binary").alias("__text")]))
    schema = T.StructType([src.schema[c] for c in names] + list(out))
    at = names.index(text) if once else len(names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        work = None
        for batch in batches:
            if not batch.num_rows:
                continue
            work = work or make()
            texts = batch.column(at).cast(pa.binary()).to_pylist()
            for a, b in blocks(texts):
                got = work(texts[a:b])
                arrays = [batch.column(i).slice(a, b - a) for i in range(len(names))]
                yield pa.RecordBatch.from_arrays(
                    [*arrays, *[pa.array(got[f.name], arrow_type(f.dataType)) for f in out]],
                    names=[*names, *[f.name for f in out]],
                )

    return src.mapInArrow(run, schema)


def arrow_type(t: T.DataType) -> pa.DataType:
    """The Arrow type of the plain Spark types that the operators return."""
    if isinstance(t, T.ArrayType):
        return pa.list_(arrow_type(t.elementType))
    if isinstance(t, T.StructType):
        return pa.struct([(f.name, arrow_type(f.dataType)) for f in t])
    return {
        T.LongType: pa.int64(), T.IntegerType: pa.int32(), T.DoubleType: pa.float64(), T.FloatType: pa.float32(),
        T.StringType: pa.string(), T.BooleanType: pa.bool_(), T.BinaryType: pa.binary(),
    }[type(t)]


def fields(ddl: str) -> T.StructType:
    """A struct type from a DDL string of plain types."""
    return T.StructType.fromDDL(ddl)


def table(spark, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def word_count(text: Column | str) -> Column:
    """Number of maximal runs outside space and tab to carriage return; null counts 0."""
    c = F.col(text) if isinstance(text, str) else text
    return F.coalesce(F.regexp_count(c, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")
