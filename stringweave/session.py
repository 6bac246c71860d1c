"""Session helpers: where intermediate tables live and how a lineage is cut.

Executors can be lost at any time, so nothing here keeps blocks on one executor:
a cut lineage is always a table in the shared folder that the cluster names in
``spark.checkpoint.dir``.
"""

from __future__ import annotations

import contextlib
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The shared scratch folder of this session.

    ``spark.checkpoint.dir`` if the cluster sets it.  Only a local master, whose
    executors share the driver's disk, may fall back to a temporary folder.
    """
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    if not spark.sparkContext.master.startswith("local["):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    own = "file://" + tempfile.mkdtemp(prefix="stringweave-")
    spark.conf.set("spark.checkpoint.dir", own)
    return own


#: One list of folders per open ``released`` block, the innermost last.
_OPEN: list[list[str]] = []


@contextlib.contextmanager
def released(spark: SparkSession):
    """Deletes at its end what was kept inside it; for work whose result has been written elsewhere."""
    _OPEN.append([])
    try:
        yield
    finally:
        for root in _OPEN.pop():
            _delete(spark, root)


def _path(spark: SparkSession, path: str):
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p, p.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf())


def _delete(spark: SparkSession, path: str) -> None:
    p, fs = _path(spark, path)
    fs.delete(p, True)


class Scratch:
    """Tables written to the shared folder; ``drop`` deletes those no longer read.

    A lazy result may read them as long as the session lives, so what nobody dropped goes when the
    session ends, or with the ``released`` block around it.
    """

    def __init__(self, spark: SparkSession, label: str):
        self.spark = spark
        self.root = f"{shared_dir(spark)}/stringweave/{label}-{uuid.uuid4().hex}"
        self.n = 0
        if _OPEN:
            _OPEN[-1].append(self.root)

    def keep(self, df: DataFrame) -> DataFrame:
        """Write ``df`` once and return a scan of what was written.

        The scan has no inherited partitioning, so both sides of a later join are plain
        exchanges, which adaptive execution may split when a key is hot; it also has
        true sizes, so small sides are broadcast and large ones are not.
        """
        path = f"{self.root}/t{self.n}"
        self.n += 1
        df.write.parquet(path)
        if path.endswith("/t0"):
            p, fs = _path(self.spark, self.root)
            fs.deleteOnExit(p)
        out = self.spark.read.schema(df.schema).parquet(path)
        out._scratch_path = path
        return out

    def drop(self, df: DataFrame | None) -> None:
        """Delete a table made by ``keep``; nothing may read it afterwards."""
        path = getattr(df, "_scratch_path", None)
        if path:
            _delete(self.spark, path)


def task_count(spark: SparkSession, n_rows: int, rows_per_task: int) -> int:
    """Tasks for a stage whose cost follows its rows, never under the session's setting."""
    return max(int(spark.conf.get("spark.sql.shuffle.partitions", "200")), -(-n_rows // rows_per_task))
