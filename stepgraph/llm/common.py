"""Helpers shared by the pipeline operators: scratch tables and A-Z lower-casing."""

from __future__ import annotations

import atexit
import functools
import tempfile
import uuid
from functools import cache

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


@cache
def _own_folder() -> str:
    return tempfile.mkdtemp(prefix="llm-scratch-")


def shared_folder(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir. Where that is unset, a folder of this machine, for a local master alone."""
    if given := spark.conf.get("spark.checkpoint.dir", None):
        return given
    if not spark.sparkContext.master.split("[")[0] == "local":
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    return f"file://{_own_folder()}"


def whole_rows(df: DataFrame) -> Column:
    """A row of ``df`` as one column, so that names an operator adds can't clash with the input's."""
    return F.struct(*(F.col(f"`{c}`") for c in df.columns)).alias("_all")


#: Tables of more rows than this are joined by shuffle, not by broadcast (40 MB or so).
BROADCAST_ROWS = 1_000_000


def broadcast_small(df: DataFrame, rows: int) -> DataFrame:
    """For a join with a table of so many rows: broadcast only if they are few."""
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df


#: Rows that go to a Python worker at once.
BATCH_ROWS = 1000


def small_batches(spark: SparkSession) -> None:
    """Lowers the session's rows a batch, so that a batch of texts takes some MB of the JVM and of a worker, not some hundred.
    It is a setting of the running session and decides nothing but memory."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(key, "0")) <= BATCH_ROWS:
        spark.conf.set(key, str(BATCH_ROWS))


def trimmed(run):
    """The same function of batches, which hands a worker's freed memory back to the machine when its task ends: workers live
    on for other tasks, beside the JVM that they share an executor with."""

    @functools.wraps(run)
    def wrapped(batches):
        try:
            yield from run(batches)
        finally:
            import ctypes

            import pyarrow

            pyarrow.default_memory_pool().release_unused()
            if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):
                trim(0)

    return wrapped


class Scratch:
    """Written tables that cut lineage. All executors and the driver see them, so a lost executor loses nothing.

    ``drop`` deletes a superseded table at once; the others go when the interpreter ends.
    """

    def __init__(self, spark: SparkSession):
        self.spark, self.root, self.paths = spark, f"{shared_folder(spark)}/t-{uuid.uuid4().hex}", {}
        atexit.register(self._end)

    def keep(self, df: DataFrame) -> DataFrame:
        path = f"{self.root}/{len(self.paths)}-{uuid.uuid4().hex[:8]}"
        df.write.parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        self.paths[id(out)] = (path, out)
        return out

    def drop(self, df: DataFrame) -> None:
        path, _ = self.paths.pop(id(df), (None, None))
        if path:
            self._delete(path)

    def _delete(self, path: str) -> None:
        jvm = self.spark.sparkContext._jvm
        where = jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)

    def _end(self) -> None:
        try:
            self._delete(self.root)
        except Exception:  # noqa: BLE001  the session may be gone by then
            pass


def ascii_lower(text: Column) -> Column:
    """A-Z only. A text of one byte a character takes the fast native path; others go through translate."""
    return F.when(F.octet_length(text) == F.char_length(text), F.lower(text)).otherwise(F.translate(text, UPPER, LOWER))


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")
