"""Rounds as relational plans: each round's state is written once, read again, and its counters come with the write."""

from __future__ import annotations

import atexit
import tempfile
import uuid
from functools import cache

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F


@cache
def _own_folder() -> str:
    return tempfile.mkdtemp(prefix="stepgraph-")


def shared_folder(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir, which all executors share; a local one only where that is unset."""
    return spark.conf.get("spark.checkpoint.dir", None) or f"file://{_own_folder()}"


class Rounds:
    """Writes the state of each round and cuts its lineage, so a lost executor costs one round at most."""

    def __init__(self, spark: SparkSession, ledger=None, max_steps: int = 10_000):
        self.spark, self.ledger, self.max_steps, self.step = spark, ledger, max_steps, 0
        self.root, self.n, self.paths, self.tables = f"{shared_folder(spark)}/r-{uuid.uuid4().hex}", 0, {}, []
        atexit.register(self._end)

    def cut(self, df: DataFrame, old: DataFrame | None = None, **counters: Column) -> tuple[DataFrame, dict]:
        """The written form of df and its counters. ``old``: the state that it replaces, which is deleted."""
        path, self.n = f"{self.root}/{self.n}", self.n + 1
        if counters:
            seen = Observation()
            df.observe(seen, *[c.alias(k) for k, c in counters.items()]).write.parquet(path)
            got = {k: v or 0 for k, v in seen.get.items()}
        else:
            df.write.parquet(path)
            got = {}
        out = self.spark.read.schema(df.schema).parquet(path)
        self.paths[id(out)] = (path, out)
        if old is not None and id(old) in self.paths:
            self._delete(self.paths.pop(id(old))[0])
        return out, got

    def keyed(self, df: DataFrame, key: str) -> DataFrame:
        """The written form of df, in as many buckets of ``key`` as a shuffle has partitions: it moves once, here, and rounds that
        join it on ``key`` move their state only."""
        buckets = int(self.spark.conf.get("spark.sql.shuffle.partitions"))
        path, self.n, name = f"{self.root}/{self.n}", self.n + 1, f"keyed_{uuid.uuid4().hex}"
        df.repartition(buckets, key).write.bucketBy(buckets, key).sortBy(key).option("path", path).saveAsTable(name)
        self.tables.append(name)
        return self.spark.table(name)

    def next(self) -> int:
        self.step += 1
        if self.step > self.max_steps:
            raise RuntimeError(f"not settled after {self.max_steps} rounds")
        return self.step

    def _delete(self, path: str) -> None:
        where = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)

    def _end(self) -> None:
        try:
            for name in self.tables:
                self.spark.sql(f"drop table if exists {name}")
            self._delete(self.root)
        except Exception:  # noqa: BLE001  the session may be gone by then
            pass


def count_if(test: Column) -> Column:
    return F.sum(F.when(test, 1).otherwise(0))
