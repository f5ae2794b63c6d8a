"""Edge streams: components kept up to date by batches, and windowed degrees."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..engine import Rounds
from ..model import Graph
from ..operators.components import hook_shortcut

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    raw = spark.readStream.schema(EVENTS).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def drained(df: DataFrame, rounds: Rounds, mode: str = "append") -> DataFrame:
    """The stream's rows once all that is there has been read, as a table."""
    path = f"{rounds.root}/stream-{rounds.n}"
    rounds.n += 1
    q = df.writeStream.format("parquet").option("path", path).option("checkpointLocation", path + "-log").outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.read.schema(df.schema).parquet(path)


class Components:
    """(id, component) of all edges seen. A batch's edges go through the labels, whose small graph is then solved; a batch
    that comes again changes nothing."""

    def __init__(self, spark: SparkSession):
        self.rounds, self.labels, self.last = Rounds(spark), None, -1

    def update(self, edges: DataFrame, batch: int) -> None:
        if batch <= self.last:
            return
        edges = edges.select("src", "dst")
        ids = edges.select(F.col("src").alias("id")).union(edges.select("dst")).distinct()
        if self.labels is None:
            now = ids.select("id", F.col("id").alias("component"))
        else:
            now = self.labels.unionByName(ids.join(self.labels, "id", "left_anti").select("id", F.col("id").alias("component")))
        now, _ = self.rounds.cut(now)
        a, b = (now.select(F.col("id").alias(k), F.col("component").alias(f"c{k}")) for k in ("src", "dst"))
        small = edges.join(a, "src").join(b, "dst").where("csrc <> cdst").select(F.col("csrc").alias("src"), F.col("cdst").alias("dst")).distinct()
        small, _ = self.rounds.cut(small)
        merged = hook_shortcut(Graph.from_edges(small)).select(F.col("id").alias("component"), F.col("component").alias("to"))
        self.labels, _ = self.rounds.cut(now.join(merged, "component", "left").select("id", F.coalesce("to", "component").alias("component")), self.labels)
        self.last = batch

    def follow(self, stream: DataFrame) -> DataFrame:
        """Runs the stream (src, dst) until it has been read, and gives the labels."""
        q = stream.writeStream.foreachBatch(lambda df, k: self.update(df, k)).option("checkpointLocation", f"{self.rounds.root}/log").trigger(availableNow=True).start()
        q.awaitTermination()
        return self.labels
