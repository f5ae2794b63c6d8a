"""What a run costs: work and messages by round and logical processor, and the two tests made of them."""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

ROUND = "algo string, step int, proc int, work long, sent long, received long"


@dataclass
class Ledger:
    """Counts of each round. Processor ``id mod p`` owns a vertex, wherever Spark puts it; so counts don't hang on partitions."""

    algo: str
    p: int = 8
    steps: list[tuple] = field(default_factory=list)  # rows of ROUND, p a round
    worst: list[tuple] = field(default_factory=list)  # (step, largest messages / (degree + 1), its vertex)
    computed: list[tuple] = field(default_factory=list)  # the same of what a vertex does
    stored: list[tuple] = field(default_factory=list)  # and of what it keeps
    combined: list[int] = field(default_factory=list)
    active: list[int] = field(default_factory=list)

    def record(self, step: int, sends: DataFrame, degrees: DataFrame | None = None, active: DataFrame | None = None, stored: DataFrame | None = None) -> int:
        """``sends``: a row (src, dst) per message before combining, with ``size`` if messages are not of one scalar. ``stored``:
        (id, n), the values that a vertex keeps between rounds besides its edges, where they are not one a vertex."""
        if "size" not in sends.columns:
            sends = sends.withColumn("size", F.lit(1))
        return self.record_all(sends.withColumn("step", F.lit(0)), [step], degrees, active, None if stored is None else stored.withColumn("step", F.lit(0)))[0]

    def record_all(self, sends: DataFrame, steps: list[int], degrees: DataFrame | None = None, active: DataFrame | None = None, stored: DataFrame | None = None) -> list[int]:
        """The same for several rounds in one pass: ``sends`` (step, src, dst, size) and ``stored`` (step, id, n), where step is a
        place in ``steps``; so the plan of a single round is the same each time and is compiled once."""
        none = F.lit(0).cast("long")
        ends = F.explode(F.array(F.struct(F.col("src").alias("id"), F.col("size").alias("sent"), none.alias("received")), F.struct(F.col("dst").alias("id"), none.alias("sent"), F.col("size").alias("received"))))
        x = sends.withColumn("size", F.col("size").cast("long")).select("step", ends.alias("e")).select("step", "e.*")
        x = x.withColumn("on", F.lit(None).cast("int") if active is not None else F.lit(0))
        if active is not None:
            for k in range(len(steps)):
                x = x.unionByName(active.select(F.lit(k).alias("step"), "id", none.alias("sent"), none.alias("received"), F.lit(1).alias("on")))
        x = x.withColumns({"acts": F.lit(1), "degree": none, "known": F.lit(0), "n": none})
        if degrees is not None:
            every = degrees.select(F.explode(F.array(*map(F.lit, range(len(steps))))).alias("step"), "id", F.lit(0).alias("acts"), F.col("degree").cast("long").alias("degree"), F.lit(1).alias("known"), (F.lit(1) if stored is None else none).cast("long").alias("n"))
            more = [every]
            if stored is not None:
                more.append(stored.select("step", "id", F.lit(0).alias("acts"), none.alias("degree"), F.lit(0).alias("known"), F.col("n").cast("long").alias("n")))
            for part in more:
                x = x.unionByName(part.withColumns({"sent": none, "received": none, "on": F.lit(0)}))
        both = x.groupBy("step", "id").agg(*[F.sum(c).alias(c) for c in ("sent", "received", "degree", "n")], *[F.max(c).alias(c) for c in ("on", "acts", "known")])
        if active is None:
            both = both.withColumn("on", (F.col("sent") > 0).cast("int"))
        both = both.fillna(0, ["on"]).withColumn("work", F.col("on") + F.col("sent") + F.col("received"))
        room, here, known = F.col("degree") + 1, F.col("acts") == 1, F.col("known") == 1
        loads = {"worst": F.when(here & known, F.greatest("sent", "received") / room), "computed": F.when(here & known, F.col("work") / room), "stored": F.when(known, (F.col("degree") + F.col("n")) / room)}
        heaviest = [F.max(F.when(v.isNotNull(), F.struct(v.alias("w"), F.col("id").alias("id")))).alias(f"_{k}") for k, v in loads.items()]
        sums = [F.sum(F.when(here, F.col(c)).otherwise(0)).alias(c) for c in ("work", "sent", "received", "on")]
        rows = both.groupBy("step", F.pmod("id", F.lit(self.p)).cast("int").alias("proc")).agg(*sums, F.count_if(here & (F.col("received") > 0)).alias("combined"), F.max("acts").alias("acts"), *heaviest).collect()
        out = []
        for k, step in enumerate(steps):
            mine = [r for r in rows if r.step == k]
            acting = [r for r in mine if r.acts]
            self.steps += [(self.algo, step, r.proc, r.work, r.sent, r.received) for r in acting]
            self.combined.append(sum(r.combined for r in acting))
            self.active.append(sum(r.on for r in acting))
            if degrees is not None:
                for name in loads:
                    w = max((r[f"_{name}"] for r in mine if r[f"_{name}"] is not None), default=None)
                    getattr(self, name).append((step, w.w if w else 0.0, w.id if w else None))
            out.append(sum(r.sent for r in acting))
        return out

    def repeat(self, step: int) -> None:
        """A round that costs what the one before it did."""
        if self.steps:
            last = self.steps[-1][1]
            self.steps += [(algo, step, *rest) for algo, at, *rest in self.steps if at == last]
        for loads in (self.worst, self.computed, self.stored):
            loads += [(step, *rest) for _, *rest in loads[-1:]]
        for counts in (self.combined, self.active):
            counts += counts[-1:]

    @property
    def rounds(self) -> int:
        return len({s[1] for s in self.steps})

    @property
    def messages(self) -> int:
        return sum(s[4] for s in self.steps)

    @property
    def work(self) -> int:
        return sum(s[3] for s in self.steps)

    def table(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.steps, ROUND)


def superstep_time(steps: DataFrame, g: float = 1.0, latency: float = 1.0) -> DataFrame:
    """(algo, step, time, fits_period): largest of work, g times traffic and the latency; and whether one period holds it."""
    x = steps.groupBy("algo", "step").agg(F.max("work").alias("w"), F.max(F.greatest("sent", "received")).alias("h"))
    return x.select("algo", "step", F.greatest("w", F.col("h") * g, F.lit(latency)).cast("double").alias("time"), ((F.col("w") <= latency) & (F.col("h") <= math.floor(latency / g))).alias("fits_period"))


def total_time(steps: DataFrame, g: float = 1.0, latency: float = 1.0) -> DataFrame:
    return superstep_time(steps, g, latency).groupBy("algo").agg(F.sum("time").alias("time"), F.count("*").alias("rounds"))


def time_processor_product(steps: DataFrame, p: int = 8, g: float = 1.0, latency: float = 1.0) -> DataFrame:
    return total_time(steps, g, latency).select("algo", "rounds", (F.col("time") * p).alias("product"))


def growth(points: DataFrame) -> DataFrame:
    """(algo, slope): slope of log(product / sequential) over log(n), of rows (algo, n, product, sequential)."""
    return points.groupBy("algo").agg(F.regr_slope(F.log(F.col("product") / F.col("sequential")), F.log("n")).alias("slope"))


def more_work(points: DataFrame, tolerance: float = 0.15) -> DataFrame:
    return growth(points).select("algo", "slope", (F.col("slope") > tolerance).alias("more_work"))


@dataclass
class Certificate:
    """The balance test: messages, compute and storage of each vertex within ``c`` times its degree, rounds within c log n."""

    storage_ok: bool
    compute_ok: bool
    messages_ok: bool
    rounds_ok: bool
    worst_ratio: float
    witness: int | None
    rounds: int
    compute_ratio: float = 0.0
    compute_witness: int | None = None
    storage_ratio: float = 0.0
    storage_witness: int | None = None

    @property
    def balanced(self) -> bool:
        return self.storage_ok and self.compute_ok and self.messages_ok and self.rounds_ok


def certificate(ledger: Ledger, n: int, c: float = 4.0) -> Certificate:
    sent, done, kept = (max(x, key=lambda w: w[1], default=(0, 0.0, None)) for x in (ledger.worst, ledger.computed, ledger.stored))
    return Certificate(kept[1] <= c, done[1] <= c, sent[1] <= c, ledger.rounds <= c * max(1.0, math.log2(max(n, 2))), *sent[1:], ledger.rounds, *done[1:], *kept[1:])
