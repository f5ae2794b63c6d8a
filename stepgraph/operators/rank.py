"""Link ranking by power iteration."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..cost import Ledger
from ..engine import Rounds
from ..model import Graph


def pagerank(g: Graph, alpha: float = 0.85, iters: int = 30, tol: float | None = None, dangling: str = "leak", ledger: Ledger | None = None) -> DataFrame:
    """(id, rank). ``alpha`` weighs what comes over links. What a vertex without out-links has is lost ("leak") or
    spread over all ("spread"). ``tol``: stop once ranks change by less in sum, in at most ``iters`` rounds."""
    rounds = Rounds(g.spark, ledger)
    e = g.simple().arcs().select("src", "dst")
    out = e.groupBy("src").agg(F.count("*").alias("deg"))
    arcs = rounds.keyed(e.join(out, "src"), "src")
    n = g.vertices.count()
    degrees = rounds.cut(g.degrees())[0] if ledger else None
    base = g.vertices.select("id").join(out.withColumnRenamed("src", "id"), "id", "left")
    stuck = F.sum(F.when(F.col("deg").isNull(), F.col("rank")))
    state, seen = rounds.cut(base.select("id", F.lit(1.0 / n if n else 0.0).alias("rank"), "deg"), lost=stuck)
    kept = state
    for k in range(iters):
        mail = arcs.join(state.select(F.col("id").alias("src"), "rank"), "src")
        if ledger and k:
            ledger.repeat(k)
        elif ledger:  # every arc carries a message in every round
            ledger.record(k, mail.select("src", "dst"), degrees)
        got = mail.groupBy(F.col("dst").alias("id")).agg(F.sum(F.col("rank") / F.col("deg")).alias("s"))
        lost = seen["lost"] if dangling == "spread" else 0.0
        new = state.join(got, "id", "left").select("id", (F.lit((1 - alpha) / n) + alpha * (F.coalesce("s", F.lit(0.0)) + lost / n)).alias("rank"), "deg", F.col("rank").alias("old"))
        new, seen = rounds.cut(new, kept, delta=F.sum(F.abs(F.col("rank") - F.col("old"))), lost=stuck)
        kept, state = new, new.drop("old")
        rounds.next()
        if tol is not None and seen["delta"] < tol:
            break
    return state.select("id", "rank")
