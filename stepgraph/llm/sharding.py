"""Sharding by best-fit-decreasing bin packing of indivisible groups (equal texts).

Groups of one size are interchangeable, so what is packed are the distinct sizes with their counts, whole and at once: no
more than sqrt(2 x bytes) of them, and in practice as many as texts have lengths. The packing says how many groups of each
size every shard takes; groups then take these places by their number within their size.

Cases: a null text weighs one byte, like an empty one, and groups with it; repeated rows are one group and have slots of
their own; an empty table gives an empty result; a null id is kept as it is. A group that outweighs an even share makes
its shard as large as it is, and the others share the rest; with a capacity, a group above it has a shard of its own.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .binpack import counts_into_bins, pack_counts
from .common import Scratch, broadcast_small

#: Rows that share a shard or a size are numbered in stretches of about so many.
STRETCH_ROWS = 500_000


def text_size(text: Column) -> Column:
    return F.coalesce(F.octet_length(text), F.lit(0)).cast("long") + 1


def _runs(sizes: DataFrame, shards: int | None, capacity: int | None) -> DataFrame:
    """(size, firsts, shards) of (size, count): the shards that take groups of a size, and the first group that each takes."""

    def pack(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        items = sorted(((s, c) for b in batches for s, c in zip(b["size"].tolist(), b["count"].tolist(), strict=True)), reverse=True)
        runs = counts_into_bins(items, shards) if shards else pack_counts(items, capacity)[0]
        by: dict[int, tuple[list[int], list[int]]] = {}
        for size, first, b in runs:
            firsts, bins = by.setdefault(size, ([], []))
            firsts.append(first)
            bins.append(b)
        if by:
            yield pd.DataFrame({"size": list(by), "firsts": [x for x, _ in by.values()], "shards": [x for _, x in by.values()]})

    return sizes.repartition(1).mapInPandas(pack, "size long, firsts array<long>, shards array<int>")


def shard_groups(df: DataFrame, id_col: str, text_col: str, shards: int | None = None, capacity: int | None = None) -> DataFrame:
    """(id, size, text_crc32, group_key, shard, slot): either into ``shards`` even ones or into few of ``capacity`` bytes."""
    if (shards is None) == (capacity is None):
        raise ValueError("give either shards or capacity")
    scratch = Scratch(df.sparkSession)
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = df.select(F.col(id_col).alias("_id"), text_size(F.col(text_col)).alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.xxhash64(text).alias("group_key"))
    rows = scratch.keep(rows)
    groups = scratch.keep(rows.groupBy("group_key").agg(F.sum("size").alias("bytes")))
    sizes = groups.groupBy(F.col("bytes").alias("size")).count()
    runs = scratch.keep(_runs(sizes, shards, capacity))
    numbered = with_slots(groups, "bytes", ["group_key"], groups.count(), "nth")
    placed = numbered.join(broadcast_small(runs.withColumnRenamed("size", "bytes"), runs.count()), "bytes")
    turn = F.size(F.filter("firsts", lambda first: first <= F.col("nth")))
    placed = scratch.keep(placed.select("group_key", F.element_at("shards", turn).alias("shard")))
    put = rows.join(broadcast_small(placed, placed.count()), "group_key")
    return with_slots(put, "shard", ["_id", "text_crc32"], rows.count(), "slot", 64).select(F.col("_id").alias(id_col), "size", "text_crc32", "group_key", "shard", "slot")


def with_slots(rows: DataFrame, by: str, order: list[str], n: int, name: str, least: int = 1) -> DataFrame:
    """Adds ``name``: gapless from 0 in each value of ``by``. Rows are numbered in hashed stretches, whose sizes give each its
    start."""
    stretches = max(least, -(-n // STRETCH_ROWS))
    rows = rows.withColumn("_s", F.pmod(F.xxhash64(*order), F.lit(stretches)))
    sizes = rows.groupBy(by, "_s").agg(F.count("*").alias("_n"))
    before = Window.partitionBy(by).orderBy("_s").rowsBetween(Window.unboundedPreceding, -1)
    starts = sizes.select(by, "_s", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_start"))
    local = F.row_number().over(Window.partitionBy(by, "_s").orderBy(*order))
    numbered = rows.withColumn("_i", local).join(starts, [by, "_s"])
    return numbered.withColumn(name, (F.col("_start") + F.col("_i") - 1).cast("long")).drop("_s", "_i", "_start")
