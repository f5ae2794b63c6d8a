"""Exact deduplication: group by a 128-bit content hash, compare bytes inside groups, keep one row of each.

Only hashes that occur more than once take their texts into a shuffle, where rows are grouped by (hash, text): partial
aggregation leaves one row of a text per task, however many copies there are, and texts that share a hash by accident
stay apart.

Cases: a null text counts as empty; repeated rows with one id are copies of each other and are marked alike; of rows
that tie on the id, all are kept or none; an empty table gives an empty result; a null id loses to any other.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Scratch, ascii_lower, whole_rows

#: More repeated hashes than this are joined by shuffle, not by broadcast (32 MB of keys).
BROADCAST_ROWS = 500_000


def normalised(text: Column) -> Column:
    return ascii_lower(F.coalesce(text, F.lit("")))


def mark_duplicates(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "min", content_hash=None) -> DataFrame:
    """(id, keep_id, group_size, kept, text_sha256), one row per row. ``keep``: the smallest or largest id of a group stays."""
    scratch = Scratch(df.sparkSession)
    content_hash = content_hash or (lambda text: F.unhex(F.md5(text.cast("binary"))))
    norm = normalised(F.col(text_col))
    given = df.select(F.col(id_col).alias("_id"), norm.alias("_text"))
    rows = scratch.keep(given.select("_id", content_hash(F.col("_text")).alias("_hash"), F.sha2(F.col("_text").cast("binary"), 256).alias("text_sha256")))
    repeated = scratch.keep(rows.groupBy("_hash").agg(F.count("*").alias("_n")).where("_n > 1").select("_hash"))
    few = repeated.count() <= BROADCAST_ROWS
    hint = F.broadcast if few else (lambda x: x)
    best = F.min if keep == "min" else F.max
    texts = given.withColumn("_hash", content_hash(F.col("_text"))).join(hint(repeated), "_hash", "left_semi")
    groups = texts.groupBy("_hash", "_text").agg(F.count("*").alias("_n"), best("_id").alias("_keep"), F.sha2(F.col("_text").cast("binary"), 256).alias("_sha"))
    groups = scratch.keep(groups.select("_hash", "_sha", "_n", "_keep"))
    clashes = groups.groupBy("_hash", "_sha").count().where("count > 1").limit(1).count()
    if clashes:  # two different texts with one hash and one SHA-256
        raise ValueError("texts differ under equal SHA-256")
    info = hint(groups.select("_hash", F.col("_sha").alias("text_sha256"), "_n", "_keep"))
    out = rows.join(info, ["_hash", "text_sha256"], "left")
    keep_id, size = F.coalesce("_keep", "_id"), F.coalesce("_n", F.lit(1))
    return out.select(F.col("_id").alias(id_col), keep_id.alias("keep_id"), size.cast("long").alias("group_size"), keep_id.eqNullSafe(F.col("_id")).alias("kept"), "text_sha256")


def drop_duplicates(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "min") -> DataFrame:
    """The rows that stay, with the columns they came with; of repeated rows with one id one stays."""
    scratch = Scratch(df.sparkSession)
    sha = lambda text: F.sha2(normalised(text).cast("binary"), 256)
    copies = mark_duplicates(df, id_col, text_col, keep).where("group_size > 1")
    copies = scratch.keep(copies.select(F.col(id_col).alias("_of"), "kept", F.col("text_sha256").alias("_of_sha")))
    ids = scratch.keep(copies.groupBy("_of").agg(F.max("kept").alias("_kept"), F.count("*").alias("_rows")))
    hint = F.broadcast if ids.count() <= BROADCAST_ROWS else (lambda x: x)
    whole = df.select(whole_rows(df), F.col(id_col).alias("_id"), F.col(text_col).alias("_text"))
    marked = whole.join(hint(ids), F.col("_id").eqNullSafe(F.col("_of")), "left").drop("_of")
    single = marked.where("_rows is null or (_kept and _rows = 1)").select("_all")
    # An id that stands on several rows is settled row by row, on its text.
    several = marked.where("_rows > 1 or (_rows = 1 and not _kept)").select("_all", "_id", sha(F.col("_text")).alias("_sha"))
    states = copies.groupBy("_of", "_of_sha").agg(F.max("kept").alias("_stays"))
    settled = several.join(hint(states), F.col("_id").eqNullSafe(F.col("_of")) & (F.col("_sha") == F.col("_of_sha")), "left")
    alone = settled.where("_stays is null").select("_all")
    one = settled.where("_stays").dropDuplicates(["_id", "_sha"]).select("_all")
    return single.unionByName(alone).unionByName(one).select("_all.*")
