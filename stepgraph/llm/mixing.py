"""Mixing sources to target weights by capped water-filling, in native DataFrame operations only.

A source's target is its share of a common water level by weight, but no more than ``epochs`` times its own size; what
a capped source leaves goes to the others by weight. The level has a closed form once sources are sorted by
size / weight: the first one at which the rest stay below their caps.

A source is then taken in whole passes and one last fractional pass: documents in the order of a seeded hash until the
target is met, the last of them cut at a word. The running sum is built from stretches of the hash's range, 256 of them or
more, so that a source with any share of the rows is spread over many keys of a bounded size.

Cases: a null or empty text has size 0 and is taken with 0 words; a null source is a source, the last; a source of size
0 has target 0; repeated rows are taken one by one; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import Scratch, broadcast_small, whole_rows

WORDS = r"[^\x20\x09-\x0D]+"
GAPPED = r"[\x20\x09-\x0D]*[^\x20\x09-\x0D]+"
#: Rows of one source are summed in stretches of about so many, 256 stretches at least.
STRETCH_ROWS = 500_000


def n_words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORDS)), F.lit(0)).cast("long")


def cyclic_weights(sources: DataFrame, weights: tuple[float, ...]) -> DataFrame:
    """Adds weight: the given ones in turn over the sources by code point, null last. One row a source."""
    place = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    return sources.withColumn("weight", F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (place % len(weights) + 1).cast("int")))


def water_fill(sources: DataFrame, epochs: int, total: Column | None = None) -> DataFrame:
    """Adds target to (source, source_size, weight). ``total``: words to mix, the sources' sum if not given."""
    cap = F.col("source_size").cast("double") * epochs
    every = Window.partitionBy()
    x = sources.withColumn("_cap", cap).withColumn("_total", total if total is not None else F.sum("source_size").over(every).cast("double"))
    order = Window.orderBy(F.col("_cap") / F.col("weight"), F.col("source").asc_nulls_last())
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    x = x.withColumn("_capped", F.coalesce(F.sum("_cap").over(before), F.lit(0.0))).withColumn("_open", F.sum("weight").over(every) - F.coalesce(F.sum("weight").over(before), F.lit(0.0)))
    x = x.withColumn("_level", (F.col("_total") - F.col("_capped")) / F.col("_open"))
    fits = F.when(F.col("_level") * F.col("weight") <= F.col("_cap"), F.col("_level"))
    level = F.first(fits, ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    return x.withColumn("target", F.when(level.isNull(), F.col("_cap")).otherwise(F.least(F.col("_cap"), level * F.col("weight")))).drop("_cap", "_total", "_capped", "_open", "_level")


def _key(source: Column) -> Column:
    return F.coalesce(F.concat(F.lit("s"), source), F.lit("n"))


def _turn(id_: Column, size: Column, seed: int) -> Column:
    """When a row's turn is in the last pass, by a seeded hash."""
    return F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(id_.cast("string"), F.lit("")), F.lit(":"), size.cast("string")).cast("binary"))


def mix(df: DataFrame, id_col: str, source_col: str, size: Column, weights: tuple[float, ...] | DataFrame, epochs: int = 3, seed: int = 0) -> DataFrame:
    """(id, source, size, source_size, target, whole, part, taken): a row is taken ``whole`` times, and its first
    ``part`` words once more. ``weights``: given in turn to the sources, or a table (source, weight)."""
    scratch = Scratch(df.sparkSession)
    rows = df.select(F.col(id_col).alias("_id"), F.col(source_col).alias("source"), size.alias("size"))
    rows = scratch.keep(rows.withColumns({"_key": _key(F.col("source")), "_turn": _turn(F.col("_id"), F.col("size"), seed)}))
    digits = 2
    while rows.count() > STRETCH_ROWS * 16**digits:
        digits += 1
    rows = rows.withColumn("_stretch", F.substring("_turn", 1, digits))
    stretches = scratch.keep(rows.groupBy("_key", "source", "_stretch").agg(F.sum("size").alias("_size")))
    sources = stretches.groupBy("_key", "source").agg(F.sum("_size").alias("source_size"))
    weighed = sources.join(weights, sources["source"].eqNullSafe(weights["source"])).select(sources["*"], weights["weight"].cast("double")) if isinstance(weights, DataFrame) else cyclic_weights(sources, weights)
    targets = water_fill(weighed, epochs).select("_key", "source_size", "target")
    ahead = F.coalesce(F.sum("_size").over(Window.partitionBy("_key").orderBy("_stretch").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    starts = stretches.withColumn("_ahead", ahead).join(targets, "_key").select("_key", "_stretch", "_ahead", "source_size", "target")
    inside = F.sum("size").over(Window.partitionBy("_key", "_stretch").orderBy("_turn", "size").rowsBetween(Window.unboundedPreceding, -1))
    x = rows.withColumn("_inside", F.coalesce(inside, F.lit(0))).join(starts, ["_key", "_stretch"])
    whole = F.when(F.col("source_size") == 0, 0).otherwise(F.floor(F.col("target") / F.col("source_size"))).cast("long")
    extra = F.floor(F.col("target") + 0.5).cast("long") - F.col("whole") * F.col("source_size")
    part = F.greatest(F.lit(0), F.least(F.col("size"), F.col("_extra") - F.col("_ahead") - F.col("_inside")))
    x = x.withColumn("whole", whole).withColumn("_extra", extra).withColumn("part", part.cast("long"))
    return x.select(F.col("_id").alias(id_col), "source", "size", "source_size", "target", "whole", "part", (F.col("whole") * F.col("size") + F.col("part")).cast("long").alias("taken"))


def mixed_rows(df: DataFrame, id_col: str, text_col: str, source_col: str, weights: tuple[float, ...], epochs: int = 3, seed: int = 0) -> DataFrame:
    """The mix itself: rows repeated as often as they are taken, with the columns they came with. A row that is taken in
    part has its text up to that word. The last pass ends in each source at one row, so a row is judged by its turn and its
    source's end, and no text moves. Rows that share an id and a size (or have no id) can end it together; these few are numbered."""
    scratch = Scratch(df.sparkSession)
    plan = mix(df, id_col, source_col, n_words(F.col(text_col)), weights, epochs, seed)
    at = F.struct("_turn", "_size")
    plan = scratch.keep(plan.select(_key(F.col("source")).alias("_key"), _turn(F.col(id_col), F.col("size"), seed).alias("_turn"), F.col("size").alias("_size"), "whole", "part"))
    ends = scratch.keep(plan.groupBy("_key").agg(F.max("whole").alias("whole"), F.max(F.when(F.col("part") > 0, at)).alias("_end")))
    n, full = ends.count(), F.col("part") == F.col("_size")
    last = plan.drop("whole").join(broadcast_small(ends, n), "_key").where(at == F.col("_end"))
    last = last.groupBy("_key").agg(F.count("*").alias("_tied"), F.count_if(full).alias("_full"), F.max(F.when(full, 0).otherwise(F.col("part"))).alias("_rest"))
    ends = scratch.keep(ends.join(last, "_key", "left"))
    scratch.drop(plan)
    whole = df.select(whole_rows(df), _key(F.col(source_col)).alias("_key"), F.col(id_col).alias("_id"), F.col(text_col).alias("_text"), n_words(F.col(text_col)).alias("_size"))
    x = whole.withColumn("_turn", _turn(F.col("_id"), F.col("_size"), seed)).join(broadcast_small(ends, n), "_key").withColumn("_nth", F.lit(1))
    if ends.where("_tied > 1").limit(1).count():
        tied = (at == F.col("_end")) & (F.col("_tied") > 1)
        several = x.where(tied).withColumn("_nth", F.row_number().over(Window.partitionBy("_key").orderBy(F.xxhash64("_text"))))
        x = x.where(~F.coalesce(tied, F.lit(False))).unionByName(several)
    size, nth = F.col("_size"), F.col("_nth")
    part = F.when(at < F.col("_end"), size).when(at == F.col("_end"), F.when(nth <= F.col("_full"), size).when(nth == F.col("_full") + 1, F.col("_rest")))
    x = x.withColumn("part", F.coalesce(part, F.lit(0)).cast("long")).where("whole > 0 or part > 0")
    # Each word with the gap before it: the first of these give the text back as it is.
    words = F.array_join(F.slice(F.regexp_extract_all("_text", F.lit(GAPPED), 0), 1, F.greatest(F.col("part"), F.lit(1)).cast("int")), "")
    cut = F.when(F.col("part") < F.col("_size"), words).otherwise(F.col("_text"))
    passes = F.col("whole") + F.when(F.col("part") > 0, 1).otherwise(0)
    x = x.withColumn("_pass", F.explode(F.sequence(F.lit(1).cast("long"), passes.cast("long"))))
    text = F.when(F.col("_pass") <= F.col("whole"), F.col("_text")).otherwise(cut)
    return x.select(*((text if c == text_col else F.col("_all").getField(c)).alias(c) for c in df.columns))
