"""Harmonic packing of token sequences.

A piece of length l belongs to the class of bins that hold ``capacity // l`` pieces each; a bin of a class is full when
it has that many. Documents are cut at the tops of the classes: whole bins first, then the largest floor(capacity / k)
that fits what is left, and so on, which takes at most four or five cuts; what is under ``SMALL`` is a class of its own by its
exact length. So a full bin of class k lacks less than k tokens. Bins are numbered by counts per class and stretch, and
so are filled by any number of workers on their own. The pieces that do not fill a bin (fewer than k per class, some
thousands at most, whatever the input) are packed best-fit-decreasing.

Cases: a null or empty text is its end token alone; repeated rows are packed one by one; an empty table gives an empty
result; texts are tokenised whole.
"""

from __future__ import annotations

import json
import struct
import zlib
from collections.abc import Iterator
from functools import cache, cached_property

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .binpack import best_fit_decreasing
from .common import Scratch, small_batches, trimmed

SMALL, STRETCHES = 32, 256
#: Pieces of one length are numbered in stretches of about so many, ``STRETCHES`` at least.
STRETCH_ROWS = 500_000


def cuts(n: int, capacity: int) -> list[int]:
    """Lengths of a document's pieces, in order."""
    out = [capacity] * (n // capacity)
    n %= capacity
    while n > SMALL:
        out.append(capacity // -(-capacity // n))
        n -= out[-1]
    return [*out, n] if n else out


class Encoder:
    """Token ids as little-endian 32-bit words. Whole texts go to the encoder at once: looking words up in a memo took longer, as
    many words of a text are rare."""

    def __init__(self, tokenizer: str, ranks: str, pattern: str):
        import base64

        import tiktoken

        table = {base64.b64decode(a): int(b) for a, b in (line.split() for line in open(ranks, "rb"))}
        self.fast = tiktoken.Encoding("packing", pat_str=pattern, mergeable_ranks=table, special_tokens={})
        self.tokenizer = tokenizer
        with open(tokenizer, encoding="utf-8") as f:
            self.special = [t["content"] for t in json.load(f).get("added_tokens") or ()]

    @cached_property
    def slow(self):
        """For the few texts that hold a special token."""
        from tokenizers import Tokenizer

        return Tokenizer.from_file(self.tokenizer)

    def ids(self, text: str) -> bytes:
        if any(s in text for s in self.special):
            got = self.slow.encode(text, add_special_tokens=False).ids
        else:
            got = self.fast.encode_ordinary(text)
        return struct.pack(f"<{len(got)}I", *got)


@cache
def encoder(tokenizer: str, ranks: str, pattern: str) -> Encoder:
    return Encoder(tokenizer, ranks, pattern)


def pieces(df: DataFrame, id_col: str, text_col: str, files: tuple[str, str, str], end_id: int, capacity: int) -> DataFrame:
    """(id, start, length, ids_crc32, doc_tokens). ``files``: tokenizer file, its rank file and its pattern."""
    small_batches(df.sparkSession)
    end = np.array([end_id], "<u4").tobytes()

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        enc, lengths = encoder(*files), {}
        for b in batches:
            rows: list[list] = [[], [], [], [], []]
            for doc, text in zip(b["_id"], b["_text"], strict=True):
                ids = (enc.ids(text) if text else b"") + end
                n, at = len(ids) // 4, 0
                if n not in lengths:
                    if len(lengths) > 50_000:
                        lengths.clear()
                    lengths[n] = cuts(n, capacity)
                view = memoryview(ids)
                for size in lengths[n]:
                    for col, v in zip(rows, (doc, at, size, zlib.crc32(view[4 * at : 4 * (at + size)]), n), strict=True):
                        col.append(v)
                    at += size
            yield pd.DataFrame(dict(zip((id_col, "start", "length", "ids_crc32", "doc_tokens"), rows, strict=True)))

    id_type = df.schema[id_col].dataType.simpleString()
    return df.select(F.col(id_col).alias("_id"), F.col(text_col).alias("_text")).mapInPandas(trimmed(run), f"`{id_col}` {id_type}, start long, length long, ids_crc32 long, doc_tokens long")


def harmonic(rows: DataFrame, order: list[str], capacity: int) -> DataFrame:
    """Adds sequence_id and offset to rows with a ``length`` of at most the capacity."""
    stretches = max(STRETCHES, -(-rows.count() // STRETCH_ROWS))
    rows = rows.withColumn("_s", F.pmod(F.xxhash64(*order), F.lit(stretches)).cast("int"))
    sizes = rows.groupBy("length", "_s").agg(F.count("*").alias("_n"))
    starts = sizes.select("length", "_s", F.coalesce(F.sum("_n").over(Window.partitionBy("length").orderBy("_s").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_start"))
    counts = {r[0]: r[1] for r in sizes.groupBy("length").agg(F.sum("_n")).collect()}  # at most one row a length
    base, at, tail = [], 0, []
    for length in sorted(counts, reverse=True):
        each = capacity // length
        base.append((length, each, at, counts[length] // each * each))
        at += counts[length] // each
        tail += [(length, j) for j in range(counts[length] // each * each, counts[length])]
    bins, _ = best_fit_decreasing([length for length, _ in tail], capacity)
    filled: dict[int, int] = {}
    plan = []
    for (length, j), b in zip(tail, bins, strict=True):
        plan.append((length, j, at + b, filled.get(b, 0)))
        filled[b] = filled.get(b, 0) + length
    spark = rows.sparkSession
    classes = F.broadcast(spark.createDataFrame(base, "length long, _each long, _base long, _full long"))
    rests = F.broadcast(spark.createDataFrame(plan, "length long, _j long, _bin long, _off long"))
    j = F.row_number().over(Window.partitionBy("length", "_s").orderBy(*order)) - 1
    x = rows.withColumn("_i", j).join(F.broadcast(starts), ["length", "_s"]).withColumn("_j", (F.col("_start") + F.col("_i")).cast("long"))
    x = x.join(classes, "length").join(rests, ["length", "_j"], "left")
    full = F.col("_j") < F.col("_full")
    seq = F.when(full, F.col("_base") + F.floor(F.col("_j") / F.col("_each"))).otherwise(F.col("_bin"))
    off = F.when(full, F.pmod(F.col("_j"), F.col("_each")) * F.col("length")).otherwise(F.col("_off"))
    return x.withColumns({"sequence_id": seq.cast("long"), "offset": off.cast("long")}).drop("_s", "_i", "_j", "_start", "_each", "_base", "_full", "_bin", "_off")


def pack(df: DataFrame, id_col: str, text_col: str, files: tuple[str, str, str], end_id: int = 1, capacity: int = 2048) -> DataFrame:
    """(id, start, length, ids_crc32, doc_tokens, sequence_id, offset), one row per piece."""
    rows = Scratch(df.sparkSession).keep(pieces(df, id_col, text_col, files, end_id, capacity))
    return harmonic(rows, [id_col, "start", "ids_crc32", "length"], capacity).select(id_col, "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")
