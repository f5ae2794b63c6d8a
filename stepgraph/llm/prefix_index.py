"""The index of the n-gram join: token-combination prefixes of sets.

Tokens are ordered globally: rare ones first, then frequent ones, each by hash. If x and y reach the threshold t, x lacks at
most m = |x| - ceil(t |x|) of its tokens in y; so among the first tokens of x, once more than m of them are counted, y has
one. Frequent tokens fall into classes, and a class of k tokens counts as k - 1, for which the prefix is extended: then x and
y share a rare token of the prefix or two tokens of one class. So rare tokens are indexed alone and frequent ones in pairs of
their class. The number of classes follows the size of the set, which keeps the pairs about as many as the tokens; sets near
the border of two sizes are indexed under both, so linked sets meet.

Which tokens are frequent is counted in two zones of the hash range. The low zone holds a little more of each set than its
prefix needs; its tokens are counted over all sets. Sets with rare tokens enough in it are indexed by these, and never look
further. The others, called wide, are made again whole, and tokens of the high zone are counted over them alone. So every
token has one flag wherever the index asks for it, and most of the tokens are never moved. What is frequent decides how sets
are indexed, never whether they are. Tokens are cut to 48 bits here: a collision makes two sets meet that share nothing, and
sets are verified whole.

A token's occurrences meet once, by a shuffle. Before it, an Arrow batch's tokens with more than ``FREQUENT`` occurrences
there are frequent for certain: the batch sends one marker for each and spreads the occurrences by their sets. So a token
that most sets have reaches a task as some rows a batch, not as a row a set.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import Scratch, broadcast_small, trimmed
from .shingles import MULS, gathered, in_steps, mixed, sets_of

#: A token in more sets than this is frequent.
FREQUENT = 8
#: Share of the hash range that is the low zone; a prefix at 80 % needs 20 % of a set.
ZONE = 0.28
CUT = 15
#: Sets whose tokens are counted together before they are sent.
STEP = 4000


def lowest(percent: int) -> int:
    """The low zone's end, as a 63-bit hash."""
    return int((ZONE + (80 - percent) / 100) * (1 << 63)) if percent < 80 else int(ZONE * (1 << 63))


def missing(size: int, percent: int) -> int:
    """Most tokens that a set may lack in another that it is linked with."""
    return size + (-percent * size) // 100


def need(size: str, percent: int) -> Column:
    """Rare tokens that a prefix of rare ones has."""
    return F.expr(f"{size} - cast((cast({size} as long) * {percent} + 99) div 100 as int) + 1")


def _occurrences(sets: DataFrame) -> DataFrame:
    """(token, node, pos) of (node, first, tokens), pos counted from ``first``. Where a batch finds a token frequent, its pos
    is -1 - pos, and a row with null node and pos marks it for the others."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in gathered(batches, STEP):
            tokens = b.column("tokens")
            flat, sizes = tokens.flatten().to_numpy(zero_copy_only=False), tokens.value_lengths().to_numpy(zero_copy_only=False)
            node = np.repeat(b.column("node").to_numpy(zero_copy_only=False), sizes)
            pos = np.arange(len(flat)) - np.repeat(np.cumsum(sizes) - sizes - b.column("first").to_numpy(zero_copy_only=False), sizes)
            known, which, counts = np.unique(flat, return_inverse=True, return_counts=True)
            hot = counts > FREQUENT
            marks = pa.nulls(int(hot.sum()), pa.int64())
            pos = np.where(hot[which], -1 - pos, pos)
            columns = pa.concat_arrays([pa.array(flat), pa.array(known[hot])]), pa.concat_arrays([pa.array(node), marks]), pa.concat_arrays([pa.array(pos), marks])
            yield pa.RecordBatch.from_arrays([c.cast(k) for c, k in zip(columns, (pa.int64(), pa.int64(), pa.int32()), strict=True)], ["token", "node", "pos"])

    return sets.select("node", "first", "tokens").mapInArrow(trimmed(run), "token long, node long, pos int")


def shared_tokens(sets: DataFrame) -> DataFrame:
    """(node, pos, frequent, token) of the tokens that at least two of the sets (node, first, tokens) have."""
    hot = F.col("pos") < 0
    count = F.sum(F.when(F.col("node").isNull(), FREQUENT + 1).otherwise(1)).over(Window.partitionBy("token", F.when(hot, F.col("node"))))
    met = _occurrences(sets).withColumn("count", count).where("node is not null and (pos < 0 or count > 1)")
    return met.select("node", F.when(hot, -1 - F.col("pos")).otherwise(F.col("pos")).alias("pos"), (hot | (F.col("count") > FREQUENT)).alias("frequent"), "token")


def classes_of(size: int, percent: int) -> list[int]:
    """Numbers of classes under which a set's frequent tokens are paired: by its own size and by the largest that could link."""
    return sorted({max(1, 1 << max(0, s.bit_length() - 3)) for s in (size, size * 100 // percent)})


def token_pairs(often: np.ndarray, lack: int, size: int, percent: int) -> list[np.ndarray]:
    """Entries (below 0) of a set's frequent tokens in order, once its rare ones are ``lack`` short of a prefix."""
    out = []
    for classes in classes_of(size, percent):
        group = ((often.astype(np.uint64) * np.uint64(0x2545F4914F6CDD1D)) >> np.uint64(33)) % np.uint64(classes)
        by: dict[int, list[int]] = {}
        pairs, worth = [], 0
        for t, g in zip(often.tolist(), group.tolist(), strict=True):
            before = by.setdefault(g, [])
            pairs += [(s, t) for s in before]
            worth += bool(before)
            before.append(t)
            if worth == lack:
                break
        if pairs:
            p = np.array(pairs, np.int64).astype(np.uint64)
            h = p[:, 0] * np.uint64(MULS[0]) + p[:, 1] * np.uint64(MULS[1]) + np.uint64(classes)
            out.append(-1 - (mixed(h) >> np.uint64(1)).astype(np.int64))
    return out


PARITY = pa.struct([(f"w{i}", pa.int64()) for i in range(4)])


def _parity(s: np.ndarray) -> dict[str, int]:
    """Whether the set has an odd number of tokens in each of 256 buckets, as four words."""
    bits = np.packbits(np.bincount(s & 255, minlength=256).astype(np.uint8) & 1, bitorder="little").view(np.int64)
    return {f"w{i}": int(w) for i, w in enumerate(bits)}


def _high_parts(sets: DataFrame, end: int) -> DataFrame:
    """(node, first, tokens, parity) of whole sets (node, tokens): their 48-bit tokens of the high zone, and where these begin."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in in_steps(batches):
            whole = [np.frombuffer(t.as_buffer(), np.int64) for t in b.column("tokens")]
            first = [int(np.searchsorted(s, end)) for s in whole]
            high = pa.array([s[i:] >> CUT for s, i in zip(whole, first, strict=True)], pa.list_(pa.int64()))
            yield pa.RecordBatch.from_arrays([b.column("node"), pa.array(first, pa.int32()), high, pa.array([_parity(s) for s in whole], PARITY)], ["node", "first", "tokens", "parity"])

    return sets.mapInArrow(trimmed(run), "node long, first int, tokens array<long>, parity struct<w0: long, w1: long, w2: long, w3: long>")


def _wide_entries(met: DataFrame, percent: int) -> DataFrame:
    """(node, size, often, sigs) of (node, size, met), met the set's shared tokens by pos. often: the set's frequent tokens, or
    null where its entries are rare tokens alone."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in in_steps(batches):
            flat = b.column("met").flatten()
            pos, frequent, token = (flat.field(k).to_numpy(zero_copy_only=False) for k in ("pos", "frequent", "token"))
            sigs, often, at = [], [], 0
            for size, n in zip(b.column("size").to_pylist(), b.column("met").value_lengths().to_pylist(), strict=True):
                p, f, t = pos[at : at + n], frequent[at : at + n], token[at : at + n]
                at += n
                enough, common = missing(size, percent) + 1, int(f.sum())
                out, short = [t[~f & (p - np.cumsum(f) < enough)]], enough - (size - common)
                if short > 0:
                    out += token_pairs(t[f], short, size, percent)
                sigs.append(np.unique(np.concatenate(out)))
                often.append(common if short > 0 else None)
            yield pa.RecordBatch.from_arrays([b.column("node"), b.column("size"), pa.array(often, pa.int32()), pa.array(sigs, pa.list_(pa.int64()))], ["node", "size", "often", "sigs"])

    return met.select("node", "size", "met").mapInArrow(trimmed(run), "node long, size int, often int, sigs array<long>")


def low_zone(heads: DataFrame, nodes: DataFrame, percent: int, scratch: Scratch) -> DataFrame:
    """(node, size, pos, _before, frequent, token, wide) of the low zone's shared tokens: how many frequent ones the set has up
    to this one, and whether rare ones are too few there.

    heads: (node, first, tokens), the low zone of each set as 48-bit tokens; nodes: (node, _id, key, size, low), low the number
    of these.
    """
    before = Window.partitionBy("node").orderBy("pos").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    flag = F.col("frequent").cast("int")
    met = shared_tokens(heads).join(nodes.select("node", "size", "low"), "node")
    met = met.withColumn("_before", F.sum(flag).over(before)).withColumn("_often", F.sum(flag).over(Window.partitionBy("node")))
    wide = (F.col("low") - F.col("_often") < need("size", percent)).alias("wide")
    return scratch.keep(met.select("node", "size", "pos", "_before", "frequent", "token", wide))


def build(met: DataFrame, nodes: DataFrame, texts: DataFrame, n: int, percent: int, scratch: Scratch) -> tuple[DataFrame, DataFrame]:
    """Index (sig, node, size, often) and parities (node, parity) of the wide sets, from ``low_zone``. sig is a rare token (0 or
    more) or a pair of frequent ones (below 0)."""
    narrow = met.where(~F.col("wide") & ~F.col("frequent") & (F.col("pos") - F.col("_before") < need("size", percent)))

    # Sets that share no token of the low zone are wide if it holds too few of theirs.
    wide = scratch.keep(met.where("wide").select("node").union(nodes.where(F.col("low") < need("size", percent)).select("node")).distinct())
    rows = wide.count()
    sets = sets_of(texts, nodes.join(broadcast_small(wide, rows), "node", "left_semi").select("node", "_id", "key"), n, scratch)
    high = scratch.keep(_high_parts(sets, lowest(percent)))
    scratch.drop(sets)
    columns = "node", "pos", "frequent", "token"
    both = met.where("wide").select(*columns).unionByName(shared_tokens(high).select(*columns))
    grouped = both.groupBy("node").agg(F.sort_array(F.collect_list(F.struct("pos", "frequent", "token"))).alias("met")).join(nodes.select("node", "size"), "node")
    entries = _wide_entries(grouped, percent).select(F.explode("sigs").alias("sig"), "node", "size", "often")
    index = scratch.keep(narrow.select(F.col("token").alias("sig"), "node", "size", F.lit(None).cast("int").alias("often")).unionByName(entries))
    parities = scratch.keep(high.select("node", "parity"))
    for old in (wide, high):
        scratch.drop(old)
    return index, parities
