"""Exact n-gram Jaccard join with token-combination prefixes, and the components of its links.

``prefix_index`` says how sets are indexed. Links are verified on whole sets, remade from texts; these are sets of 63-bit
hashes of the word n-grams, and that is what the join is exact about.

Pairs of an index entry's group are compared by what is known of them before any set moves: their sizes, how many entries
they share, and for wide sets (mostly frequent tokens, such as documents with one long passage in common) the parities of
their tokens in 256 buckets, as two sets differ in at least as many tokens as in parities. Large groups of pairs of frequent
tokens are looked at first, star-wise: each set meets one hub of its group, once a round, and the links found this way join
what belongs together. Then all pairs of each group that are not yet in one component are compared and, if they can link,
verified. No pair that could join two components is left out, and pairs inside one are not listed.

Sets are known by 8-byte row numbers; the index holds these and two counts, and parities stand in a table of their own.

Cases: a text without words (or null) has an empty set and is linked with nothing; with fewer words than n, the whole
sequence is one token; equal sets are one node; rows are linked by their texts, so ids may be null, repeated, or stand on
different texts; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Scratch, broadcast_small, small_batches, trimmed, whole_rows
from .components import components
from .prefix_index import CUT, FREQUENT, build, low_zone, lowest
from .shingles import Memo, in_steps, set_key, sets_of, token_set

#: Index groups above this meet a hub first; of smaller ones every pair is looked at.
BIG = 4 * FREQUENT
#: Rounds of hubs at most. They end sooner once they find nothing more, or few comparisons are left.
STAR_ROUNDS = 3


def _heads(texts: DataFrame, n: int, percent: int) -> DataFrame:
    """(_id, size, key, tokens) of (_id, _text), and other columns as they are: the set's 48-bit tokens of the low zone."""
    more = [c for c in texts.columns if c != "_text"]
    kinds = ", ".join(f"{c} {texts.schema[c].dataType.simpleString()}" for c in more)
    end = lowest(percent)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        memo = Memo()
        for b in in_steps(batches):
            sets = [token_set(text, n, memo) for text in b.column("_text").to_pylist()]
            low = pa.array([s[: int(np.searchsorted(s, end))] >> CUT for s in sets], pa.list_(pa.int64()))
            made = [pa.array([len(s) for s in sets], pa.int32()), pa.array([set_key(s) for s in sets], pa.binary()), low]
            yield pa.RecordBatch.from_arrays([*map(b.column, more), *made], [*more, "size", "key", "tokens"])

    return texts.mapInArrow(trimmed(run), f"{kinds}, size int, key binary, tokens array<long>")


def _order(*more: str) -> Column:
    """Rows by id, null ids last."""
    return F.struct(F.col("_id").isNull().alias("_none"), "_id", *more)


def _rows_and_tokens(heads: DataFrame, scratch: Scratch) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Rows (_id, _row, size, key, low, node, least) with the other columns of ``_heads``; tokens (node, first, tokens); copies
    (node, least) of the sets that several rows have. A set's node is the number of its first row, ``least`` that row's id."""
    known = heads.where("key is not null").groupBy("key").agg(F.count("*").alias("_n"), F.min(_order("_row")).alias("_first"))
    copies = scratch.keep(known.where("_n > 1").select("key", F.col("_first._row").alias("_node"), F.col("_first._id").alias("_least")))
    marked = heads.join(broadcast_small(copies, copies.count()), "key", "left")
    several = F.col("_node").isNotNull()
    node = F.when(F.col("key").isNotNull(), F.coalesce("_node", "_row"))
    least = F.when(several, F.col("_least")).otherwise(F.col("_id"))
    rows = marked.withColumns({"low": F.size("tokens"), "node": node, "least": least}).drop("tokens", "_node", "_least")
    first = marked.where(F.col("key").isNotNull() & (~several | (F.col("_node") == F.col("_row"))))
    return scratch.keep(rows), first.select(F.col("_row").alias("node"), F.lit(0).alias("first"), "tokens"), copies.select(F.col("_node").alias("node"), F.col("_least").alias("least"))


def _verified(pairs: DataFrame, texts: DataFrame, nodes: DataFrame, n: int, percent: int, scratch: Scratch) -> DataFrame:
    """(a, b, linked) of pairs of nodes."""
    wanted = scratch.keep(pairs.select(F.col("a").alias("node")).union(pairs.select("b")).distinct())
    named = nodes.select("node", "_id", "key").join(broadcast_small(wanted, wanted.count()), "node", "left_semi")
    sets = sets_of(texts, named, n, scratch)
    side = lambda k: sets.select(F.col("node").alias(k), F.col("tokens").alias(f"t{k}"))
    both = pairs.join(side("b"), "b").join(side("a"), "a").select("a", "b", "ta", "tb")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in in_steps(batches):
            linked = []
            for u, v in zip(batch.column("ta"), batch.column("tb"), strict=True):
                u, v = np.frombuffer(u.as_buffer(), np.int64), np.frombuffer(v.as_buffer(), np.int64)
                common = len(np.intersect1d(u, v, assume_unique=True))
                linked.append(100 * common >= percent * (len(u) + len(v) - common))
            yield pa.RecordBatch.from_arrays([batch.column("a"), batch.column("b"), pa.array(linked, pa.bool_())], ["a", "b", "linked"])

    out = scratch.keep(both.mapInArrow(trimmed(run), "a long, b long, linked boolean"))
    scratch.drop(sets)
    scratch.drop(wanted)
    return out


def _overlap(percent: int) -> Column:
    """Tokens that two linked sets have in common at least."""
    return F.ceil((F.col("na") + F.col("nb")) * percent / (100 + percent) - F.lit(1e-9))


def _shared(percent: int) -> Column:
    """Rare entries that two linked sets share at least, if any. A set whose entries are all rare, and end before the other's
    do, has all that it shares of them among the other's, and lacks no more of them than of its whole. Two sets with fewer
    rare tokens than that have all of them among their entries, and can share no more frequent ones than either has."""
    must = lambda size: size - F.ceil(size * percent / 100 - F.lit(1e-9)) + 1 - (size - _overlap(percent))
    a, b, fa, fb = must(F.col("na")), must(F.col("nb")), F.col("fa"), F.col("fb")
    least = F.when(fa.isNull() & fb.isNull(), F.least(a, b)).when(fa.isNull(), a).when(fb.isNull(), b)
    return F.greatest(F.lit(1), least.otherwise(_overlap(percent) - F.least(fa, fb)))


def _apart(a: str, b: str) -> Column:
    """Tokens that are in one of two sets alone, at least: an odd bucket of one and an even one of the other differ in one."""
    words = [F.bit_count(F.col(f"{a}.w{i}").bitwiseXOR(F.col(f"{b}.w{i}"))) for i in range(4)]
    return words[0] + words[1] + words[2] + words[3]


def _side(entries: DataFrame, k: str) -> DataFrame:
    """Entries as one side of pairs."""
    names = {"node": k, "component": f"c{k}", "size": f"n{k}", "often": f"f{k}", "parity": f"p{k}"}
    return entries.select("sig", *(F.col(c).alias(x) for c, x in names.items() if c in entries.columns))


def _close(percent: int) -> Column:
    """Pairs of two components, of sizes that a linked pair may have."""
    sizes = (F.col("na") * 100 >= F.col("nb") * percent) & (F.col("nb") * 100 >= F.col("na") * percent)
    return (F.col("ca") != F.col("cb")) & sizes


def _covered(percent: int) -> Column:
    """Pairs of wide sets whose frequent tokens and parities allow a link."""
    least = _overlap(percent)
    return (least <= F.least("fa", "fb")) & (_apart("pa", "pb") <= F.col("na") + F.col("nb") - 2 * least)


def _light(percent: int) -> Column:
    """Entries of sets that can be the one of two wide sets with fewer tokens of its own: linked sets whose rare entries don't
    meet have at least 2p / (100 + p) of the smaller one's tokens among its frequent ones."""
    return (F.col("sig") < 0) & (F.col("often") * (100 + percent) >= F.col("size") * (2 * percent))


class _Links:
    """What is known of links so far: pairs that were tried, links found, and components (node, component) of these."""

    def __init__(self, texts: DataFrame, nodes: DataFrame, n: int, percent: int, scratch: Scratch):
        self.texts, self.nodes, self.n, self.percent, self.scratch = texts, nodes, n, percent, scratch
        self.tried = self.found = self.comps = None

    def label(self, entries: DataFrame) -> DataFrame:
        """Entries with the component of their node."""
        if self.comps is None:
            return entries.withColumn("component", F.col("node"))
        known = self.comps.select("node", F.col("component").alias("_component"))
        out = entries.join(broadcast_small(known, known.count()), "node", "left")
        return out.withColumn("component", F.coalesce("_component", "node")).drop("_component")

    def try_pairs(self, pairs: DataFrame) -> int:
        """Verifies pairs (a, b) of two components that were not tried before; returns the number of links."""
        pairs = pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
        if self.comps is not None:
            rows = self.comps.count()
            side = lambda k: broadcast_small(self.comps.select(F.col("node").alias(k), F.col("component").alias(f"c{k}")), rows)
            apart = F.coalesce("ca", "a") != F.coalesce("cb", "b")
            pairs = pairs.join(side("a"), "a", "left").join(side("b"), "b", "left").where(apart).select("a", "b")
        if self.tried is not None:
            pairs = pairs.join(self.tried, ["a", "b"], "left_anti")
        pairs = self.scratch.keep(pairs)
        done = _verified(pairs, self.texts, self.nodes, self.n, self.percent, self.scratch)
        self.scratch.drop(pairs)
        links = done.where("linked").select("a", "b")
        self.tried = done.select("a", "b") if self.tried is None else self.tried.unionByName(done.select("a", "b"))
        self.found = links if self.found is None else self.found.unionByName(links)
        count = links.count()
        if count:
            old, self.comps = self.comps, components(self.found, self.scratch)
            if old is not None:
                self.scratch.drop(old)
        return count


def _through_hubs(entries: DataFrame, links: _Links, few: int) -> DataFrame:
    """Entries (sig, node, size, often, parity) of large groups, with components, of groups that hold several of these. Before
    that, links are sought from one hub a group, until fewer than ``few`` comparisons are left or a round finds none."""
    scratch, percent = links.scratch, links.percent
    light = _light(percent)
    for turn in range(STAR_ROUNDS + 1):
        at = links.label(entries.drop("component"))
        if links.comps is not None:  # read twice below, joined once
            at = scratch.keep(at)
        open_ = at.groupBy("sig").agg(F.min("component").alias("_x"), F.max("component").alias("_y"), F.count("*").alias("_n"), F.sum(light.cast("long")).alias("_light"))
        open_ = scratch.keep(open_.where("_x <> _y and _light > 0").select("sig", "_n", "_light"))
        left, groups = open_.agg(F.coalesce(F.sum(F.col("_n") * F.col("_light")), F.lit(0)), F.count("*")).first()
        old, entries = entries, scratch.keep(at.join(broadcast_small(open_.select("sig"), groups), "sig", "left_semi"))
        for table in (old, at, open_):
            scratch.drop(table)
        if left <= few or turn == STAR_ROUNDS:
            break
        # What a group has in common is frequent, so the set with the least besides is nearest to all; later, one of about the least.
        own = 1 - F.col("often") / F.col("size")
        order = F.struct(own if turn == 0 else F.floor(own * 16), F.xxhash64("node", F.lit(turn)))
        hub = F.struct(order.alias("o"), F.col("node").alias("a"), F.col("size").alias("na"), F.col("component").alias("ca"), F.col("often").alias("fa"), F.col("parity").alias("pa"))
        hubs = entries.where(light).groupBy("sig").agg(F.min(hub).alias("m")).select("sig", "m.a", "m.na", "m.ca", "m.fa", "m.pa")
        met = _side(entries, "b").join(broadcast_small(hubs, 4 * groups), "sig").where((F.col("a") != F.col("b")) & _close(percent) & _covered(percent))
        best = met.groupBy("b", "a").agg(F.count("*").alias("n")).groupBy("b").agg(F.max_by("a", "n").alias("a"))
        if not links.try_pairs(best):
            break
    return entries


def _pairs(rare: DataFrame, wide: DataFrame, percent: int) -> DataFrame:
    """(a, b) of entries that may be linked, of two components where these are known for their group: by rare tokens (sig, node, component, size, often), or by pairs of
    frequent ones (with parities besides)."""
    single = _side(rare, "a").join(_side(rare, "b"), "sig").where((F.col("a") < F.col("b")) & _close(percent))
    single = single.groupBy("a", "b", "na", "nb", "fa", "fb").agg(F.count("*").alias("n")).where(F.col("n") >= _shared(percent))
    both = _side(wide.where(_light(percent)), "a").join(_side(wide, "b"), "sig")
    both = both.where((F.col("a") != F.col("b")) & _close(percent) & _covered(percent))
    return single.select("a", "b").unionByName(both.select("a", "b"))


def links(df: DataFrame, id_col: str, text_col: str, n: int = 5, percent: int = 80, **more: Column) -> tuple[DataFrame, DataFrame, Scratch]:
    """Rows (_id, size, node, least) with ``more``, and a table (node, component_id, component) of the nodes that several rows or
    links have. component_id is the component's smallest id that is not null, which another component can have too; component
    is its own. least is the smallest id of the rows of a node."""
    if not 60 <= percent <= 100:
        raise ValueError("percent must be from 60 to 100")
    scratch = Scratch(df.sparkSession)
    small_batches(df.sparkSession)
    texts = df.select(F.col(id_col).alias("_id"), F.col(text_col).alias("_text"))
    heads = scratch.keep(_heads(texts.withColumns(more), n, percent).withColumn("_row", F.monotonically_increasing_id()))
    rows, tokens, copies = _rows_and_tokens(heads, scratch)
    nodes = rows.where("node = _row").select("node", "_id", "key", "size", "low")
    met = low_zone(tokens, nodes, percent, scratch)
    scratch.drop(heads)
    index, parities = build(met, nodes, texts, n, percent, scratch)
    scratch.drop(met)

    entries, rare = index.count(), index.where("sig >= 0")
    paired = index.where("sig < 0").join(broadcast_small(parities, 2 * parities.count()), "node")
    sizes = index.where("sig < 0").groupBy("sig").agg(F.count("*").alias("n"), F.max(_light(percent)).alias("light"))
    big = scratch.keep(sizes.where((F.col("n") > BIG) & F.col("light")).select("sig"))
    groups = big.count()
    known = _Links(texts, nodes, n, percent, scratch)
    large = _through_hubs(scratch.keep(paired.join(broadcast_small(big, groups), "sig", "left_semi")), known, 4 * entries)
    small = paired.join(broadcast_small(big, groups), "sig", "left_anti").withColumn("component", F.col("node"))
    known.try_pairs(_pairs(rare.withColumn("component", F.col("node")), small.unionByName(large.select(*small.columns)), percent))
    for old in (index, parities, big, large):
        scratch.drop(old)

    single = copies.select("node", F.col("least").alias("component_id"), F.col("node").alias("component"))
    if known.comps is None:
        return rows, single, scratch
    owned = scratch.keep(rows.where("node = _row").select("node", "least").join(broadcast_small(known.comps, known.comps.count()), "node"))
    named = owned.join(owned.groupBy("component").agg(F.min("least").alias("component_id")), "component").select("node", "component_id", "component")
    return rows, scratch.keep(single.join(named, "node", "left_anti").unionByName(named)), scratch


def near_duplicates(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", n: int = 5, percent: int = 80) -> DataFrame:
    """(id, n_shingles, component_id), one row per row: component_id is the smallest id that is not null and that links reach,
    and null only where all of these are."""
    rows, named, _ = links(df, id_col, text_col, n, percent)
    out = rows.select("_id", "size", "node").join(broadcast_small(named, named.count()), "node", "left")
    return out.select(F.col("_id").alias(id_col), F.col("size").cast("long").alias("n_shingles"), F.coalesce("component_id", "_id").alias("component_id"))


def keep_one(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", n: int = 5, percent: int = 80) -> DataFrame:
    """One row of each component, that of the smallest id that is not null, with the columns it came with. Rows without words
    all stay. A row is known by its id and its text's hash, as others can have its id; of equal ones that tie, one stays."""
    hashed = F.unhex(F.md5(F.col(text_col)))
    rows, named, scratch = links(df, id_col, text_col, n, percent, _hash=F.unhex(F.md5("_text")))
    held = scratch.keep(rows.join(broadcast_small(named, named.count()), "node").select("_id", "_hash", "component"))
    best = held.groupBy("component").agg(F.min(_order("_hash")).alias("_best"))
    stays = F.col("_id").eqNullSafe(F.col("_best._id")) & (F.col("_hash") == F.col("_best._hash"))
    judged = held.join(broadcast_small(best, held.count()), "component").groupBy(F.col("_id").alias("_of"), F.col("_hash").alias("_of_hash"), stays.alias("_stays"))
    judged = scratch.keep(judged.agg(F.count("*").alias("_n")))
    gone, twice = judged.where("not _stays"), judged.where("_stays and _n > 1")
    whole = df.select(whole_rows(df), F.col(id_col).alias("_id"), hashed.alias("_hash"))
    same = F.col("_id").eqNullSafe(F.col("_of")) & (F.col("_hash") == F.col("_of_hash"))
    out = whole.join(broadcast_small(gone, gone.count()), same, "left_anti")
    if again := twice.count():
        several = out.join(broadcast_small(twice, again), same, "left_semi").dropDuplicates(["_id", "_hash"])
        out = out.join(broadcast_small(twice, again), same, "left_anti").unionByName(several)
    return out.select("_all.*")
