"""Sets of hashed word n-grams: made from texts in Arrow batches, and made again for the few sets that have to be compared."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, broadcast_small, trimmed

#: Words whose hashes a worker remembers at once, some 10 MB.
MEMO = 50_000
LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
MULS = [pow(0x9E3779B97F4A7C15, 2 * i + 1, 1 << 64) for i in range(64)]
#: Texts that a worker turns into sets at once.
STEP = 200


def mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


class Memo(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) >= MEMO:
            self.clear()
        h = xxhash.xxh3_64_intdigest(word)
        if len(word) <= 64:
            self[word] = h
        return h


def token_set(text: str | None, n: int, memo: Memo) -> np.ndarray:
    """Sorted distinct 63-bit hashes of the text's word n-grams; of all its words, if it has fewer."""
    words = text.encode("utf-8", "surrogatepass").translate(LOWER).split() if text else []
    if not words:
        return np.zeros(0, np.int64)
    w = np.fromiter(map(memo.__getitem__, words), np.uint64, len(words))
    k = min(n, len(w))
    h = np.full(len(w) - k + 1, k, np.uint64)
    for i in range(k):
        h = h + w[i : len(w) - k + 1 + i] * np.uint64(MULS[i])
    return np.unique((mixed(h) >> np.uint64(1)).astype(np.int64))


def set_key(s: np.ndarray) -> bytes | None:
    return xxhash.xxh3_128_digest(s.tobytes()) if len(s) else None


def in_steps(batches: Iterator[pa.RecordBatch], step: int = STEP) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for k in range(0, whole.num_rows, step):
            yield whole.slice(k, step)


def gathered(batches: Iterator[pa.RecordBatch], rows: int) -> Iterator[pa.RecordBatch]:
    """Batches put together until they have so many rows."""
    held: list[pa.RecordBatch] = []
    for b in batches:
        held.append(b)
        if sum(x.num_rows for x in held) >= rows:
            yield pa.concat_batches(held)
            held = []
    if held:
        yield pa.concat_batches(held)


def sets_of(texts: DataFrame, wanted: DataFrame, n: int, scratch: Scratch) -> DataFrame:
    """(node, tokens) of the sets that ``wanted`` (node, _id, key) names, made again from ``texts`` (_id, _text).

    Only ids are compared with all texts, and only the texts of these ids are read further. A row is taken for a node if
    its set has the node's key, so ids may be shared; where equal rows give a node's set twice, one is kept.
    """
    wanted = scratch.keep(wanted)
    rows = wanted.count()
    ids = broadcast_small(wanted.select(F.col("_id").alias("_wanted")).distinct(), rows)
    few = texts.join(ids, F.col("_id").eqNullSafe(F.col("_wanted")), "left_semi")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        memo = Memo()
        for b in in_steps(batches):
            sets = [token_set(t, n, memo) for t in b.column("_text").to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array([set_key(s) for s in sets], pa.binary()), pa.array([s.tobytes() for s in sets], pa.binary())], ["key", "tokens"])

    made = few.select("_text").mapInArrow(trimmed(run), "key binary, tokens binary")
    made = scratch.keep(made.join(broadcast_small(wanted.select("node", "key"), rows), "key").select("node", "tokens"))
    scratch.drop(wanted)
    if made.count() == rows:
        return made
    once = scratch.keep(made.groupBy("node").agg(F.first("tokens").alias("tokens")))
    scratch.drop(made)
    return once
