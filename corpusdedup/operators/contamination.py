"""Overlap of a corpus with test items, by shared shingles: near-duplicates and contained passages."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusdedup.functions.hashing import codes_of
from corpusdedup.plans.shared import spread

#: Characters of items that one pass over the documents looks up, about; more items take more passes.
PROBES = 1 << 21
_MIX = 0x9E3779B97F4A7C15


def gram_hashes(text: str, k: int) -> np.ndarray:
    """The distinct 64-bit hashes of a text's k-grams of characters, ascending."""
    codes = codes_of(text).astype(np.uint64)
    if len(codes) < k:
        return np.zeros(0, dtype=np.uint64)
    h = np.zeros(len(codes) - k + 1, dtype=np.uint64)
    for j in range(k):
        h = (h ^ codes[j : j + len(h)]) * np.uint64(_MIX)
        h ^= h >> np.uint64(29)
    return np.unique(h)


@dataclass
class Probes:
    """Hashes to look up, ascending; each one's items; and how many of its hashes an item needs."""

    hashes: np.ndarray
    many: np.ndarray
    first: np.ndarray
    items: np.ndarray
    need: np.ndarray
    ids: list

    def met(self, text: str, k: int) -> list:
        """Ids of the items that have enough of their probes in the text."""
        own = gram_hashes(text, k)
        at = np.searchsorted(self.hashes, own)
        at = at[self.hashes[np.minimum(at, len(self.hashes) - 1)] == own] if len(self.hashes) else at[:0]
        n = self.many[at]
        which = self.items[np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n) + np.repeat(self.first[at], n)]
        hits = np.bincount(which, minlength=len(self.need))
        return [self.ids[i] for i in np.flatnonzero(hits >= self.need).tolist()]


def probes_of(texts: list[tuple[object, str]], k: int, least: float) -> Probes:
    """Of each item its hashes that fewest items share, as many as leave no document out.

    A document that has enough of an item lacks at most ``miss`` of its shingles, so of any ``2 miss + 1`` it has more than
    ``miss``, and of all of them it has ``total - miss``.
    """
    texts = [(i, own) for i, t in texts if len(own := gram_hashes(t, k))]
    every, number, df = np.unique(np.concatenate([x for _, x in texts]) if texts else np.zeros(0, np.uint64), return_inverse=True, return_counts=True)
    hashes, items, need, at = [], [], [], 0
    for n, (_, own) in enumerate(texts):
        mine = number[at : at + len(own)]
        at += len(own)
        miss = len(own) - int(np.ceil(len(own) * least - 1e-9))
        asked = min(len(own), 2 * miss + 1)
        hashes.append(mine[np.argsort(df[mine], kind="stable")[:asked]]), items.append(np.full(asked, n)), need.append(asked - miss)
    which = np.concatenate(hashes) if hashes else np.zeros(0, np.int64)
    order = np.argsort(which, kind="stable")
    found, many = np.unique(which, return_counts=True)
    return Probes(every[found], many, np.cumsum(many) - many, np.concatenate(items)[order] if items else which, np.array(need, dtype=np.int64), [i for i, _ in texts])


def gram_set(text: str, k: int) -> set[str]:
    return {text[i : i + k] for i in range(len(text) - k + 1)}


def contained_items(docs: DataFrame, items: DataFrame, k: int = 5, least: float = 0.8, probes: int = PROBES) -> DataFrame:
    """doc_id, item_id, common, total, containment: the share of an item's distinct shingles that a document has.

    One pass over the documents for every ``probes`` characters of items (about) finds candidates by hashes and counts them in
    full, on the shingles themselves, so hashes that collide do no harm and no pair is lost.
    """
    own = spread(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").where("text is not null"))
    items = items.select(F.col("item_id").cast("long").alias("item_id"), "text").where("text is not null")
    held = items.agg(F.sum(F.char_length("text"))).first()[0] or 0
    passes = -(-held // probes) or 1
    spark, found = docs.sparkSession, None
    for n in range(passes):
        some = {r["item_id"]: r["text"] for r in items.where(F.pmod(F.xxhash64("item_id"), F.lit(passes)) == n).toLocalIterator()}
        shared = spark.sparkContext.broadcast((probes_of(list(some.items()), k, least), some))

        def run(batches: Iterable[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            asked, texts = shared.value
            sets: dict[int, set[str]] = {}
            for batch in batches:
                rows: list[tuple[int, int, int, int]] = []
                for d, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                    met = asked.met(t, k)
                    grams = gram_set(t, k) if met else set()
                    for i in met:
                        if i not in sets:
                            sets[i] = gram_set(texts[i], k)
                        common = len(sets[i] & grams)
                        if common / len(sets[i]) >= least:
                            rows.append((d, i, common, len(sets[i])))
                yield pa.RecordBatch.from_arrays([pa.array([r[j] for r in rows], pa.int64()) for j in range(4)], names=["doc_id", "item_id", "common", "total"])

        met = own.mapInArrow(run, "doc_id long, item_id long, common long, total long")
        found = met if found is None else found.union(met)
    return found.withColumn("containment", F.col("common") / F.col("total"))
