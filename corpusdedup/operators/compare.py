"""Comparison inside buckets: all pairs in tiles, with an early exit, or against an anchor."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusdedup.config import DedupConfig
from corpusdedup.operators.graph import connected_components, local_forest
from corpusdedup.plans.shared import fitted, materialise

TILE, CHUNK = 256, 32


def tile_matches(a: np.ndarray, b: np.ndarray, least: int, early_exit: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row of a, row of b, matching entries) of all pairs with at least ``least``.

    With the early exit, pairs that miss too many of the first entries are not looked at again; none is lost by that.
    """
    n = a.shape[1]
    first = min(CHUNK, n) if early_exit else n
    count = np.zeros((len(a), len(b)), dtype=np.int16)
    for k in range(first):
        count += a[:, k, None] == b[None, :, k]
    i, j = np.nonzero(count >= least - (n - first))
    found = count[i, j].astype(np.int64)
    for k in range(first, n, CHUNK):
        found += (a[i, k : k + CHUNK] == b[j, k : k + CHUNK]).sum(axis=1)
        keep = found >= least - max(0, n - k - CHUNK)
        i, j, found = i[keep], j[keep], found[keep]
    return i, j, found


def all_pairs(ids: np.ndarray, sig: np.ndarray, cfg: DedupConfig, part: np.ndarray | None = None, tile: int = TILE, early_exit: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """u < v and their matches, over the upper triangle of one bucket, or between two of its sub-units (``part`` tells them apart)."""
    out: list[tuple[np.ndarray, ...]] = []
    own = [np.arange(len(ids))] * 2 if part is None or (part == part[0]).all() else [np.flatnonzero(part == part.min()), np.flatnonzero(part != part.min())]
    same = own[0] is own[1]
    for x in range(0, len(own[0]), tile):
        for y in range(x if same else 0, len(own[1]), tile):
            r, c = own[0][x : x + tile], own[1][y : y + tile]
            i, j, n = tile_matches(sig[r], sig[c], cfg.min_matches, early_exit)
            if same and x == y:
                keep = i < j
                i, j, n = i[keep], j[keep], n[keep]
            out.append((ids[r[i]], ids[c[j]], n))
    if not out:
        return ids[:0], ids[:0], np.zeros(0, np.int64)
    u, v, n = map(np.concatenate, zip(*out))
    real = u != v
    u, v, n = u[real], v[real], n[real]
    return np.minimum(u, v), np.maximum(u, v), n


def against_anchor(anchor: int, anchor_sig: np.ndarray, ids: np.ndarray, sig: np.ndarray, cfg: DedupConfig, verify: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Pairs of the anchor with other members of its bucket, verified on the full signature or taken as they are."""
    n = (sig == anchor_sig).sum(axis=1)
    keep = (ids != anchor) & ((n >= cfg.min_matches) | (not verify))
    return np.full(int(keep.sum()), anchor), ids[keep], n[keep]


def oversize_buckets(rows: DataFrame, cfg: DedupConfig) -> DataFrame:
    """band, bucket, n and least id of the buckets of more than ``d_max`` rows."""
    sizes = rows.groupBy("band", "bucket").agg(F.count("*").alias("n"), F.min("doc_id").alias("head"))
    return materialise(sizes.where(F.col("n") > cfg.d_max), "oversize")


#: Rows of a bucket that travel together, in whole sub-units: 2 MB of signatures of 128 entries.
HELD_ROWS = 1 << 12


def _units(rows: DataFrame, cfg: DedupConfig, large: DataFrame | None, together: int = 1) -> DataFrame:
    """Add ``units`` (of the row's bucket) and ``unit`` (the row's own): parts of about ``d_max`` rows by a hash of doc_id, so many ``together``.

    ``n``, if it is a column, is the size of the row's bucket; else sizes are looked up in ``large``.
    """
    if "n" not in rows.columns:
        large = oversize_buckets(rows, cfg) if large is None else large
        rows = rows.join(fitted(large.select("band", "bucket", "n"), 32), ["band", "bucket"], "left")
    units = F.ceil(F.coalesce("n", F.lit(1)) / (cfg.d_max * together)).cast("int")
    return rows.withColumn("units", units).withColumn("unit", F.pmod(F.xxhash64("doc_id"), F.col("units")).cast("int"))


def split_oversize(rows: DataFrame, cfg: DedupConfig, large: DataFrame | None = None) -> DataFrame:
    """Add ``unit``, ``bi``, ``bj``: buckets of more than ``d_max`` rows are cut in sub-units.

    ``block_pairs`` sends a row to every pair of sub-units that holds its own, so no pair is lost; sub-units that a task can hold
    together travel as one, so a row has no copy for each other sub-unit of its bucket.  ``independent`` compares inside sub-units only.
    """
    if cfg.oversize == "independent":
        own = _units(rows, cfg, large)
        return own.withColumn("bi", F.col("unit")).withColumn("bj", F.col("unit"))
    own = _units(rows, cfg, large, max(1, HELD_ROWS // cfg.d_max))
    own = own.withColumn("other", F.explode(F.when(F.col("units") == 1, F.array(F.lit(0))).otherwise(F.sequence(F.lit(0), F.col("units") - 1))))
    return own.withColumn("bi", F.least("unit", "other")).withColumn("bj", F.greatest("unit", "other")).drop("other")


def split_apart(rows: DataFrame, cfg: DedupConfig) -> DataFrame:
    """The same for buckets of which one component holds some rows (column ``joined``) already: no two of these meet again.

    Columns ``n_joined`` and ``n_others`` are the bucket's sizes.  Rows of the component take sub-units of their own and go to
    the others' sub-units only.
    """
    few = lambda c: F.ceil(F.col(c) / cfg.d_max).cast("int")
    own = rows.withColumn("a", few("n_joined")).withColumn("b", few("n_others")).where("b > 0")
    h = F.xxhash64("doc_id")
    own = own.withColumn("unit", F.when(F.col("joined"), F.pmod(h, F.col("a"))).otherwise(F.col("a") + F.pmod(h, F.col("b"))).cast("int"))
    own = own.withColumn("other", F.explode(F.sequence(F.when(F.col("joined"), F.col("a")).otherwise(F.lit(0)), F.col("a") + F.col("b") - 1)))
    return own.withColumn("bi", F.least("unit", "other")).withColumn("bj", F.greatest("unit", "other"))


def _salted_anchors(rows: DataFrame, cfg: DedupConfig, large: DataFrame | None) -> DataFrame:
    """Cut large buckets in sub-units, each with a copy of the bucket's anchor: its least id."""
    large = oversize_buckets(rows, cfg) if large is None else large
    own = rows.join(fitted(large.select("band", "bucket", "n", "head"), 40), ["band", "bucket"], "left")
    units = F.ceil(F.coalesce("n", F.lit(1)) / cfg.d_max).cast("int")
    mine = F.array(F.pmod(F.xxhash64("doc_id"), units).cast("int"))
    return own.withColumn("bi", F.explode(F.when(F.col("doc_id") == F.col("head"), F.sequence(F.lit(0), units - 1)).otherwise(mine))).withColumn("unit", F.lit(0)).withColumn("bj", F.lit(0))


#: Pairs that a task holds before it reduces them and passes them on.
HELD_PAIRS = 1 << 18


def compare(rows: DataFrame, cfg: DedupConfig, how: str = "all", verify: bool = True, reduce: bool = True, early_exit: bool = True, large: DataFrame | None = None) -> DataFrame:
    """u, v, matches inside buckets of (band, bucket, doc_id, sig) rows.

    Buckets are brought together by one exchange and read bucket by bucket from a sorted stream.  ``all``: all pairs, of which a
    sub-unit or two are held; ``anchor``: the least id with each other, of which only the anchor is held.  With ``reduce`` a
    task leaves a spanning forest of its pairs, which connects the same documents; without it all its pairs, distinct in the
    task.  ``large`` gives the oversize buckets where they are known; rows that have ``bi``, ``bj`` and ``unit`` are cut already.
    """
    if how == "anchor":
        keyed = _salted_anchors(rows, cfg, large)
    else:
        keyed = rows if "bi" in rows.columns else split_oversize(rows, cfg, large)
    keys = ["band", "bucket", "bi", "bj"]
    keyed = keyed.select(*keys, "unit", "doc_id", "sig").repartition(*keys).sortWithinPartitions(*keys, *(["doc_id"] if how == "anchor" else []))

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pairs: list[tuple[np.ndarray, ...]] = []
        held: list[tuple[np.ndarray, ...]] = []

        def bucket(part: list[tuple[np.ndarray, ...]]) -> None:
            unit, ids, sig = map(np.concatenate, zip(*part))
            if len(ids) > 1:
                pairs.append(all_pairs(ids, sig, cfg, unit, early_exit=early_exit))

        def leave() -> pa.RecordBatch:
            u, v, n = map(np.concatenate, zip(*pairs)) if pairs else (np.zeros(0, np.int64),) * 3
            pairs.clear()
            if len(u):
                own = np.unique(np.stack((u, v, n), axis=1), axis=0)
                u, v, n = own.T
                if reduce:
                    u, v = local_forest(u.tolist(), v.tolist())
                    n = np.zeros(len(u), np.int64)
            return pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64()), pa.array(n.astype(np.int32), pa.int32())], names=["u", "v", "matches"])

        last = None
        for batch in batches:
            if not batch.num_rows:
                continue
            key = np.stack([batch.column(k).to_numpy(zero_copy_only=False).astype(np.int64) for k in range(4)], axis=1)
            unit, ids = (batch.column(k).to_numpy(zero_copy_only=False) for k in (4, 5))
            sig = batch.column(6).flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1)
            cuts = np.concatenate(([0], np.flatnonzero((key[1:] != key[:-1]).any(axis=1)) + 1, [len(ids)]))
            for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist()):
                own = tuple(key[a])
                if own != last and held:
                    if how == "all":
                        bucket(held)
                    held = []
                last = own
                if how == "all":
                    held.append((unit[a:b], ids[a:b], sig[a:b]))
                    continue
                if not held:
                    held = [(ids[a], sig[a].copy())]
                if b - a > 1 or ids[a] != held[0][0]:
                    pairs.append(against_anchor(*held[0], ids[a:b], sig[a:b], cfg, verify))
            if sum(len(x[0]) for x in pairs) > HELD_PAIRS:
                yield leave()
        if held and how == "all":
            bucket(held)
        yield leave()

    return keyed.mapInArrow(run, "u long, v long, matches int")


def candidates(rows: DataFrame) -> DataFrame:
    """u < v of all pairs that share a bucket in some band: for small tables and checks."""
    a, b = rows.select("band", "bucket", F.col("doc_id").alias("u")), rows.select("band", "bucket", F.col("doc_id").alias("v"))
    return a.join(b, ["band", "bucket"]).where("u < v").select("u", "v").distinct()


def verify_pairs(pairs: DataFrame, sig: DataFrame, cfg: DedupConfig) -> DataFrame:
    """u, v, matches of the candidate pairs whose signatures agree often enough."""
    one, two = sig.select(F.col("doc_id").alias("u"), F.col("sig").alias("su")), sig.select(F.col("doc_id").alias("v"), F.col("sig").alias("sv"))
    from corpusdedup.functions.shingles import match_count

    both = pairs.select("u", "v").join(one, "u").join(two, "v").select("u", "v", match_count(F.col("su"), F.col("sv")).alias("matches"))
    return both.where(F.col("matches") >= cfg.min_matches)


def crowded_pairs(members: DataFrame, sig: DataFrame, cfg: DedupConfig) -> DataFrame:
    """Edges that connect what all pairs in these buckets connect: a star around each head, then all others.

    ``members`` has band, bucket, doc_id, and the bucket's size ``n`` and least id ``head``.
    """
    star = members.where("doc_id <> head").select(F.col("head").alias("u"), F.col("doc_id").alias("v")).distinct()
    star = materialise(verify_pairs(star, sig, cfg), "crowded-stars")
    labels = materialise(connected_components(star.select("u", "v")), "crowded-labels")
    named = members.join(fitted(labels, 16).withColumnsRenamed({"node": "doc_id"}), "doc_id", "left").withColumn("component", F.coalesce("component", "doc_id"))
    heads = named.where("doc_id = head").select("band", "bucket", F.col("component").alias("of"))
    flagged = materialise(named.where("n > 2").join(fitted(heads, 20), ["band", "bucket"]).select("band", "bucket", "doc_id", (F.col("component") == F.col("of")).alias("joined")), "crowded-buckets")
    sizes = flagged.groupBy("band", "bucket").agg(F.sum(F.col("joined").cast("long")).alias("n_joined"), F.sum((~F.col("joined")).cast("long")).alias("n_others"))
    rows = flagged.join(fitted(materialise(sizes, "crowded-sizes"), 28), ["band", "bucket"]).where("n_others > 0").join(sig.select("doc_id", "sig"), "doc_id")
    return star.select("u", "v", "matches").union(compare(split_apart(rows, cfg), cfg))
