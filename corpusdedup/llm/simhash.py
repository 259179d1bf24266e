"""SimHash near-duplicates by anchor-point covering.

Anchors are the words of a covering code: the product of two perfect 23-bit codes of covering radius 3, over 46 of the 64
bits.  Every fingerprint has one home anchor within that radius.  A fingerprint at ``threshold`` or fewer bits from it lies
within radius plus threshold of that anchor, counted block by block, so fingerprints are replicated to all such anchors
(about 61 for 2 bits) and each anchor's homes are compared with its visitors.  No link can be missed.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from functools import lru_cache
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusdedup.llm.common import materialise, slices, text_bytes
from corpusdedup.operators.graph import LOCAL_EDGES, contract, local_forest
from corpusdedup.plans.shared import fitted

SEED = 42
SHINGLE = 3
THRESHOLD = 2
#: The perfect binary code: length, redundancy, covering radius, and its generator polynomial as bits.
LENGTH, REDUNDANCY, RADIUS, GENERATOR = 23, 11, 3, 0b101011100011
#: Comparisons held at once.
PAIRS_AT_ONCE = 1 << 20
#: Fingerprints at home at an anchor above which its group is cut.
CROWD = 4096
#: A fingerprint of more than one in so many rows is joined apart from the others.
HOT_SHARE = 1000


def shingle_hashes(words: list[bytes], shingle: int) -> np.ndarray:
    """64-bit hashes of all runs of ``shingle`` words; fewer words are one run."""
    joined = b" ".join(words)
    if len(words) <= shingle:
        return np.array([xxhash.xxh64_intdigest(joined, SEED)] if words else [], dtype="<u8")
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))
    digest, view = xxhash.xxh64_intdigest, memoryview(joined)
    return np.array([digest(view[a:b], SEED) for a, b in zip(starts[: 1 - shingle].tolist(), ends[shingle - 1 :].tolist())], dtype="<u8")


def fingerprint(text: bytes, shingle: int = SHINGLE) -> int:
    """The 64-bit fingerprint of a text: a bit is set if it is set in more than half of the shingles' hashes."""
    return majority(shingle_hashes(text.lower().split(), shingle))


def majority(hashes: np.ndarray) -> int:
    """A bit is set if it is set in more than half of the hashes."""
    set_bits = np.zeros(64, dtype=np.int64)
    for k in range(0, len(hashes), 1 << 16):
        set_bits += np.unpackbits(hashes[k : k + (1 << 16)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * set_bits > len(hashes), bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, shingle: int = SHINGLE) -> DataFrame:
    """doc_id and fingerprint (the 64 bits as a signed long) of each whole text; a text without words has 0."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text"):
                found = np.array([fingerprint(t, shingle) for t in part.column(1).to_pylist()], dtype=np.uint64).view(np.int64)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(found)], names=["doc_id", "fingerprint"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_bytes().alias("text")).mapInArrow(run, "doc_id long, fingerprint long")


@lru_cache(maxsize=1)
def _code(threshold: int):
    """Syndrome tables of the code, and for each syndrome its error patterns up to radius + threshold bits with their excess over the radius."""
    bit = []
    for i in range(LENGTH):
        x = 1 << i
        for k in range(LENGTH - 1, REDUNDANCY - 1, -1):
            if x >> k & 1:
                x ^= GENERATOR << (k - REDUNDANCY)
        bit.append(x)
    low = np.zeros(1 << 12, dtype=np.int64)
    high = np.zeros(1 << 11, dtype=np.int64)
    for i in range(12):
        low[1 << i : 2 << i] = low[: 1 << i] ^ bit[i]
    for i in range(11):
        high[1 << i : 2 << i] = high[: 1 << i] ^ bit[12 + i]
    patterns: list[list[tuple[int, int]]] = [[] for _ in range(1 << REDUNDANCY)]
    for n in range(RADIUS + threshold + 1):
        for own in combinations(range(LENGTH), n):
            e = s = 0
            for i in own:
                e |= 1 << i
                s ^= bit[i]
            patterns[s].append((e, max(0, n - RADIUS)))
    tables = [(np.array([e for e, _ in p], dtype=np.int64), np.array([x for _, x in p], dtype=np.int64)) for p in patterns]
    return low, high, tables


def home_anchors(x: np.ndarray, threshold: int = THRESHOLD) -> np.ndarray:
    """The one anchor within the radius of each fingerprint."""
    low, high, tables = _code(threshold)
    nearest = np.array([e[int(np.flatnonzero(over == 0)[0])] for e, over in tables], dtype=np.int64)
    mask = (1 << LENGTH) - 1
    a, b = x & mask, (x >> LENGTH) & mask
    return (a ^ nearest[low[a & 4095] ^ high[a >> 12]]) | ((b ^ nearest[low[b & 4095] ^ high[b >> 12]]) << LENGTH)


def replicas(x: np.ndarray, threshold: int = THRESHOLD) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(index into x, anchor, is it home) for every anchor that a fingerprint goes to."""
    low, high, tables = _code(threshold)
    mask = (1 << LENGTH) - 1
    a, b = x & mask, (x >> LENGTH) & mask
    sa, sb = (low[y & 4095] ^ high[y >> 12] for y in (a, b))
    index, anchor, home = [], [], []
    for i, (p, q, s, t) in enumerate(zip(a.tolist(), b.tolist(), sa.tolist(), sb.tolist())):
        (e, ex), (f, fx) = tables[s], tables[t]
        over = ex[:, None] + fx[None, :]
        j, k = np.nonzero(over <= threshold)
        anchor.append((p ^ e[j]) | ((q ^ f[k]) << LENGTH))
        home.append(over[j, k] == 0)
        index.append(np.full(len(j), i))
    cat = lambda parts, kind: np.concatenate(parts) if parts else np.empty(0, kind)
    return cat(index, np.int64), cat(anchor, np.int64), cat(home, bool)


def matches(group: np.ndarray, fp: np.ndarray, home: np.ndarray, threshold: int) -> tuple[np.ndarray, np.ndarray]:
    """Links between homes and visitors of equal group; the rows are sorted by group."""
    first = np.flatnonzero(np.concatenate(([True], group[1:] != group[:-1])))
    size = np.diff(np.concatenate((first, [len(group)])))
    number = np.repeat(np.arange(len(first)), size)
    h = np.flatnonzero(home & (size[number] > 1))
    u, v = [], []
    each = size[number[h]]
    stops = np.cumsum(each)
    lo = 0
    while lo < len(h):
        hi = max(lo + 1, int(np.searchsorted(stops, (stops[lo - 1] if lo else 0) + PAIRS_AT_ONCE, "right")))
        own, n = h[lo:hi], each[lo:hi]
        left = np.repeat(own, n)
        right = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n) + np.repeat(first[number[own]], n)
        x, y = fp[left], fp[right]
        near = (np.bitwise_count((x ^ y).view(np.uint64)) <= threshold) & (x != y)
        u.append(x[near]), v.append(y[near])
        lo = hi
    return (np.concatenate(u), np.concatenate(v)) if u else (fp[:0], fp[:0])


def crowded_anchors(nodes: DataFrame, threshold: int = THRESHOLD, crowd: int = CROWD) -> DataFrame:
    """The anchors at which more than ``crowd`` fingerprints are at home: at most one in so many fingerprints has one."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array(home_anchors(batch.column(0).to_numpy(zero_copy_only=False), threshold))], names=["anchor"])

    return nodes.select("fingerprint").mapInArrow(run, "anchor long").groupBy("anchor").count().where(F.col("count") > crowd).select("anchor")


def links(nodes: DataFrame, threshold: int = THRESHOLD, crowd: int = CROWD) -> DataFrame:
    """Edges (u, v) that connect what pairs of distinct fingerprints within ``threshold`` bits connect.

    The group of a crowded anchor is cut by the bits that anchors don't cover: they fall into one segment more than
    ``threshold``, so two linked fingerprints agree in a segment, and a row goes to a part for each of its segments.  Each task
    reduces the links that it finds to a spanning forest, so a dense group leaves fewer edges than members.
    """

    def spread(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(0, batch.num_rows, 2048):
                x = batch.column(0).slice(k, 2048).to_numpy(zero_copy_only=False)
                i, anchor, home = replicas(x, threshold)
                yield pa.RecordBatch.from_arrays([pa.array(anchor), pa.array(x[i]), pa.array(home)], names=["anchor", "fingerprint", "home"])

    def compare(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, ...]] = []

        def flush(rows: tuple[np.ndarray, ...]) -> pa.RecordBatch:
            anchor, part, fp, home = rows
            group = np.cumsum(np.concatenate(([False], (anchor[1:] != anchor[:-1]) | (part[1:] != part[:-1]))))
            u, v = matches(group, fp, home, threshold)
            if len(u):
                a, b = np.minimum(u, v), np.maximum(u, v)
                a, b = np.unique(np.stack((a, b), axis=1), axis=0).T
                u, v = local_forest(a.tolist(), b.tolist())
            return pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64())], names=["u", "v"])

        for batch in batches:
            if not batch.num_rows:
                continue
            held.append(tuple(batch.column(k).to_numpy(zero_copy_only=False) for k in range(4)))
            first, last = held[0], held[-1]
            if (last[0][-1], last[1][-1]) == (first[0][0], first[1][0]):
                continue  # one group's rows so far
            rows = tuple(map(np.concatenate, zip(*held)))
            cut = int(np.flatnonzero((rows[0] != rows[0][-1]) | (rows[1] != rows[1][-1]))[-1]) + 1
            held = [tuple(c[cut:] for c in rows)]
            yield flush(tuple(c[:cut] for c in rows))
        if held:
            yield flush(tuple(map(np.concatenate, zip(*held))))

    spread_out = nodes.select("fingerprint").mapInArrow(spread, "anchor long, fingerprint long, home boolean")
    crowded = materialise(crowded_anchors(nodes, threshold, crowd), "crowded-anchors")
    if crowded.head(1):
        segments = np.array_split(np.arange(2 * LENGTH, 64), threshold + 1)
        bits = lambda s: F.shiftrightunsigned("fingerprint", int(s[0])).bitwiseAND((1 << len(s)) - 1)
        parts = F.array(*[(F.lit(1 + (k << 18)).cast("long") + bits(s)) for k, s in enumerate(segments)])
        flagged = spread_out.join(fitted(crowded.withColumn("_crowded", F.lit(True)), 9), "anchor", "left")
        split = flagged.select("anchor", F.explode(F.when(F.col("_crowded"), parts).otherwise(F.array(F.lit(0).cast("long")))).alias("part"), "fingerprint", "home")
    else:
        split = spread_out.select("anchor", F.lit(0).cast("long").alias("part"), "fingerprint", "home")
    return split.repartition("anchor", "part").sortWithinPartitions("anchor", "part").mapInArrow(compare, "u long, v long")


def near_duplicates(docs: DataFrame, threshold: int = THRESHOLD, shingle: int = SHINGLE) -> DataFrame:
    """doc_id, fingerprint (signed long), component_id (least doc_id reachable over links of at most ``threshold`` bits).

    Texts of equal fingerprint are one node.  Null and empty texts have fingerprint 0 and link like any other; repeated rows
    appear as often as they occur; rows without doc_id keep a null doc_id and don't name components; other columns are not
    read; an empty table gives an empty result.
    """
    own = materialise(fingerprints(docs, shingle), "fingerprints")
    nodes = materialise(own.groupBy("fingerprint").agg(F.min("doc_id").alias("least"), F.count("*").alias("n")), "fingerprint-nodes")
    roots = contract(links(nodes, threshold), LOCAL_EDGES).withColumnRenamed("node", "fingerprint")
    linked = nodes.join(roots, "fingerprint")
    least = linked.groupBy("root").agg(F.min("least").alias("component"))
    named = linked.join(least, "root").select("fingerprint", "component")
    every = materialise(nodes.join(named, "fingerprint", "left").select("fingerprint", F.coalesce("component", "least").alias("component_id"), "n"), "fingerprint-components")
    # Fingerprints of many rows, of which there can't be more than ``HOT_SHARE``, don't meet their rows in a shuffle.
    rows = every.agg(F.sum("n")).first()[0] or 0
    hot = F.broadcast(every.where(F.col("n") * HOT_SHARE > rows).select("fingerprint", "component_id"))
    apart = own.join(hot, "fingerprint").select("doc_id", "fingerprint", "component_id")
    others = own.join(hot.select("fingerprint"), "fingerprint", "left_anti").join(every.select("fingerprint", "component_id"), "fingerprint")
    return apart.union(others.select("doc_id", "fingerprint", "component_id"))


def keep_first(docs: DataFrame, threshold: int = THRESHOLD) -> DataFrame:
    """The documents whose doc_id names their component, one row each, all columns kept; rows without doc_id stay as they are.

    Rows of equal doc_id are one document, of which any row stays.
    """
    found = materialise(near_duplicates(docs, threshold).where("doc_id is not null"), "simhash-groups")
    gone = materialise(found.where("doc_id <> component_id").select(F.col("doc_id").alias("_gone")).distinct(), "simhash-gone")
    kept = docs.join(fitted(gone, 8), docs["doc_id"].cast("long") == gone["_gone"], "left_anti")
    if not found.groupBy("doc_id").count().where("count > 1").head(1):
        return kept
    return kept.where("doc_id is not null").dropDuplicates(["doc_id"]).union(kept.where("doc_id is null"))
