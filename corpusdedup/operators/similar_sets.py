"""All pairs of documents whose shingle sets have a Jaccard similarity of at least so much: no pair is lost, none is estimated."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusdedup.functions.hashing import codes_of
from corpusdedup.operators.exact import copies_of
from corpusdedup.operators.graph import connected_components
from corpusdedup.plans.shared import fitted, materialise, releasing

#: Sizes of sets at which classes end.
ENDS = np.unique(np.ceil(8 * 1.5 ** np.arange(80)).astype(np.int64))[:48]

#: Bytes of sketches, and characters of texts, of about which a sub-unit is made.
UNIT_BYTES, UNIT_CHARS = 1 << 19, 1 << 22

#: Texts of small components that are numbered together.
HELD_TEXTS = 512


def packed_grams(codes: np.ndarray, k: int) -> np.ndarray:
    """A number for the k-gram at each position; equal numbers are equal grams among these codes."""
    m = len(codes) - k + 1
    if m < 1:
        return codes[:0]
    if int(codes.max() + 1) ** k >= 1 << 63:
        # Numbers of the code points in use, in their order.
        used = np.zeros(int(codes.max()) + 1, np.int64)
        used[codes] = 1
        codes = (np.cumsum(used) - 1)[codes]
    base = int(codes.max()) + 1
    if base**k < 1 << 63:
        own = codes[:m]
        for j in range(1, k):
            own = own * base + codes[j : m + j]
        return own
    own = codes[:m]
    for j in range(1, k):
        own = np.unique(own * base + codes[j : m + j], return_inverse=True)[1].astype(np.int64)
    return own


def distinct_grams(codes: np.ndarray, k: int) -> list[np.ndarray]:
    """The first, second, ... code points of the distinct k-grams."""
    base = int(codes.max()) + 1 if len(codes) else 1
    if base**k < 1 << 63:
        own = np.unique(packed_grams(codes, k))
        return [own // base ** (k - 1 - j) % base for j in range(k)]
    at = np.unique(packed_grams(codes, k), return_index=True)[1]
    return [codes[at + j] for j in range(k)]


def most_apart(a: float, b: float, least: float) -> float:
    """Elements that one of two sets of these sizes has and the other lacks, at most, where the similarity is ``least`` or more."""
    return (1 - least) / (1 + least) * (a + b) + 1e-6


def sketch_bits(c: int, least: float) -> int:
    """Bits of a sketch of class c: three times the elements in which its largest sets may differ, in whole words."""
    return 64 * (int(3 * most_apart(ENDS[c], ENDS[c], least)) // 64 + 1)


def classes_of(n: int, least: float) -> range:
    """Classes of the sets that are no smaller than one of ``n`` elements and may be similar to it."""
    first = last = int(np.searchsorted(ENDS, n))
    while n >= least * (ENDS[last] + 1) - 1e-6:
        last += 1
    return range(first, last + 1)


def parity_sketches(docs: DataFrame, k: int, least: float) -> DataFrame:
    """cls, doc_id, n (distinct shingles), sketch, of each class that the document's partners may have.

    A sketch has the parities of the elements in each of its cells.  Where two sketches differ, an element is in one of the two
    sets only, so they differ in no more bits than the sets in elements.
    """

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first in range(0, batch.num_rows, 256):
                part, rows = batch.slice(first, 256), []
                for i, text in zip(part.column(0).to_pylist(), part.column(1).to_pylist()):
                    letters = distinct_grams(codes_of(text), k)
                    n = len(letters[0])
                    if not n:
                        continue
                    h = np.zeros(n, np.uint64)
                    for x in letters:
                        h = (h + x.astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
                        h ^= h >> np.uint64(29)
                    for c in classes_of(n, least):
                        bits = sketch_bits(c, least)
                        odd = np.bincount((h % np.uint64(bits)).astype(np.int64), minlength=bits) & 1
                        rows.append((c, i, n, np.packbits(odd.astype(np.uint8)).tobytes()))
                columns = zip(*rows) if rows else ((),) * 4
                yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(columns, (pa.int32(), pa.int64(), pa.int64(), pa.binary()))], names=["cls", "doc_id", "n", "sketch"])

    return docs.where("text is not null").select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "cls int, doc_id long, n long, sketch binary")


def close_pairs(n: np.ndarray, sketch: np.ndarray, m: np.ndarray, other: np.ndarray, same: bool, over: int, least: float, tile: int = 64, wide: int = 1024) -> tuple[np.ndarray, np.ndarray]:
    """(row, row of the other) of pairs whose sizes and sketches allow the similarity and whose larger set has more than ``over`` elements.

    Rows come in the order of their sizes ``n`` and ``m``.  With ``same`` both are one table, and a pair is given once.
    """
    out: list[tuple[np.ndarray, np.ndarray]] = []
    mine, others = np.ascontiguousarray(sketch.T), np.ascontiguousarray(other.T)
    xor, ones = np.empty((tile, wide), np.uint64), np.empty((tile, wide), np.uint8)
    sums = np.empty((tile, wide), np.uint16 if 64 * len(mine) < 1 << 16 else np.int32)
    for x in range(0, len(n), tile):
        a = slice(x, min(x + tile, len(n)))
        low = x if same else int(np.searchsorted(m, least * n[x] - 1e-6))
        high = int(np.searchsorted(m, n[a.stop - 1] / least + 1e-6, "right"))
        for y in range(low, high, wide):
            b = slice(y, min(y + wide, high))
            d, e, apart = (z.ravel()[: (a.stop - x) * (b.stop - y)].reshape(a.stop - x, -1) for z in (xor, ones, sums))
            apart[:] = 0
            for p, q in zip(mine[:, a], others[:, b]):
                np.bitwise_xor(p[:, None], q, out=d)
                np.add(apart, np.bitwise_count(d, out=e), out=apart)
            i, j = np.nonzero((apart <= most_apart(n[a, None], m[None, b], least)) & (np.maximum(n[a, None], m[None, b]) > over))
            i, j = i + x, j + y
            keep = (np.minimum(n[i], m[j]) >= least * np.maximum(n[i], m[j]) - 1e-6) & ((j > i) | (not same))
            out.append((i[keep], j[keep]))
    return tuple(map(np.concatenate, zip(*out))) if out else (np.zeros(0, np.int64),) * 2


def _blocks(batches: Iterable[pa.RecordBatch], n_keys: int, together: int = 1) -> Iterator[tuple[tuple, pa.Table]]:
    """Rows of each key (the first columns, integers) from batches in the order of the key; keys of so many rows ``together``."""
    held: list[pa.RecordBatch] = []
    first = last = None
    for batch in batches:
        if not batch.num_rows:
            continue
        key = np.stack([batch.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in range(n_keys)], axis=1)
        cuts = (np.flatnonzero((key[1:] != key[:-1]).any(axis=1)) + 1).tolist()
        start, n = 0, sum(h.num_rows for h in held)
        for cut in ([0] if last is not None and tuple(key[0].tolist()) != last else []) + cuts:
            if n + cut - start >= together:
                held.append(batch.slice(start, cut - start))
                yield first if first is not None else tuple(key[start].tolist()), pa.Table.from_batches(held)
                held, first, start, n = [], None, cut, 0
        held.append(batch.slice(start))
        first = first if first is not None else tuple(key[start].tolist())
        last = tuple(key[-1].tolist())
    if held:
        yield first, pa.Table.from_batches(held)


def _cut(rows: DataFrame, key: str, units: DataFrame) -> DataFrame:
    """Add ``unit``, ``bi``, ``bj``: a row goes to every pair of its key's sub-units that holds its own."""
    own = rows.join(fitted(units, 24), key).withColumn("unit", F.pmod(F.xxhash64("doc_id"), F.col("units")).cast("int"))
    own = own.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("units") - 1)))
    return own.withColumn("bi", F.least("unit", "other")).withColumn("bj", F.greatest("unit", "other"))


def sketched_pairs(sketches: DataFrame, least: float) -> DataFrame:
    """u < v of pairs that written sketches leave possible, each once: all pairs of a class, in sub-units."""
    units = sketches.groupBy("cls").agg(F.ceil(F.sum(F.length("sketch")) / UNIT_BYTES).cast("int").alias("units"))
    keys = ["cls", "bi", "bj"]
    rows = _cut(sketches, "cls", materialise(units, "sketch-units")).select(*keys, "unit", "doc_id", "n", "sketch").repartition(*keys).sortWithinPartitions(*keys)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for (c, bi, bj), block in _blocks(batches, 3):
            unit, ids, n = (block.column(x).to_numpy() for x in (3, 4, 5))
            words = np.frombuffer(b"".join(block.column(6).to_pylist()), np.uint64).reshape(len(ids), -1)
            order = np.argsort(n, kind="stable")
            x, y = (order[unit[order] == u] for u in (bi, bj))
            i, j = close_pairs(n[x], words[x], n[y], words[y], bi == bj, int(ENDS[c - 1]) if c else 0, least)
            u, v = ids[x[i]], ids[y[j]]
            yield pa.RecordBatch.from_arrays([pa.array(np.minimum(u, v), pa.int64()), pa.array(np.maximum(u, v), pa.int64())], names=["u", "v"])

    return rows.mapInArrow(run, "u long, v long")


def counted_pairs(pairs: DataFrame, docs: DataFrame, k: int, least: float) -> DataFrame:
    """u, v, common, total of written pairs that reach ``least``, by the sets of the texts.

    A text travels to its component of the pairs once, or where the component's texts are many, to the blocks of its
    sub-units in which it has a pair.
    """
    labels = materialise(connected_components(pairs, written=True).withColumnsRenamed({"node": "doc_id", "component": "group"}), "similar-groups")
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(fitted(labels.select("doc_id"), 8), "doc_id", "left_semi")
    chars = texts.select("doc_id", F.char_length("text").alias("chars")).join(fitted(labels, 16), "doc_id")
    units = materialise(chars.groupBy("group").agg(F.ceil((F.sum("chars") + 1) / UNIT_CHARS).cast("int").alias("units")), "similar-units")
    own = pairs.join(fitted(labels.withColumnRenamed("doc_id", "u"), 16), "u").join(fitted(units, 12), "group")
    unit = lambda c: F.pmod(F.xxhash64(c), F.col("units")).cast("int")
    own = materialise(own.select("group", F.least(unit("u"), unit("v")).alias("bi"), F.greatest(unit("u"), unit("v")).alias("bj"), "u", "v"), "similar-blocks")
    keys = ["group", "bi", "bj"]
    partners = own.groupBy(*keys, F.col("v").alias("doc_id")).agg(F.collect_list("u").alias("partners"))
    needed = own.select(*keys, F.explode(F.array("u", "v")).alias("doc_id")).distinct().join(partners, [*keys, "doc_id"], "left")
    rows = needed.join(texts, "doc_id").select(*keys, "doc_id", "partners", "text").repartition(*keys).sortWithinPartitions(*keys)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, block in _blocks(batches, 3, HELD_TEXTS):
            ids, wanted = block.column(3).to_pylist(), block.column(4).to_pylist()
            codes = [codes_of(t) for t in block.column(5).to_pylist()]
            # One numbering for the whole block; a gram that runs over the end of a text is left out.
            numbers = packed_grams(np.concatenate(codes), k)
            ends = np.cumsum([len(c) for c in codes])
            sets = {i: np.unique(numbers[e - len(c) : e - k + 1]) for i, c, e in zip(ids, codes, ends.tolist())}
            found = []
            for v, us in zip(ids, wanted):
                for u in us or ():
                    a, b = sets[u], sets[v]
                    common = len(np.intersect1d(a, b, assume_unique=True))
                    total = len(a) + len(b) - common
                    if common / total >= least:
                        found.append((u, v, common, total))
            columns = zip(*found) if found else ((),) * 4
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=["u", "v", "common", "total"])

    return rows.mapInArrow(run, "u long, v long, common long, total long")


def jaccard_pairs(docs: DataFrame, k: int = 5, least: float = 0.8) -> DataFrame:
    """u, v, common, total, jaccard of all pairs of documents whose sets of k-grams of characters reach ``least`` (above 0).

    Equal texts are compared once and their pairs made at the end.  Candidates are the pairs of all others whose sizes and parity
    sketches allow the similarity; their sets are then counted from the texts.
    """
    spark = docs.sparkSession
    with releasing(spark) as keep:
        hashed = docs.where("text is not null").select(F.col("doc_id").cast("long").alias("doc_id"), F.unhex(F.sha2("text", 256)).alias("text_key"))
        copies = materialise(copies_of(hashed), "similar-copies")
        single = docs.where("text is not null").join(fitted(copies.select(F.col("v").alias("doc_id")), 8), "doc_id", "left_anti")
        sketches = materialise(parity_sketches(single, k, least), "sketches")
        close = materialise(sketched_pairs(sketches, least), "close-pairs")
        found = materialise(counted_pairs(close, single, k, least), "similar-pairs")
        heads = materialise(copies.select(F.col("u").alias("doc_id")).distinct().join(sketches.select("doc_id", "n").distinct(), "doc_id"), "similar-heads")
        members = copies.union(heads.select("doc_id", "doc_id")).toDF("head", "member")
        members = materialise(members, "similar-members")
        for end in ("u", "v"):
            mine = members.select(F.col("head").alias(end), F.col("member").alias("_m"))
            found = found.join(fitted(mine, 16), end, "left").withColumn(end, F.coalesce("_m", end)).drop("_m")
        one, two = (members.select(F.col("head").alias("doc_id"), F.col("member").alias(end)) for end in ("u", "v"))
        inside = heads.join(fitted(one, 16), "doc_id").join(fitted(two, 16), "doc_id").where("u < v")
        both = found.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"), "common", "total").union(inside.select("u", "v", F.col("n").alias("common"), F.col("n").alias("total")))
        both = materialise(both, "jaccard-pairs")
        keep(both)
    return both.withColumn("jaccard", F.col("common") / F.col("total")).select("u", "v", "common", "total", "jaccard")
