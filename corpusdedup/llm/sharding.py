"""Sharding by sampled splitters.

A size-weighted sample of keys gives splitters that cut the key order into many ranges of about equal bytes.  Ranges that
hold more than their share (one key can hold a third of all rows) are subdivided by a second key.  Exact byte and row counts
of the ranges, not the sample, then place the shard boundaries, so shards are equal to within about one small group.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from corpusdedup.llm.common import materialise, portable_unit

SHARDS = 16
#: Ranges cut at least, rows of a range (about) beyond that, and keys drawn for each range; a range should fit a task's sort.
RANGES, RANGE_ROWS, KEYS_EACH = 1024, 1 << 19, 8
#: Groups of equal texts stay in one shard unless they hold more than this share of a shard.
TOGETHER = 0.01


def splitters(items: DataFrame, sample: int = KEYS_EACH * RANGES, ranges: int = RANGES, seed: int = 7) -> list[int]:
    """Upper bounds (inclusive) of all ranges but the last, from a priority sample of ``sample`` keys.

    A key is drawn by its size over a random number; one that is drawn stands for its size, or for the first priority that
    was not drawn if that is more, so that sums over the sample estimate bytes without bias.  A key that the sample shows on
    two or more boundaries gets a range of its own.
    """
    drawn = items.select("key", "size", (F.col("size") / portable_unit(F.col("doc_id"), seed)).alias("w")).orderBy(F.col("w").desc(), "key").limit(sample + 1)
    rows = [(r["key"], r["size"], r["w"]) for r in drawn.collect()]
    least = rows.pop()[2] if len(rows) > sample else 0.0
    rows.sort()
    at = np.cumsum([max(size, least) for _, size, _ in rows])
    places = np.searchsorted(at, [at[-1] * k / ranges for k in range(1, ranges)]) if rows else []
    cuts = [rows[k][0] for k in places]
    out: set[int] = set()
    for key, own in itertools.groupby(cuts):
        out.add(key)
        if len(list(own)) > 1 and key > -(1 << 63):
            out.add(key - 1)
    return sorted(out)


def ranged(items: DataFrame, bounds: list[int]) -> DataFrame:
    """Add ``range_id``: the number of splitters below the key."""
    schema = T.StructType([*items.schema.fields, T.StructField("range_id", T.IntegerType())])
    at = items.columns.index("key")
    own = np.array(bounds, dtype=np.int64)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = np.searchsorted(own, b.column(at).to_numpy(zero_copy_only=False), "left").astype(np.int32)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(found)], names=[*b.schema.names, "range_id"])

    return items.mapInArrow(run, schema)


def shard(docs: DataFrame, shards: int = SHARDS, ranges: int = RANGES, range_rows: int = RANGE_ROWS, together: float = TOGETHER) -> DataFrame:
    """doc_id, size (UTF-8 bytes + 1), text_crc32, shard and slot (gapless from 0 in each shard) of every row.

    Shards are runs of the order (hash of the text, doc_id), cut where the bytes before reach a multiple of the total over
    ``shards``.  Equal texts stay together unless they hold more than ``together`` of a shard.  Null and empty texts have
    size 1 and the checksum of nothing; repeated rows each get a slot; other columns are not read; an empty table gives an
    empty result.
    """
    spark = docs.sparkSession
    text = F.coalesce(F.col("text"), F.lit(""))
    items = docs.select(F.col("doc_id").cast("long").alias("doc_id"), (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.xxhash64(text).alias("key"))
    items = materialise(items, "shard-items")
    total, rows = items.agg(F.coalesce(F.sum("size"), F.lit(0)), F.count("*")).first()
    ranges = max(ranges, -(-rows // range_rows))
    bounds = splitters(items, KEYS_EACH * ranges, ranges)
    share = max(1.0, total / shards)
    items = materialise(ranged(items, bounds), "shard-ranges")
    # As many rows as there are ranges.
    held = {r["range_id"]: r["b"] for r in items.groupBy("range_id").agg(F.sum("size").alias("b")).collect()}
    most = 4 * max(total / max(1, len(bounds) + 1), 1)
    over = [(k, -(-b // int(most))) for k, b in held.items() if b > most]
    parts = spark.createDataFrame(over, "range_id int, parts long")  # at most as many rows as there are ranges
    split = items.join(F.broadcast(parts), "range_id", "left").withColumn("part", F.when(F.col("parts").isNotNull(), F.pmod(F.xxhash64("doc_id", "text_crc32"), F.col("parts"))).otherwise(F.lit(0)).cast("int"))
    cells = [(r["range_id"], r["part"], r["b"], r["n"]) for r in split.groupBy("range_id", "part").agg(F.sum("size").alias("b"), F.count("*").alias("n")).collect()]
    cells.sort()
    at_bytes, at_rows, before = 0, 0, []
    for k, p, b, n in cells:
        before.append((k, p, at_bytes, at_rows))
        at_bytes, at_rows = at_bytes + b, at_rows + n
    places = spark.createDataFrame(before, "range_id int, part int, bytes_before long, rows_before long")
    cell = Window.partitionBy("range_id", "part").orderBy("key", "doc_id", "text_crc32", "size")
    group = Window.partitionBy("range_id", "part", "key")
    run = split.withColumn("_end", F.sum("size").over(cell.rowsBetween(Window.unboundedPreceding, 0))).withColumn("_row", F.row_number().over(cell).cast("long"))
    run = run.withColumn("_group", F.sum("size").over(group)).withColumn("_first", F.min(F.col("_end") - F.col("size")).over(group))
    small = (F.col("_group") <= F.lit(max(1.0, together * share))) & F.col("parts").isNull()
    middle = F.when(small, F.col("_first") + F.col("_group") / 2).otherwise(F.col("_end") - F.col("size") / 2)
    placed = run.join(F.broadcast(places), ["range_id", "part"]).withColumn("shard", F.least(F.floor((F.col("bytes_before") + middle) / F.lit(share)), F.lit(shards - 1)).cast("int"))
    placed = materialise(placed.select("doc_id", "size", "text_crc32", "shard", (F.col("rows_before") + F.col("_row") - 1).alias("place")), "shard-places")
    starts = F.broadcast(placed.groupBy("shard").agg(F.min("place").alias("_start")))  # at most ``shards`` rows
    return placed.join(starts, "shard").select("doc_id", "size", "text_crc32", "shard", (F.col("place") - F.col("_start")).alias("slot"))
