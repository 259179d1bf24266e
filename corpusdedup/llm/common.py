"""What the operators of this subpackage share: tables in the shared folder, safe column names, Arrow slices."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from corpusdedup.plans.shared import fitted, materialise

#: Bytes of text that an Arrow operator holds at once, besides a single longer text.
SLICE_BYTES = 1 << 20


def text_bytes(column: str = "text") -> Column:
    """UTF-8 bytes of a text column; null becomes empty."""
    return F.coalesce(F.col(column).cast("binary"), F.lit(b""))


def slices(batch: pa.RecordBatch, column: str, limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut an Arrow batch so that each part holds at most ``limit`` bytes of ``column``, or one row."""
    if batch.num_rows == 0:
        return
    i = batch.schema.get_field_index(column)
    sizes = np.array([len(x) if x is not None else 0 for x in map(_buffer, batch.column(i))], dtype=np.int64)
    start, held = 0, 0
    for k, n in enumerate(sizes.tolist()):
        if held + n > limit and k > start:
            yield batch.slice(start, k - start)
            start, held = k, 0
        held += n
    yield batch.slice(start, batch.num_rows - start)


def map_rows(df: DataFrame, run: Callable[[Iterable[pa.RecordBatch]], Iterator[pa.RecordBatch]], kept: int | None = None) -> DataFrame:
    """``df`` through a function of Arrow batches that gives its columns (the first ``kept``) back; columns go by number, for Spark can't pass names with dots."""
    kept = len(df.columns) if kept is None else kept
    fields = [T.StructField(str(k), f.dataType, f.nullable) for k, f in enumerate(df.schema.fields)]
    return df.toDF(*map(str, range(len(fields)))).mapInArrow(run, T.StructType(fields[:kept])).toDF(*df.columns[:kept])


def _buffer(x):
    return x.as_buffer() if x.is_valid else None


def thinned(rows: DataFrame, per_label: int, salt: str, *key: str) -> DataFrame:
    """Of the rows of each ``label`` about twice ``per_label``, or all if there are fewer, by a hash of their key; with the hash as ``_at``."""
    own = rows.withColumn("_at", F.pmod(F.xxhash64(*key, F.lit(salt)), F.lit(1 << 30)))
    draw = F.lit(False)
    for r in rows.groupBy("label").count().collect():  # a row for each label
        draw = draw | ((F.col("label") == r["label"]) & (F.col("_at") < int((1 << 30) * min(1.0, 2 * per_label / r["count"])) + 1))
    return own.where(draw)


def bounded_draw(rows: DataFrame, per_label: int, bytes_each: int, salt: str) -> list[tuple[int, str, bytes]]:
    """(doc_id, label, text) of a draw from rows of these columns: of each label at most so many rows and bytes of text.

    Rows are drawn by a hash of id and text; those above the bound of bytes are not drawn.  Sorted.
    """
    some = thinned(rows.where(F.octet_length("text") <= bytes_each), per_label, salt, "doc_id", "text")
    first = Window.partitionBy("label").orderBy("_at", "doc_id").rowsBetween(Window.unboundedPreceding, 0)
    some = some.withColumn("_n", F.count("*").over(first)).withColumn("_bytes", F.sum(F.octet_length("text")).over(first))
    found = some.where((F.col("_n") <= per_label) & (F.col("_bytes") <= bytes_each)).select("doc_id", "label", "text").collect()
    return sorted(((r["doc_id"], r["label"], bytes(r["text"])) for r in found), key=lambda r: (r[0] is None, r[0] or 0, r[1], r[2]))


def marked_draw(docs: DataFrame, marked: DataFrame, per_label: int, bytes_each: int, salt: str) -> list[tuple[int, str, bytes]]:
    """The same from documents whose labels are in a table of their own (doc_id, label): ids are thinned before texts are looked at."""
    some = materialise(thinned(marked, per_label, salt, "doc_id").drop("_at"), "marked")
    texts = docs.where("text is not null").select(F.col("doc_id").cast("long").alias("doc_id"), text_bytes().alias("text"))
    return bounded_draw(materialise(texts.join(fitted(some, 16), "doc_id"), "marked-texts"), per_label, bytes_each, salt)


def portable_unit(key: Column, salt: int) -> Column:
    """A number in (0, 1) fixed by the key: what a sample by rank is drawn with."""
    return (F.pmod(F.xxhash64(key, F.lit(salt)), F.lit(1 << 52)) + F.lit(0.5)) / F.lit(float(1 << 52))


def unused(columns: list[str], *names: str) -> list[str]:
    """The names, each with as many underscores before it as keep it apart from the columns."""
    taken, out = {c.lower() for c in columns}, []
    for n in names:
        while n.lower() in taken:
            n = "_" + n
        taken.add(n.lower())
        out.append(n)
    return out


def quoted(column: str) -> Column:
    """A column by its exact name, dots and all."""
    return F.col(f"`{column.replace('`', '``')}`")


def gathered(batches: Iterable[pa.RecordBatch], limit: int, rows: int = 1 << 13) -> Iterator[tuple[list, list[bytes]]]:
    """(ids, texts) of the two columns of Arrow batches, whatever their size: runs of at most so many rows with at most ``limit`` bytes of text, or one row."""
    ids, texts, held = [], [], 0
    for batch in batches:
        for part in slices(batch, batch.schema.names[1], limit):
            for i, t in zip(part.column(0).to_pylist(), part.column(1).to_pylist()):
                if texts and (held + len(t) > limit or len(texts) == rows):
                    yield ids, texts
                    ids, texts, held = [], [], 0
                ids.append(i), texts.append(t)
                held += len(t)
    if texts:
        yield ids, texts


#: Rows and bytes of an Arrow batch where they carry whole texts; a batch ends with the row that reaches the bytes.
BATCH_ROWS, BATCH_BYTES = 512, 1 << 20


@contextmanager
def small_batches(spark: SparkSession, rows: int = BATCH_ROWS, size: int = BATCH_BYTES) -> Iterator[None]:
    """Arrow batches of at most so many rows and about so many bytes for what is written inside the block; the session's own settings hold again after it."""
    own = {"spark.sql.execution.arrow.maxRecordsPerBatch": str(rows), "spark.sql.execution.arrow.maxBytesPerBatch": str(size)}
    before = {key: spark.conf.get(key) for key in own}
    try:
        for key, value in own.items():
            spark.conf.set(key, value)
        yield
    finally:
        for key, value in before.items():
            spark.conf.set(key, value)
