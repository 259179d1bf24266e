"""Intermediate tables in the folder that the driver and all executors share."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


#: The folders made for sessions on one machine that name none.
_own: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """The session's spark.checkpoint.dir.  Where it is unset, a folder of our own, but on one machine only."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        sc = spark.sparkContext
        if sc.master.split("[")[0] != "local":
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        if sc.applicationId not in _own:
            _own[sc.applicationId] = tempfile.mkdtemp(prefix="shared-")
        found = _own[sc.applicationId]
    return found.rstrip("/")


#: Paths of the tables written so far and not deleted, oldest first.
_written: list[str] = []


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it back.

    The lineage ends there, so a lost executor costs the tasks that it ran and nothing else.  Tables stay until ``releasing``
    deletes them, for a result that isn't computed yet may read them.
    """
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _written.append(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def paths_of(*tables: DataFrame) -> set[str]:
    """Folders of the written tables that these results read directly."""
    return {f.rpartition("/")[0] for t in tables for f in t.inputFiles()}


def delete(spark: SparkSession, *tables: DataFrame) -> None:
    """Delete written tables that nothing needs any more."""
    for path in paths_of(*tables):
        _delete(spark, path)
        _written[:] = [p for p in _written if p.rpartition("/")[2] != path.rpartition("/")[2]]


def _delete(spark: SparkSession, path: str) -> None:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


@contextmanager
def releasing(spark: SparkSession) -> Iterator[Callable[..., None]]:
    """Delete the tables written inside the block at its end, but for those handed to the function that it gives.

    What is handed over must be written itself: what it was computed from goes.
    """
    first, kept = len(_written), set()
    try:
        yield lambda *tables: kept.update(paths_of(*tables))
    finally:
        mine, names = _written[first:], {p.rpartition("/")[2] for p in kept}
        del _written[first:]
        for path in mine:
            if path.rpartition("/")[2] in names:
                _written.append(path)
                continue
            _delete(spark, path)


#: Whether the shuffle files of a query go at its end, not when the driver happens to collect its garbage.
SHUFFLES_GO = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextmanager
def dropping_shuffles(spark: SparkSession) -> Iterator[None]:
    """Delete the shuffle files of each query that the block starts when that query ends.

    For blocks whose queries meet in written tables only: a result that is computed twice would miss its files.
    """
    before = spark.conf.get(SHUFFLES_GO, None)
    spark.conf.set(SHUFFLES_GO, "true")
    try:
        yield
    finally:
        spark.conf.unset(SHUFFLES_GO) if before is None else spark.conf.set(SHUFFLES_GO, before)


#: Estimated bytes up to which ``fitted`` marks a table for broadcasting.
BROADCAST_BYTES = 24 << 20


def fitted(table: DataFrame, row_bytes: int, limit: int = BROADCAST_BYTES) -> DataFrame:
    """``table``, marked for broadcasting if its counted rows take at most ``limit`` bytes; else left to a shuffled join.

    The table is counted, so pass a written one.
    """
    return F.broadcast(table) if table.count() * row_bytes <= limit else table


#: Estimated bytes a core above which ``spread`` leaves an input as it is.
SPREAD_BYTES = 16 << 20


def spread(docs: DataFrame) -> DataFrame:
    """Over all cores, where a small input comes in fewer splits than there are; large inputs stay as they are.

    The estimate of the plan's size comes first: asking for splits runs the shuffles that the input may hold.
    """
    n = docs.sparkSession.sparkContext.defaultParallelism
    if int(str(docs._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())) > n * SPREAD_BYTES:
        return docs
    return docs.repartition(n, "doc_id") if docs.rdd.getNumPartitions() < n else docs
