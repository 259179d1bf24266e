"""Readers and writers of corpora.  Schemas are declared: nothing is inferred on the way in."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusdedup.plans.shared import shared_dir

SCHEMA = "doc_id long, text string"


def read_corpus(spark: SparkSession, path: str, fmt: str = "parquet", schema: str = SCHEMA, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """A corpus with at least doc_id and text from Parquet, ORC, JSON lines or CSV; ``text`` files give a row for each file line."""
    if fmt == "text":
        return spark.read.text(path).select(F.monotonically_increasing_id().alias("doc_id"), F.col("value").alias("text"))
    reader = spark.read if fmt in ("parquet", "orc") else spark.read.schema(schema)
    df = reader.format(fmt).load(path)
    return df.withColumnsRenamed({id_col: "doc_id", text_col: "text"})


def with_source_file(df: DataFrame) -> DataFrame:
    """Add ``src_file``: the file that each row of a file scan came from."""
    return df.select("*", F.col("_metadata.file_path").alias("src_file"))


def stream_corpus(spark: SparkSession, path: str, fmt: str = "parquet", schema: str = SCHEMA, files_per_batch: int = 16) -> DataFrame:
    """An unbounded corpus: each file that appears in a folder is read once."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).format(fmt).load(path)


def write_corpus(df: DataFrame, path: str, fmt: str = "json", by: str | None = None) -> None:
    w = df.write.mode("overwrite")
    (w.partitionBy(by) if by else w).format(fmt).save(path)


def round_trip(df: DataFrame, fmt: str, by: str | None = None) -> str:
    """Write to the shared folder; returns the path."""
    path = f"{shared_dir(df.sparkSession)}/round-trip-{uuid.uuid4().hex}"
    write_corpus(df, path, fmt, by)
    return path


def pages_as_documents(pages: DataFrame) -> DataFrame:
    """Raw pages as a corpus: scripts, styles and tags out, white space collapsed."""
    body = F.regexp_replace(F.regexp_replace("html", "(?s)<(script|style)[^>]*>.*?</(script|style)>", " "), "<[^>]+>", " ")
    return pages.select(F.col("page_id").alias("doc_id"), F.trim(F.regexp_replace(body, r"\s+", " ")).alias("text"))


def conversations_as_documents(turns: DataFrame) -> DataFrame:
    """Conversations as a corpus: turns in order, one to a line."""
    own = turns.groupBy(F.col("conv_id").alias("doc_id")).agg(F.array_sort(F.collect_list(F.struct("turn", "text"))).alias("m"))
    return own.select("doc_id", F.array_join(F.transform("m", lambda x: x["text"]), "\n").alias("text"))
