"""Event-time aggregates, duplicates online, joins of streams and stateful heads."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from typing import Any

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from corpusdedup.plans.shared import shared_dir

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def table_stream(spark: SparkSession, sf: str, name: str, schema: str) -> DataFrame:
    """A stream over a given table, be it one Parquet file or a folder of them.

    The bracket makes the path a pattern, which it must be for one file; a filter on file names would leave out the files of a folder.
    """
    return spark.readStream.schema(schema).parquet(f"{sf}/{name}.parque[t]")


def event_stream(spark: SparkSession, sf: str, watermark: str = "1 hour") -> DataFrame:
    own = table_stream(spark, sf, "events", EVENTS)
    return own.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark)


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over what there is and return its output; state and output lie in the shared folder."""
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", f"{base}/out").option("checkpointLocation", f"{base}/state").outputMode("append").trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{base}/out")
    # The last batch of a complete result replaces all before it.
    q = stream.writeStream.foreachBatch(lambda df, _: df.write.mode("overwrite").parquet(f"{base}/out")).option("checkpointLocation", f"{base}/state").outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{base}/out")


def windowed_counts(events: DataFrame, size: str, slide: str | None = None) -> DataFrame:
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return events.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "event_type", "n", "total")


def sessions(events: DataFrame, gap: str) -> DataFrame:
    own = events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return own.select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), "n")


def distinct_events(events: DataFrame) -> DataFrame:
    return events.dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id")


def clicks_before_purchases(events: DataFrame, buys: DataFrame, within: str = "10 minutes") -> DataFrame:
    """Pairs of a user's click and a purchase at most ``within`` later, of two streams."""
    a = events.where("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("u"), F.col("ts").alias("ta"))
    b = buys.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("v"), F.col("ts").alias("tb"))
    return a.join(b, F.expr(f"u = v AND tb >= ta AND tb <= ta + INTERVAL {within}")).select("click", "purchase")


def first_of_bucket(rows: DataFrame) -> DataFrame:
    """The least doc_id seen in each bucket so far, for a stream of (bucket, doc_id): the anchor of the bucket, kept as state."""

    def head(key: tuple[Any, ...], batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        least = min([int(p["doc_id"].min()) for p in batches] + ([state.get[0]] if state.exists else []))
        state.update((least,))
        yield pd.DataFrame({"bucket": [key[0]], "head": [least]})

    return rows.groupBy("bucket").applyInPandasWithState(head, "bucket long, head long", "head long", "update", GroupStateTimeout.NoTimeout)
