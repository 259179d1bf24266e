"""Streaming operations, run over the given tables to their end, and the batch SQL of the same result."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusdedup.plans.shared import shared_dir
from corpusdedup.queries import methods
from corpusdedup.streaming.incremental import stream_dedup
from corpusdedup.streaming.windows import clicks_before_purchases, distinct_events, drain, event_stream, first_of_bucket, sessions, table_stream, windowed_counts

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def op(name: str, sql: str | None = None):
    def add(f):
        QUERIES[f"op_stream_{name}"] = f
        if sql is not None:
            SQL[f"op_stream_{name}"] = sql
        return f

    return add


@op("tumbling", "SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2")
def tumbling(spark, sf):
    return drain(windowed_counts(event_stream(spark, sf), "1 hour"), "complete")


@op(
    "sliding",
    "SELECT time_bucket(INTERVAL 30 MINUTE, ts) - k * INTERVAL 30 MINUTE AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events, unnest([0, 1]) AS t(k) GROUP BY 1, 2",
)
def sliding(spark, sf):
    return drain(windowed_counts(event_stream(spark, sf), "1 hour", "30 minutes"), "complete")


@op(
    "session",
    "WITH g AS (SELECT *, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(ts) AS start, count(*) AS n FROM s GROUP BY user_id, k",
)
def session(spark, sf):
    return drain(sessions(event_stream(spark, sf), "30 minutes"), "complete")


@op(
    "watermark_late",
    "SELECT * FROM (SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2) WHERE start + INTERVAL 1 HOUR <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events)",
)
def watermark_late(spark, sf):
    """Append mode: windows that the watermark has closed, the rest stay in the state."""
    return drain(windowed_counts(event_stream(spark, sf), "1 hour"))


@op("dedup", "SELECT event_id, any_value(user_id) AS user_id FROM events GROUP BY 1")
def dedup_events(spark, sf):
    return drain(distinct_events(event_stream(spark, sf)))


@op(
    "stream_join",
    "SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE WHERE a.event_type = 'click' AND b.event_type = 'purchase'",
)
def stream_join(spark, sf):
    return drain(clicks_before_purchases(event_stream(spark, sf), event_stream(spark, sf)))


@op("stateful", methods.with_(", ".join((methods.SIG, methods.kk(), methods.DENSE)), "SELECT band * 4294967296 + bucket AS bucket, min(doc_id) AS head FROM bands GROUP BY 1"))
def stateful(spark, sf):
    """The anchor of every dense bucket of every band, as documents arrive."""
    from corpusdedup.operators.bucketing import buckets_for
    from corpusdedup.operators.normalize import clean
    from corpusdedup.operators.signatures import band_rows, signatures

    k = buckets_for(methods.docs(spark, sf), methods.CFG)
    own = table_stream(spark, sf, "documents", "doc_id long, text string")
    rows = band_rows(signatures(clean(own, methods.CFG), methods.CFG, k), methods.CFG, beside=None)
    return drain(first_of_bucket(rows.select((F.col("band") * (1 << 32) + F.col("bucket")).alias("bucket"), "doc_id")), "update")


_KEPT = ", ".join((methods.EXACT, methods.EXACT_BAND, methods.CANDIDATES, methods.VERIFIED, methods.CC))


@op("foreachbatch", methods.with_(_KEPT, "SELECT doc_id, md5(text) AS digest FROM docs WHERE doc_id NOT IN (SELECT doc_id FROM comp WHERE doc_id <> cluster)", True))
def foreachbatch(spark, sf):
    base = f"{shared_dir(spark)}/incremental-{uuid.uuid4().hex}"
    own = table_stream(spark, sf, "documents", "doc_id long, text string")
    stream_dedup(own, f"{base}/index", f"{base}/out", f"{base}/state").awaitTermination()
    return spark.read.schema("doc_id long, text string").parquet(f"{base}/out").select("doc_id", F.md5("text").alias("digest"))
