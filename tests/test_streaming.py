import uuid

import pytest
from pyspark.sql import functions as F

from corpusdedup.config import DedupConfig
from corpusdedup.plans.pipelines import dedup
from corpusdedup.plans.shared import shared_dir
from corpusdedup.queries import streams
from corpusdedup.sources.corpus import conversations_as_documents, pages_as_documents, read_corpus, with_source_file, write_corpus
from corpusdedup.streaming.incremental import SignatureIndex, dedup_batch, stream_dedup
from corpusdedup.streaming.windows import drain, windowed_counts

CFG = DedupConfig()


def test_batches_in_ascending_order_equal_one_run(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    base = f"{shared_dir(spark)}/{uuid.uuid4().hex}"
    for k, (lo, hi) in enumerate(((0, 70), (70, 140), (140, 1000))):
        docs.where(f"doc_id >= {lo} and doc_id < {hi}").coalesce(1).write.mode("append").parquet(f"{base}/in")
        source = spark.readStream.schema("doc_id long, text string").parquet(f"{base}/in")
        stream_dedup(source, f"{base}/index", f"{base}/out", f"{base}/state").awaitTermination()
    kept = {r.doc_id for r in spark.read.parquet(f"{base}/out").collect()}
    assert kept == {r.doc_id for r in dedup(docs, plan="scale").kept.collect()}


def test_a_replayed_batch_changes_nothing(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").where("doc_id < 60").select("doc_id", "text")
    index = SignatureIndex(spark, f"{shared_dir(spark)}/{uuid.uuid4().hex}")
    first = {r.doc_id for r in dedup_batch(docs, 0, index).collect()}
    assert first == {r.doc_id for r in dedup_batch(docs, 0, index).collect()}
    assert dedup_batch(docs, 1, index).count() == 0


def test_late_rows_are_dropped(spark):
    base = f"{shared_dir(spark)}/{uuid.uuid4().hex}"
    rows = [("2024-01-01 00:05:00", 1), ("2024-01-01 03:00:00", 2), ("2024-01-01 03:01:00", 5), ("2024-01-01 00:06:00", 3), ("2024-01-01 06:00:00", 4), ("2024-01-01 06:01:00", 6)]
    for k, (ts, i) in enumerate(rows):
        spark.createDataFrame([(i, ts)], "event_id long, ts string").select("event_id", F.col("ts").cast("timestamp"), F.lit("x").alias("event_type"), F.lit(1.0).alias("value")).coalesce(1).write.mode("append").parquet(f"{base}/in")
    source = spark.readStream.schema("event_id long, ts timestamp, event_type string, value double").option("maxFilesPerTrigger", 1).parquet(f"{base}/in").withWatermark("ts", "10 minutes")
    got = {(str(r.start)[11:16], r.n) for r in drain(windowed_counts(source, "1 hour")).collect()}
    assert got == {("00:00", 1), ("03:00", 2)}


def test_sources(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    for fmt in ("json", "orc", "parquet"):
        path = f"{shared_dir(spark)}/{uuid.uuid4().hex}"
        write_corpus(docs, path, fmt)
        assert read_corpus(spark, path, fmt).exceptAll(docs).count() == 0
    assert with_source_file(spark.read.parquet(f"{sf}/documents.parquet")).select("src_file").distinct().count() == 1
    pages = pages_as_documents(spark.read.parquet(f"{sf}/pages.parquet"))
    assert pages.where(F.col("text").contains("<p>")).count() == 0 and pages.count() == 50
    assert conversations_as_documents(spark.read.parquet(f"{sf}/conversations.parquet")).select("doc_id").distinct().count() > 1


def test_sql_functions(spark):
    from corpusdedup.functions.registered import register

    register(spark)
    spark.createDataFrame([(1, "some text to sign"), (2, "some text to sign"), (3, None)], "doc_id long, text string").createOrReplaceTempView("_t")
    r = spark.sql("SELECT est_similarity(minhash_signature(a.text), minhash_signature(b.text)) AS s FROM _t a JOIN _t b ON a.doc_id = 1 AND b.doc_id = 2").first()
    assert r.s == 1.0
    rows = spark.sql("SELECT band, bucket FROM (SELECT minhash_signature(text) AS sig FROM _t WHERE doc_id = 1), LATERAL lsh_buckets(sig, 7)").collect()
    assert sorted(x.band for x in rows) == list(range(16)) and all(0 <= x.bucket < 7 for x in rows)


@pytest.mark.parametrize("name", ["op_stream_foreachbatch", "op_stream_stateful", "op_stream_dedup"])
def test_tables_in_folders_of_several_files(spark, sf, name):
    folder = f"{shared_dir(spark)}/{uuid.uuid4().hex}"
    for t in ("documents", "events"):
        spark.read.parquet(f"{sf}/{t}.parquet").repartition(3).write.parquet(f"{folder}/{t}.parquet")
    one, many = (sorted(map(tuple, streams.QUERIES[name](spark, at).collect())) for at in (sf, folder))
    assert one == many and one
