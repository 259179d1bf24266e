"""Arrow batches that carry texts are bounded in bytes, in each stage of the pipeline that sends texts to Python."""

import pyarrow as pa
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from corpusdedup.llm import common, decontaminate, language, packing

LIMITS = ("spark.sql.execution.arrow.maxRecordsPerBatch", "spark.sql.execution.arrow.maxBytesPerBatch")


def test_batches_end_at_their_bytes(spark):
    def run(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([b.num_rows]), pa.array([b.nbytes])], names=["n", "size"])

    docs = spark.range(0, 600, 1, 1).select(F.repeat(F.lit("x"), 10_000).alias("text"))
    before = [spark.conf.get(k) for k in LIMITS]
    with common.small_batches(spark):
        rows = docs.mapInArrow(run, "n long, size long").collect()
    assert sum(r.n for r in rows) == 600 and max(r.size for r in rows) < common.BATCH_BYTES + 20_000
    assert [spark.conf.get(k) for k in LIMITS] == before


@pytest.mark.parametrize("name, module, tables", [("language", language, ["unidentified"]), ("decontamination", decontaminate, ["postings", "contaminated"]), ("packing", packing, ["pieces"])])
def test_a_stage_sends_texts_in_small_batches(spark, sf, monkeypatch, name, module, tables):
    seen, write = {}, module.materialise
    monkeypatch.setattr(module, "materialise", lambda df, own: (seen.__setitem__(own, [spark.conf.get(k) for k in LIMITS]), write(df, own))[1])
    result = dict(corpus_pipeline.STAGES)[name](spark, spark.read.parquet(f"{sf}/documents.parquet"), sf)
    assert {t: seen[t] for t in tables} == {t: [str(common.BATCH_ROWS), str(common.BATCH_BYTES)] for t in tables}
    # What the caller runs later, under its own settings, sends no text to Python.
    assert "InArrow" not in result._jdf.queryExecution().executedPlan().toString()


def test_a_block_of_the_index_gathers_several_batches(spark, monkeypatch):
    docs = spark.range(0, 40, 1, 1).select(F.col("id").alias("doc_id"), F.concat_ws(" ", F.lit("one two"), F.col("id")).alias("text"))
    key, before = LIMITS[0], spark.conf.get(LIMITS[0])
    spark.conf.set(key, "3")
    try:
        rows = decontaminate.build_index(docs).collect()
    finally:
        spark.conf.set(key, before)
    assert [r.doc_ids for r in rows] == [list(range(40))]


def test_gathered_runs_are_bounded():
    rows = [(1, b"a" * 4), (2, b""), (3, b"b" * 7), (4, b"c" * 30), (None, b"d" * 3), (6, b"e" * 7), (7, b""), (8, b""), (9, b"")]
    batch = lambda own: pa.RecordBatch.from_arrays([pa.array([r[0] for r in own], pa.int64()), pa.array([r[1] for r in own], pa.binary())], names=["doc_id", "text"])
    for step in (1, 2, 9):
        got = list(common.gathered([batch(rows[k : k + step]) for k in range(0, 9, step)] + [batch([])], 10, rows=4))
        assert [ids for ids, _ in got] == [[1, 2], [3], [4], [None, 6, 7, 8], [9]]
        assert [t for _, own in got for t in own] == [t for _, t in rows]
