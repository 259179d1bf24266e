"""Incremental deduplication: each arriving batch against itself and against a stored index of band keys.

The first document of a group to arrive survives.  That equals the batch result if ids arrive in ascending order and no later
document bridges two groups that were apart until then.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from corpusdedup.config import DedupConfig
from corpusdedup.operators.compare import verify_pairs
from corpusdedup.operators.normalize import clean
from corpusdedup.operators.signatures import band_rows, signatures
from corpusdedup.plans.pipelines import keys_only_pairs
from corpusdedup.operators.graph import connected_components
from corpusdedup.plans.shared import materialise


#: Ranges of keys, and classes of documents, that the index is cut into: a batch reads those that it has keys in.
PARTS = 64


def key_part(bucket: Column) -> Column:
    """The range of a 64-bit key."""
    return F.shiftrightunsigned(bucket, 58).cast("int")


def doc_part(doc: Column) -> Column:
    return F.pmod(F.xxhash64(doc), F.lit(PARTS)).cast("int")


class SignatureIndex:
    """Kept documents' signatures and band keys as Parquet, by batch and part: a batch that runs again replaces its own, a look-up reads its parts only."""

    SIGS, KEYS = "doc_id long, sig array<int>, batch_id long, part int", "doc_id long, band int, bucket long, batch_id long, part int"

    def __init__(self, spark: SparkSession, path: str) -> None:
        self.spark, self.path = spark, path

    def _read(self, part: str, schema: str, before: int, wanted: DataFrame | None) -> DataFrame:
        path = f"{self.path}/{part}"
        hadoop = self.spark._jvm.org.apache.hadoop.fs.Path(path)
        if not hadoop.getFileSystem(self.spark._jsc.hadoopConfiguration()).exists(hadoop):
            return self.spark.createDataFrame([], schema)
        rows = self.spark.read.schema(schema).parquet(path).where(F.col("batch_id") < before)
        if wanted is None:
            return rows
        parts = [r["part"] for r in wanted.select("part").distinct().collect()]  # at most ``PARTS``
        return rows.where(F.col("part").isin(parts))

    def sigs(self, before: int, wanted: DataFrame | None = None) -> DataFrame:
        """Signatures of earlier batches: all, or of the parts of ``wanted``."""
        return self._read("sigs", self.SIGS, before, wanted)

    def keys(self, before: int, wanted: DataFrame | None = None) -> DataFrame:
        return self._read("keys", self.KEYS, before, wanted)

    def append(self, sig: DataFrame, cfg: DedupConfig, batch: int) -> None:
        own = sig.select("doc_id", "sig").withColumn("part", doc_part(F.col("doc_id")))
        own.repartitionByRange("part", "doc_id").sortWithinPartitions("part", "doc_id").write.mode("overwrite").partitionBy("part").parquet(f"{self.path}/sigs/batch_id={batch}")
        keys = band_rows(sig, cfg, "exact_band", None).select("doc_id", "band", "bucket").withColumn("part", key_part(F.col("bucket")))
        keys.repartitionByRange("part", "bucket").sortWithinPartitions("part", "bucket").write.mode("overwrite").partitionBy("part").parquet(f"{self.path}/keys/batch_id={batch}")


def dedup_batch(docs: DataFrame, batch: int, index: SignatureIndex, cfg: DedupConfig = DedupConfig()) -> DataFrame:
    """The documents of a batch that neither an earlier batch nor an earlier document of this one resembles; they join the index."""
    own = materialise(clean(docs, cfg).dropDuplicates(["doc_id"]), "batch")
    sig = materialise(signatures(own, cfg), "batch-signatures")
    keys = band_rows(sig, cfg, "exact_band", None).select(F.col("doc_id").alias("u"), "band", "bucket").withColumn("part", key_part(F.col("bucket")))
    met = keys.join(index.keys(batch, keys).select(F.col("doc_id").alias("v"), "band", "bucket", "part"), ["part", "band", "bucket"])
    seen = materialise(met.select("u", "v").distinct(), "batch-seen")
    both = sig.select("doc_id", "sig").union(index.sigs(batch, seen.select(doc_part(F.col("v")).alias("part"))).select("doc_id", "sig"))
    known = materialise(verify_pairs(seen, both, cfg).select(F.col("u").alias("doc_id")).distinct(), "batch-known")
    new = materialise(sig.join(known, "doc_id", "left_anti"), "batch-new")
    groups = connected_components(keys_only_pairs(new, cfg).select("u", "v"))
    gone = materialise(groups.where("node <> component").select(F.col("node").alias("doc_id")), "batch-gone")
    kept = new.join(gone, "doc_id", "left_anti")
    index.append(kept, cfg, batch)
    return own.join(index.sigs(batch + 1).where(F.col("batch_id") == batch).select("doc_id"), "doc_id", "left_semi")


def stream_dedup(stream: DataFrame, index_path: str, out_path: str, checkpoint: str, cfg: DedupConfig = DedupConfig()) -> StreamingQuery:
    """Run ``dedup_batch`` on every micro-batch; a batch that is replayed replaces its own output and index partitions."""

    def each(docs: DataFrame, batch: int) -> None:
        index = SignatureIndex(docs.sparkSession, index_path)
        dedup_batch(docs, batch, index, cfg).write.mode("overwrite").parquet(f"{out_path}/batch_id={batch}")

    return stream.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
