"""MinHash signatures and bucket ids: a fused Arrow kernel without any shuffle, and a relational engine."""

from __future__ import annotations

import hashlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusdedup.config import DedupConfig
from corpusdedup.functions.hashing import base_hash_column, char_grams, codes_of, remixed, signature

SCHEMA = "doc_id long, sig array<int>, buckets array<int>"


def word_codes(text: str) -> np.ndarray:
    """A number below 2^31 for each word, so that words can stand for characters."""
    return np.array([int.from_bytes(hashlib.md5(w.encode("utf-8", "surrogatepass")).digest()[:4], "big") >> 1 for w in text.split()], dtype=np.int64)


def dense_buckets(sig: np.ndarray, cfg: DedupConfig, k_buckets: int) -> np.ndarray:
    """Bucket id of each band: the sum of its rows modulo the number of buckets."""
    return sig.reshape(cfg.bands, cfg.rows).sum(axis=1) % k_buckets


def signatures(docs: DataFrame, cfg: DedupConfig = DedupConfig(), k_buckets: int | None = None, engine: str = "arrow", text_key: bool = False, method: str = "direct") -> DataFrame:
    """doc_id, sig, buckets of each document; null sig for a text without a shingle, null buckets without ``k_buckets``.

    The ``sql`` engine explodes shingles and takes minima by a partial and a final aggregate; it leaves such texts out.  With
    ``text_key`` the SHA-256 of the text comes along, from the same reading of the texts.  ``method`` evaluates polynomial hashes.
    """
    if engine == "sql":
        return _sql_signatures(docs, cfg, k_buckets)
    names = ["doc_id", "sig", "buckets"] + ["text_key"] * text_key

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ints = pa.list_(pa.int32())
        for batch in batches:
            ids = batch.column(0)
            for k in range(0, batch.num_rows, 256):
                sigs, buckets = [], []
                for t in batch.column(1).slice(k, 256).to_pylist():
                    s = signature(codes_of(t) if cfg.unit == "char" else word_codes(t), cfg, method) if t is not None else None
                    sigs.append(s), buckets.append(dense_buckets(s, cfg, k_buckets) if s is not None and k_buckets else None)
                own = [batch.column(2).slice(k, 256)] if text_key else []
                yield pa.RecordBatch.from_arrays([ids.slice(k, 256), pa.array(sigs, ints), pa.array(buckets, ints), *own], names=names)

    own = [F.unhex(F.sha2("text", 256)).alias("text_key")] if text_key else []
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", *own).mapInArrow(run, SCHEMA + ", text_key binary" * text_key)


def _sql_signatures(docs: DataFrame, cfg: DedupConfig, k_buckets: int | None) -> DataFrame:
    if cfg.family == "multibase" or cfg.unit != "char":
        raise ValueError("the SQL engine has one base hash over characters")
    grams = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.explode(char_grams(F.col("text"), cfg.k)).alias("g")).select("doc_id", base_hash_column(F.col("g"), cfg).alias("h"))
    least = grams.groupBy("doc_id").agg(*[F.min(x).alias(f"m{i}") for i, x in enumerate(remixed(F.col("h"), cfg))])
    sig = F.array(*[F.col(f"m{i}").cast("int") for i in range(cfg.n_hashes)])
    if not k_buckets:
        return least.select("doc_id", sig.alias("sig"), F.lit(None).cast("array<int>").alias("buckets"))
    band = [sum((F.col(f"m{j * cfg.rows + i}") for i in range(1, cfg.rows)), F.col(f"m{j * cfg.rows}")) % F.lit(k_buckets) for j in range(cfg.bands)]
    return least.select("doc_id", sig.alias("sig"), F.array(*[b.cast("int") for b in band]).alias("buckets"))


def signature_long(sig: DataFrame) -> DataFrame:
    """doc_id, pos, val: the signature matrix row by row."""
    return sig.where("sig is not null").select("doc_id", F.posexplode("sig").alias("pos", "val"))


def band_rows(sig: DataFrame, cfg: DedupConfig, key: str = "dense", beside: str | None = "sig") -> DataFrame:
    """doc_id, band, bucket, sig: a row for each band of each document, with another column (or none) than ``sig`` beside.

    ``dense`` takes the bucket ids made with the signature; ``exact_band`` a 64-bit hash of the band's rows; ``md5`` the MD5 of
    the rows as text.
    """
    own = sig.where("sig is not null")
    beside = [beside] if beside else []
    if key == "dense":
        return own.select("doc_id", F.posexplode("buckets").alias("band", "bucket"), *beside).withColumn("bucket", F.col("bucket").cast("long"))
    part = lambda j: F.slice("sig", j * cfg.rows + 1, cfg.rows)
    if key == "exact_band":
        keys = [F.xxhash64(part(j)) for j in range(cfg.bands)]
    elif key == "md5":
        keys = [F.conv(F.substring(F.md5(F.array_join(F.transform(part(j), lambda x: x.cast("string")), ",")), 1, 15), 16, 10).cast("long") for j in range(cfg.bands)]
    else:
        raise ValueError(f"no such band key: {key}")
    return own.select("doc_id", F.posexplode(F.array(*keys)).alias("band", "bucket"), *beside)
