"""Exact methods: identical texts, and MinHash without locality-sensitive hashing."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from corpusdedup.config import DedupConfig
from corpusdedup.operators.compare import compare, crowded_pairs, verify_pairs
from corpusdedup.operators.graph import connected_components
from corpusdedup.plans.shared import fitted, materialise


def exact_duplicates(docs: DataFrame, key: str = "hash") -> DataFrame:
    """doc_id, cluster, copies of the documents whose text another has too: cluster is the least id of the group.

    ``hash`` groups by SHA-256, ``text`` by the text itself.
    """
    k = F.sha2("text", 256) if key == "hash" else F.col("text")
    own = docs.where("text is not null").select("doc_id", k.alias("_k"))
    heads = own.groupBy("_k").agg(F.min("doc_id").alias("cluster"), F.count("*").alias("copies")).where("copies > 1")
    return own.join(heads, "_k").select("doc_id", "cluster", "copies")


def copies_of(sig: DataFrame) -> DataFrame:
    """Edges (u, v) from the least id of each text to its copies, by ``text_key`` of written signatures: texts are not read again."""
    keys = sig.where("text_key is not null").select("doc_id", "text_key")
    heads = keys.groupBy("text_key").agg(F.min("doc_id").alias("u"), F.count("*").alias("copies")).where("copies > 1")
    return keys.join(heads, "text_key").where("doc_id <> u").select("u", F.col("doc_id").alias("v"))


def signature_copies(sig: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Edges (u, v) from the least id of each signature to the others that have it, and a row of each signature."""
    own = sig.where("sig is not null")
    keyed = own.select("doc_id", F.unhex(F.sha2(F.array_join("sig", ","), 256)).alias("text_key"))
    copies = materialise(copies_of(keyed), "signature-copies")
    return copies, own.join(fitted(copies.select(F.col("v").alias("doc_id")), 8), "doc_id", "left_anti")


def agreement_keys(sig: DataFrame, cfg: DedupConfig) -> DataFrame:
    """doc_id, key: 64-bit keys of which two signatures of enough equal entries share at least one, wherever they differ.

    The positions fall into one group more than half the mismatches that a pair may have, so in some group it has one at most.
    A key stands for a group without one of its positions.
    """
    groups = np.array_split(np.arange(cfg.n_hashes), (cfg.n_hashes - cfg.min_matches) // 2 + 1)
    starts, group = np.array([g[0] for g in groups]), np.repeat(np.arange(len(groups)), [len(g) for g in groups])
    salt = np.random.Generator(np.random.PCG64(cfg.seed)).integers(0, 1 << 64, (2, cfg.n_hashes), dtype=np.uint64)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(0, batch.num_rows, 256):
                part = batch.slice(k, 256)
                x = part.column(1).flatten().to_numpy(zero_copy_only=False).reshape(part.num_rows, -1).astype(np.uint64) + salt[0]
                for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
                    x = (x ^ (x >> np.uint64(shift))) * np.uint64(factor)
                x ^= x >> np.uint64(31)
                key = np.add.reduceat(x, starts, axis=1)[:, group] - x + salt[1]
                ids = np.repeat(part.column(0).to_numpy(zero_copy_only=False), cfg.n_hashes)
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(key.ravel().view(np.int64))], names=["doc_id", "key"])

    return sig.where("sig is not null").select("doc_id", "sig").mapInArrow(run, "doc_id long, key long")


def agreeing(sig: DataFrame, cfg: DedupConfig) -> DataFrame:
    """band (0), bucket, n, head, doc_id: the members of shared agreement keys, how many they are and the least of them.

    Of keys that the same documents share, as copies do in all of theirs, one is left; sets are told by hashes.
    """
    shared = agreement_keys(sig, cfg).withColumn("n", F.count("*").over(Window.partitionBy("key"))).where("n > 1")
    shared = materialise(shared, "agreeing")
    mark = lambda salt: F.bit_xor(F.xxhash64("doc_id", F.lit(salt)))
    sets = shared.groupBy("key").agg(F.max("n").alias("n"), F.min("doc_id").alias("head"), mark(1).alias("s"), mark(2).alias("t"))
    once = materialise(sets.groupBy("n", "head", "s", "t").agg(F.min("key").alias("key")).select("key", "head"), "agreeing-sets")
    return shared.join(fitted(once, 16), "key").select(F.lit(0).alias("band"), F.col("key").alias("bucket"), "n", "head", "doc_id")


def exact_minhash_pairs(sig: DataFrame, cfg: DedupConfig, method: str = "join", reduce: bool = False) -> DataFrame:
    """u < v, matches of all pairs of enough equal entries, whatever their buckets.

    Both methods meet candidates by ``agreement_keys``, which lose none, so entries that many unlike documents share bring nobody
    together.  ``join`` pairs the members of a key and looks both signatures up; ``tiles`` compares all documents that shared keys
    connect, in blocks of rows, so a signature travels once and not with each of its keys.

    With ``reduce`` the pairs left connect the same documents and no more: copies of a signature hang on the least of them, and
    the members of a key are compared with its head first, so a large group is not expanded into all its pairs.
    """
    if reduce:
        copies, single = signature_copies(sig)
        members = materialise(agreeing(single, cfg), "agreeing-members")
        return crowded_pairs(members, single, cfg).union(copies.select("u", "v", F.lit(cfg.n_hashes).alias("matches")))
    members = materialise(agreeing(sig, cfg), "agreeing-members")
    if method == "join":
        a, b = members.select("bucket", F.col("doc_id").alias("u")), members.select("bucket", F.col("doc_id").alias("v"))
        return verify_pairs(a.join(b, "bucket").where("u < v").select("u", "v").distinct(), sig, cfg)
    heads = members.groupBy("bucket").agg(F.min("doc_id").alias("u"))
    linked = members.join(heads, "bucket").where("doc_id <> u").select("u", F.col("doc_id").alias("v")).distinct()
    groups = materialise(connected_components(linked), "agreeing-groups")
    rows = groups.select(F.lit(0).alias("band"), F.col("component").alias("bucket"), F.col("node").alias("doc_id"))
    found = compare(rows.join(sig.select("doc_id", "sig"), "doc_id"), cfg, reduce=False)
    return found.groupBy("u", "v").agg(F.max("matches").alias("matches"))
