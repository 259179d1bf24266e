"""Whole pipelines: documents to decisions, with the seconds of each phase."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusdedup.config import DedupConfig
from corpusdedup.operators.bucketing import buckets_for
from corpusdedup.operators.compare import compare, crowded_pairs
from corpusdedup.operators.exact import copies_of, exact_duplicates, exact_minhash_pairs
from corpusdedup.operators.graph import connected_components
from corpusdedup.operators.normalize import clean
from corpusdedup.operators.select import apply_dedup, drop_list, select_survivors
from corpusdedup.operators.signatures import band_rows, signatures
from corpusdedup.plans.shared import fitted, materialise, releasing, spread
from corpusdedup.plans.store import HashStore, streamed_compare

PLANS = ("dense", "stream", "scale", "cpu_baseline", "gpu_baseline", "exact_minhash", "exact_text", "none")


@dataclass
class DedupResult:
    corpus: DataFrame  # cleaned documents
    pairs: DataFrame  # u, v, matches
    clusters: DataFrame  # node, component
    decisions: DataFrame  # doc_id, cluster, keep
    seconds: dict[str, float] = field(default_factory=dict)

    @property
    def drop(self) -> DataFrame:
        return drop_list(self.decisions)

    @property
    def kept(self) -> DataFrame:
        return apply_dedup(self.corpus, self.drop)

    def metrics(self, run: str) -> DataFrame:
        """run, phase, key, value: the seconds of each phase."""
        rows = [(run, phase, "seconds", s) for phase, s in self.seconds.items()]
        return self.corpus.sparkSession.createDataFrame(rows, "run string, phase string, key string, value double")


def find_pairs(docs: DataFrame, cfg: DedupConfig, plan: str, verify: bool = True, reduce: bool = True, collapse: bool | None = None, seconds: dict[str, float] | None = None, even: bool = True, pipelined: bool = True) -> DataFrame:
    """u, v, matches by one of ``PLANS`` over cleaned documents.

    ``dense``: few large buckets, all pairs.  ``stream``: the same from a hash store in sweeps.  ``scale``: buckets of equal
    bands, keys only exchanged, equal texts collapsed first.  ``cpu_baseline``: SHA-1, equal bands, anchor.  ``gpu_baseline``:
    Murmur3, MD5 of the band, all signatures exchanged with every band, anchor.  ``even``: see to it that all cores have input.  Without
    ``pipelined`` texts are written before they are hashed, and sweeps run one after the other.
    """
    seconds = seconds if seconds is not None else {}
    spark = docs.sparkSession
    began = time.time()
    if plan == "none":
        return spark.createDataFrame([], "u long, v long, matches int")
    if plan == "exact_text":
        groups = exact_duplicates(docs).where("doc_id <> cluster")
        return groups.select(F.col("cluster").alias("u"), F.col("doc_id").alias("v"), F.lit(cfg.n_hashes).alias("matches"))
    if plan == "cpu_baseline":
        cfg = cfg.but(family="sha1")
    if plan == "gpu_baseline":
        cfg = cfg.but(family="murmur3")
    copies, one_text = None, collapse if collapse is not None else plan == "scale"
    k = buckets_for(docs, cfg) if plan in ("dense", "stream") else None
    docs = spread(docs) if even else docs
    sig = materialise(signatures(docs if pipelined else materialise(docs, "texts"), cfg, k, text_key=one_text), "signatures")
    if one_text:
        copies = copies_of(sig)
        if plan != "scale":
            sig = sig.join(fitted(materialise(copies.select(F.col("v").alias("doc_id")), "text-copies"), 8), "doc_id", "left_anti")
    seconds["generation"] = time.time() - began
    began = time.time()
    if plan == "exact_minhash":
        pairs = exact_minhash_pairs(sig, cfg, reduce=reduce)
    elif plan == "dense":
        pairs = compare(band_rows(sig, cfg), cfg, reduce=reduce)
    elif plan == "stream":
        store = HashStore(spark).write(band_rows(sig, cfg))
        pairs = streamed_compare(store, cfg, k, cfg.buckets_per_pass or max(1, k // 4), reduce=reduce, pipelined=pipelined)
    elif plan == "cpu_baseline":
        pairs = compare(band_rows(sig, cfg, "exact_band"), cfg, "anchor", verify=verify, reduce=False)
    elif plan == "gpu_baseline":
        pairs = compare(band_rows(sig, cfg, "md5"), cfg, "anchor", verify=verify, reduce=False)
    elif plan == "scale":
        pairs = keys_only_pairs(sig, cfg, reduce)
    else:
        raise ValueError(f"no such plan: {plan}")
    if copies is not None:
        pairs = pairs.union(copies.select("u", "v", F.lit(cfg.n_hashes).alias("matches")))
    pairs = pairs.groupBy("u", "v").agg(F.max("matches").alias("matches"))
    pairs = materialise(pairs, "pairs")
    seconds["comparison"] = time.time() - began
    return pairs


def keys_only_pairs(sig: DataFrame, cfg: DedupConfig, reduce: bool = True) -> DataFrame:
    """Pairs in buckets of equal bands: keys are exchanged and singletons dropped before any signature travels.

    With a ``text_key`` only the least id of equal texts takes part.  With ``reduce`` an oversize bucket is first compared with
    its head, and what that connects is not compared again with itself.
    """
    text = ["text_key"] if "text_key" in sig.columns else []
    keys = band_rows(sig.withColumn("text_key", F.xxhash64("text_key")) if text else sig, cfg, "exact_band", *(text or [None]))
    # Bands in which the same documents meet are told by hashes of the set; one of them is enough.
    mark = lambda salt: F.bit_xor(F.xxhash64("doc_id", F.lit(salt)))
    told = [F.count("*").alias("n"), F.min("doc_id").alias("head"), mark(1).alias("s"), mark(2).alias("t")]
    shared = keys.groupBy("band", "bucket").agg(*told, *[F.min(c).alias("lo") for c in text], *[F.max(c).alias("hi") for c in text]).where("lo <> hi" if text else "n > 1")
    shared = shared.groupBy("n", "head", "s", "t").agg(F.min(F.struct("band", "bucket")).alias("b")).select("b.band", "b.bucket", "n", "head")
    members = keys.join(shared, ["band", "bucket"])
    if text:
        members = members.groupBy("band", "bucket", "n", "head", "text_key").agg(F.min("doc_id").alias("doc_id")).drop("text_key")
    members = materialise(members, "shared-bands")
    found = compare((members.where(F.col("n") <= cfg.d_max) if reduce else members).join(sig.select("doc_id", "sig"), "doc_id"), cfg, reduce=reduce)
    if reduce and (members.agg(F.max("n")).first()[0] or 0) > cfg.d_max:
        found = found.union(crowded_pairs(members.where(F.col("n") > cfg.d_max), sig, cfg))
    return found


def dedup(docs: DataFrame, cfg: DedupConfig = DedupConfig(), plan: str = "scale", verify: bool = True, components: str = "contract", nfc: bool = True, reduce: bool = True, collapse: bool | None = None, labels: DataFrame | None = None, pipelined: bool = True) -> DedupResult:
    """Clean, hash, compare, connect, choose.

    Null texts and those below ``cfg.min_chars`` are no part of the corpus; ids must be unique; an empty corpus gives empty
    results.
    """
    seconds: dict[str, float] = {}
    corpus = clean(spread(docs), cfg, nfc)
    with releasing(docs.sparkSession) as keep:
        pairs = find_pairs(corpus, cfg, plan, verify, reduce, collapse, seconds, even=False, pipelined=pipelined)
        keep(pairs)
    began = time.time()
    with releasing(docs.sparkSession) as keep:
        clusters = materialise(connected_components(pairs.select("u", "v"), components, written=True), "clusters")
        keep(clusters)
    decisions = select_survivors(clusters, cfg.keep, corpus, labels)
    seconds["union"] = time.time() - began
    return DedupResult(corpus, pairs, clusters, decisions, seconds)
