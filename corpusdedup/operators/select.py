"""Survivors of duplicate clusters and the corpus without the rest."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from corpusdedup.plans.shared import fitted


def select_survivors(clusters: DataFrame, keep: str = "min_id", docs: DataFrame | None = None, labels: DataFrame | None = None) -> DataFrame:
    """doc_id, cluster, keep for every member of a cluster (node, component).

    ``min_id`` keeps the least id, ``longest`` the longest text, ``best_quality`` a document marked 1 before one marked 0 or
    not at all; ties go to the least id.
    """
    own = clusters.select(F.col("node").alias("doc_id"), F.col("component").alias("cluster"))
    if keep == "min_id":
        return own.withColumn("keep", F.col("doc_id") == F.col("cluster"))
    if keep == "longest":
        own = own.join(docs.select("doc_id", F.char_length("text").alias("_w")), "doc_id", "left")
    elif keep == "best_quality":
        own = own.join(labels.groupBy("doc_id").agg(F.max("quality").alias("_w")), "doc_id", "left")
    else:
        raise ValueError(f"no such rule: {keep}")
    best = own.groupBy("cluster").agg(F.max(F.struct(F.coalesce("_w", F.lit(-1)), -F.col("doc_id"))).alias("_b"))
    return own.join(best.select("cluster", (-F.col("_b.col2")).alias("_best")), "cluster").select("doc_id", "cluster", (F.col("doc_id") == F.col("_best")).alias("keep"))


def drop_list(decisions: DataFrame) -> DataFrame:
    return decisions.where(~F.col("keep")).select("doc_id")


def apply_dedup(docs: DataFrame, drop: DataFrame) -> DataFrame:
    """The documents that aren't in the list; the list is broadcast only if its counted size fits."""
    return docs.join(fitted(drop, 8), "doc_id", "left_anti")


def ranked_members(clusters: DataFrame) -> DataFrame:
    """doc_id, cluster, rank of each member by id."""
    w = Window.partitionBy("component").orderBy("node")
    return clusters.select(F.col("node").alias("doc_id"), F.col("component").alias("cluster"), F.row_number().over(w).alias("rank"))


def portable_share(key: Column) -> Column:
    """A number in [0, 1) from the MD5 of a key as text: the same in every engine."""
    return F.conv(F.substring(F.md5(key.cast("string")), 1, 8), 16, 10).cast("double") / F.lit(float(1 << 32))


def sample_clusters(docs: DataFrame, clusters: DataFrame, share: float, rates: dict[str, float] | None = None, stratum: str = "lang") -> DataFrame:
    """doc_id, cluster, stratum of a sample that keeps clusters whole: a document outside any is a cluster of its own.

    A cluster is drawn by a hash of its id, at the rate of its stratum (that of the document it is named after; ``share`` where
    ``rates`` says nothing), so each stratum and each size of cluster is drawn at its rate.
    """
    own = docs.select("doc_id", stratum).join(clusters.select(F.col("node").alias("doc_id"), F.col("component").alias("cluster")), "doc_id", "left")
    own = own.withColumn("cluster", F.coalesce("cluster", "doc_id"))
    heads = own.where("doc_id = cluster").select("cluster", F.col(stratum).alias("stratum"))
    rate = F.lit(share)
    for value, r in (rates or {}).items():
        rate = F.when(F.col("stratum") == value, F.lit(r)).otherwise(rate)
    drawn = heads.where(portable_share(F.col("cluster")) < rate)
    return own.join(drawn, "cluster").select("doc_id", "cluster", "stratum")
