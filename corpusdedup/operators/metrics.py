"""Accuracy and cost measures."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusdedup.operators.bucketing import bucket_sizes


def fidelity(a: DataFrame, b: DataFrame, on: list[str], level: str, method: str) -> DataFrame:
    """One row: sizes of two sets of ids or pairs, what they share, and the measures; b is the reference."""
    both = a.select(on).distinct().withColumn("_a", F.lit(1)).join(b.select(on).distinct().withColumn("_b", F.lit(1)), on, "full_outer")
    one = both.agg(F.count("_a").alias("n_a"), F.count("_b").alias("n_b"), F.count(F.col("_a") + F.col("_b")).alias("n_both"), F.count("*").alias("n_any"))
    ratio = lambda x, y: F.when(F.col(y) == 0, F.lit(1.0)).otherwise(F.col(x) / F.col(y))
    return one.select(
        F.lit(method).alias("method"), F.lit(level).alias("level"), "n_a", "n_b", "n_both", ratio("n_both", "n_any").alias("jaccard"), ratio("n_both", "n_a").alias("precision"),
        ratio("n_both", "n_b").alias("recall"), (100 * ratio("n_both", "n_b")).alias("overlap_pct"),
    )


def with_f1(fidelities: DataFrame) -> DataFrame:
    """The harmonic mean of precision and recall beside them."""
    both = F.col("precision") + F.col("recall")
    return fidelities.withColumn("f1", F.when(both == 0, F.lit(0.0)).otherwise(2 * F.col("precision") * F.col("recall") / both))


def missed(a: DataFrame, reference: DataFrame, on: list[str]) -> DataFrame:
    """What the reference has and ``a`` lacks."""
    return reference.select(on).distinct().join(a.select(on).distinct(), on, "left_anti")


def bucket_balance(rows: DataFrame, k_buckets: int, n_docs: int) -> DataFrame:
    """Sizes, comparisons and outliers of the buckets of each band; empty buckets count.

    A bucket is an outlier above mean + 2 population deviations.  Expected comparisons are those of equal buckets.  The
    relative error is given over the expected and over the actual comparisons, since both are in use.
    """
    sizes = bucket_sizes(rows)
    per_band = sizes.groupBy("band").agg(F.sum("n").alias("docs"), F.sum(F.col("n") * F.col("n")).alias("squares"), F.sum(F.col("n") * (F.col("n") - 1) / 2).cast("long").alias("comparisons"))
    k = F.lit(k_buckets)
    mean, second = F.col("docs") / k, F.col("squares") / k
    per_band = per_band.select("band", mean.alias("mean"), F.sqrt(F.greatest(second - mean * mean, F.lit(0.0))).alias("stddev"), "comparisons")
    limit = per_band.select("band", (F.col("mean") + 2 * F.col("stddev")).alias("limit"))
    out = sizes.join(F.broadcast(limit), "band").where("n > limit").groupBy("band").agg(F.count("*").alias("outliers"), F.sum(F.col("n") * (F.col("n") - 1) / 2).cast("long").alias("out_comparisons"))
    both = per_band.join(out, "band", "left").fillna(0, ["outliers", "out_comparisons"])
    m = n_docs / k_buckets
    expected = F.lit(k_buckets * m * (m - 1) / 2)
    delta = F.col("comparisons") - expected
    return both.select(
        "band", F.lit(k_buckets).cast("long").alias("n_buckets"), "mean", "stddev", "comparisons", "outliers", (100 * F.col("outliers") / k).alias("pct_out"), "out_comparisons",
        (100 * F.col("out_comparisons") / F.col("comparisons")).alias("pct_out_comparisons"), expected.alias("expected"), delta.alias("delta"),
        (100 * delta / expected).alias("rel_err_expected_pct"), (100 * delta / F.col("comparisons")).alias("rel_err_actual_pct"),
    )


def rank_balance(balance: DataFrame) -> DataFrame:
    """How far the busiest band is above the mean one, in comparisons."""
    return balance.agg(F.max("comparisons").alias("most"), F.avg("comparisons").alias("mean")).withColumn("imbalance", F.col("most") / F.col("mean"))


def cluster_counts(decisions: DataFrame) -> DataFrame:
    """members, clusters, removed: three numbers that must not be mistaken for one another."""
    return decisions.agg(F.count("*").alias("members"), F.countDistinct("cluster").alias("clusters"), F.coalesce(F.sum((~F.col("keep")).cast("long")), F.lit(0)).alias("removed"))


def token_savings(docs: DataFrame, drop: DataFrame) -> DataFrame:
    """Tokens (runs without white space) before and after, and the share saved."""
    own = docs.select("doc_id", F.size(F.regexp_extract_all("text", F.lit(r"(\S+)"), F.lit(1))).cast("long").alias("t"))
    both = own.join(drop.select("doc_id", F.lit(True).alias("_gone")), "doc_id", "left")
    return both.agg(F.sum("t").alias("tokens_raw"), F.sum(F.when(F.col("_gone").isNull(), F.col("t")).otherwise(0)).alias("tokens_kept")).withColumn("saved", 1 - F.col("tokens_kept") / F.col("tokens_raw"))


def hash_quality(docs: DataFrame, cfg, cells: int = 64) -> DataFrame:
    """Distinct shingles, distinct hash values, collision rate against 1/p, and the chi-square of the values over equal cells."""
    from corpusdedup.functions.hashing import base_hash_column, char_grams

    grams = docs.select(F.explode(char_grams(F.col("text"), cfg.k)).alias("g")).distinct().select(base_hash_column(F.col("g"), cfg).alias("h"))
    cell = grams.groupBy(F.floor(F.col("h") * cells / cfg.p).alias("c")).agg(F.count("*").alias("n"))
    chi = cell.agg(F.sum("n").alias("n"), F.sum(F.col("n") * F.col("n")).alias("s")).select("n", (F.col("s") * cells / F.col("n") - F.col("n")).alias("chi_square"))
    # Pairs that collide, out of all pairs.
    same = grams.groupBy("h").agg(F.count("*").alias("c")).agg(F.sum(F.col("c") * (F.col("c") - 1) / 2).alias("colliding"), F.count("*").alias("values"))
    return chi.crossJoin(same).select(F.col("n").alias("shingles"), F.col("values"), (2 * F.col("colliding") / F.col("n") / (F.col("n") - 1)).alias("collision_rate"), F.lit(1.0 / cfg.p).alias("expected_rate"), "chi_square")


def speedup(baseline_s: float, own_s: float) -> float:
    return baseline_s / own_s


def overlap_pct(both: int, reference: int) -> float:
    return 100 * both / reference
