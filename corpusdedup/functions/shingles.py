"""Shingle columns and set similarity."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corpusdedup.functions.hashing import char_grams


def char_shingles(text: Column, k: int = 5) -> Column:
    return char_grams(text, k)


def word_shingles(text: Column, k: int = 5) -> Column:
    """k-grams of words, joined by single spaces; none for fewer words.

    The words are bound by an outer lambda: an expression used inside one is else evaluated again for each shingle.
    """
    words = F.filter(F.split(text, r"\s+"), lambda w: w != "")
    grams = lambda w: F.transform(F.sequence(F.lit(1), F.size(w) - (k - 1)), lambda i: F.array_join(F.slice(w, i, k), " "))
    return F.get(F.transform(F.array(words), lambda w: F.when(F.size(w) >= k, grams(w)).otherwise(F.array().cast("array<string>"))), F.lit(0))


def shingle_set(grams: Column) -> Column:
    return F.array_distinct(grams)


def jaccard(a: Column, b: Column) -> Column:
    """Similarity of two sets; two empty sets are equal."""
    union = F.size(F.array_union(a, b))
    return F.when(union == 0, F.lit(1.0)).otherwise(F.size(F.array_intersect(a, b)) / union)


def match_count(a: Column, b: Column) -> Column:
    """Equal entries of two signatures."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x == y).cast("int")), F.lit(0), lambda s, x: s + x)


def est_similarity(a: Column, b: Column) -> Column:
    return match_count(a, b) / F.size(a)


def gram_rows(docs: DataFrame, k: int = 5, distinct: bool = False) -> DataFrame:
    """doc_id, gram: a row for each shingle, or for each distinct one."""
    rows = docs.select("doc_id", F.explode(char_grams(F.col("text"), k)).alias("gram"))
    return rows.distinct() if distinct else rows


def lsh_probability(s: Column, bands: int, rows: int) -> Column:
    """Chance that a pair of similarity s shares a band."""
    return 1 - F.pow(1 - F.pow(s, rows), bands)
