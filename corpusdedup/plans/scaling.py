"""Larger corpora of the same structure, and how cost grows with them."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Fixed value: the letters that ``enlarged`` turns round.
LETTERS = "abcdefghijklmnopqrstuvwxyz"


def enlarged(docs: DataFrame, copies: int, stride: int) -> DataFrame:
    """``copies`` corpora in one, each with ids ``stride`` apart and its letters turned by one more place.

    Duplicates stay inside a copy, for a text and its turned form share few shingles; so clusters are those of one corpus times
    the number of copies (at most as many as there are letters).
    """
    if not 1 <= copies <= len(LETTERS):
        raise ValueError(f"between 1 and {len(LETTERS)} copies")
    both = LETTERS + LETTERS.upper()
    turned = lambda k: F.translate("text", both, (t := LETTERS[k:] + LETTERS[:k]) + t.upper())
    each = F.explode(F.array(*[F.struct(F.lit(k).cast("long").alias("copy"), turned(k).alias("text")) for k in range(copies)]))
    rest = [F.col(c) for c in docs.columns if c not in ("doc_id", "text")]
    return docs.select("doc_id", *rest, each.alias("_e")).select((F.col("doc_id") + F.col("_e.copy") * stride).alias("doc_id"), F.col("_e.text").alias("text"), *rest)


def growth_exponent(sizes: list[float], costs: list[float]) -> float:
    """The power of the size that the costs follow, by least squares on logarithms."""
    return float(np.polyfit(np.log(sizes), np.log(costs), 1)[0])


def parallel_efficiency(workers: list[int], seconds: list[float]) -> list[float]:
    """Speedup over the run with fewest workers, per worker added."""
    first = min(range(len(workers)), key=lambda i: workers[i])
    return [seconds[first] / s / (w / workers[first]) for w, s in zip(workers, seconds)]
