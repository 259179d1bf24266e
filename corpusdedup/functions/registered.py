"""Functions for SQL users: signatures, their comparison and merge, and the rows of a signature's bands."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from corpusdedup.config import DedupConfig
from corpusdedup.functions.hashing import codes_of, signature

CFG = DedupConfig()


def _sign(texts: pd.Series) -> pd.Series:
    return texts.map(lambda t: signature(codes_of(t), CFG) if t is not None else None)


def _similar(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([float(np.mean(np.asarray(x) == np.asarray(y))) if x is not None and y is not None else None for x, y in zip(a, b)])


def _merge(sigs: pd.Series) -> list:
    return np.minimum.reduce([np.asarray(x) for x in sigs]).tolist()


def _lengths(texts: pd.Series) -> pd.Series:
    return texts.str.len().astype("Int64")


_merge.__annotations__ = {"sigs": pd.Series, "return": list}
for _f, _n in ((_sign, 1), (_similar, 2), (_lengths, 1)):
    _f.__annotations__ = {k: pd.Series for k in [*_f.__code__.co_varnames[:_n], "return"]}


def minhash_signature():
    return F.pandas_udf(_sign, "array<int>")


def est_similarity():
    return F.pandas_udf(_similar, "double")


def text_lengths():
    return F.pandas_udf(_lengths, "long")


def min_merge():
    """Aggregate: the element-wise minimum of signatures, which is the signature of the union of their sets."""
    return F.pandas_udf(_merge, "array<int>", F.PandasUDFType.GROUPED_AGG)


class BandRows:
    """Rows (band, bucket) of a signature for a number of buckets."""

    def eval(self, sig: list, k_buckets: int):
        if sig is None:
            return
        sums = np.asarray(sig, dtype=np.int64).reshape(CFG.bands, CFG.rows).sum(axis=1) % k_buckets
        for band, bucket in enumerate(sums.tolist()):
            yield band, bucket


def register(spark: SparkSession) -> None:
    """Make minhash_signature(text), est_similarity(sig, sig) and the table function lsh_buckets(sig, k) known to SQL."""
    spark.udf.register("minhash_signature", minhash_signature())
    spark.udf.register("est_similarity", est_similarity())
    spark.udtf.register("lsh_buckets", F.udtf(BandRows, returnType="band int, bucket long"))
