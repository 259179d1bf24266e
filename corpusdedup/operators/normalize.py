"""Cleaning: composed Unicode, short documents out."""

from __future__ import annotations

import unicodedata

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusdedup.config import DedupConfig


def _composed(s: pd.Series) -> pd.Series:
    return s.map(lambda x: unicodedata.normalize("NFC", x) if x is not None else None)


def normalize_nfc(docs: DataFrame, col: str = "text") -> DataFrame:
    """The column in normal form C.  Only texts with a non-ASCII character travel to Python, the others are in that form."""
    nfc = F.pandas_udf(_composed, "string")
    foreign = F.octet_length(col) != F.char_length(col)
    return docs.withColumn(col, F.coalesce(nfc(F.when(foreign, F.col(col))), F.col(col)))


def filter_short(docs: DataFrame, min_chars: int = 200, col: str = "text") -> DataFrame:
    """Documents of at least ``min_chars`` characters; null texts go."""
    return docs.where(F.char_length(col) >= min_chars)


def clean(docs: DataFrame, cfg: DedupConfig = DedupConfig(), nfc: bool = True) -> DataFrame:
    return filter_short(normalize_nfc(docs) if nfc else docs, cfg.min_chars)
