"""Pieces that several operators of this subpackage share."""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Stands for a null id where ids are ordered or packed: a null id comes before all others, and rows without id count as one document.
NO_ID = -(1 << 63)

WORD = re.compile(r"[^\x20\x09-\x0D]+")
WORD_BYTES = re.compile(rb"[^\x20\x09-\x0D]+")
ASCII_LOWER = bytes.maketrans(bytes(range(65, 91)), bytes(range(97, 123)))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def id_or_low(name: str) -> Column:
    return F.coalesce(F.col(name).cast("long"), F.lit(NO_ID))


def id_or_null(name: str) -> Column:
    return F.when(F.col(name) != NO_ID, F.col(name))


def text_key(name: str) -> Column:
    """Tells apart the rows that share an id but not a text; null and empty texts get different keys, which is harmless."""
    return F.xxhash64(F.col(name))
