"""Joins whose keys may be very unevenly held."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from winnow.functions.textops import spare

#: A key is dealt out if it holds more than this share of all rows, so at most so many keys are, and their list is always small.
HEAVY_KEYS = 10_000
#: No key of fewer rows is dealt out, however few rows there are.
LEAST = 64


def salted_join(left: DataFrame, right: DataFrame, keys: Sequence[str], total: int, counts: DataFrame | None = None, least: int = LEAST, how: str = "inner") -> DataFrame:
    """The inner (or, by ``how``, left) join of ``left`` and ``right`` on ``keys``, in which no task gets more than a small share of ``left`` for one key.

    A key of more than total / HEAVY_KEYS rows of ``left`` (``total`` rows in all) has its rows dealt by hash over enough salts,
    and its rows of ``right`` copied once for each. Heavy keys are HEAVY_KEYS at most, so their list is broadcast; copies of ``right``
    rows are at most 2 * HEAVY_KEYS times the rows that share a heavy key. ``counts`` (keys, n) gives the rows of ``left`` by key where
    they are known, or a good guess of them. Null keys meet nothing; rows that repeat in ``left`` are each joined, by the salt of one.
    """
    keys = list(keys)
    per = max(least, -(-total // HEAVY_KEYS))
    if counts is None:
        counts = left.groupBy(*keys).agg(F.count(F.lit(1)).alias("n"))
    salt, salts = (spare([*left.columns, *right.columns], x) for x in ("_salt", "_salts"))
    heavy = F.broadcast(counts.where(F.col("n") > per).select(*keys, F.ceil(F.col("n") / F.lit(per)).cast("int").alias(salts)))
    others = [c for c in left.columns if c not in keys] or keys
    dealt = left.join(heavy, keys, "left").withColumn(salt, F.when(F.col(salts).isNull(), 0).otherwise(F.pmod(F.xxhash64(*others), F.col(salts)).cast("int"))).drop(salts)
    copied = right.join(heavy, keys, "left").withColumn(salt, F.explode(F.sequence(F.lit(0), F.coalesce(F.col(salts), F.lit(1)) - 1))).drop(salts)
    return dealt.join(copied, [*keys, salt], how).drop(salt)
