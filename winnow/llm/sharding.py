"""Sharding by proportional stratified interleaving.

Rows are shuffled by a seeded hash and ranked within their source; (rank + 1/2) / rows of the source is a row's
fractional rank. All rows in the order of it are cut into stretches of equal length, so every shard, and every
prefix of one, holds the sources in the corpus's proportions. The law is ``rows``: counts differ by one at most.

Both ranks are taken over range-partitioned rows, so neither a hot source nor the whole is ever one task, and
texts stay where they are: only ids, sizes and checksums are shuffled.

Defined cases: a null text has size 1 and the checksum of no bytes; null sources are one source, last in ties;
null ids come first in ties; rows equal in everything shuffled are alike, so their order doesn't matter; fewer
rows than shards leave shards empty; other columns are not carried along.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from winnow.llm.common import table
from winnow.operators.ranking import ranked
from winnow.plans.settle import settle

SHARDS = 16
SEED = "shard-1"


def shard(docs: DataFrame, shards: int = SHARDS, seed: str = SEED, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """(doc_id, source, size, text_crc32, shard, slot) of every row."""
    raw = F.coalesce(F.col(text_col).cast("string"), F.lit("")).cast("binary")
    rows = settle(
        docs.select(
            F.col(id_col).cast("long").alias("doc_id"),
            F.col(source_col).cast("string").alias("source"),
            (F.octet_length(raw) + 1).cast("long").alias("size"),
            F.crc32(raw).alias("text_crc32"),
            F.md5(F.concat(F.coalesce(F.col(id_col).cast("string"), F.lit("")), F.lit(f":{seed}")).cast("binary")).alias("shuffled"),
        )
    )
    tie = ["shuffled", "doc_id", "size", "text_crc32"]
    sums = rows.groupBy(F.col("source").alias("_s")).agg(F.count(F.lit(1)).alias("_rows"))
    within = ranked(rows, ["source"], tie, "_rank")
    shares = within.join(sums, F.col("source").eqNullSafe(F.col("_s"))).withColumn("_share", (F.col("_rank") + 0.5) / F.col("_rows"))
    whole = ranked(shares.drop("_s", "_rank", "_rows"), [], ["_share", F.col("source").asc_nulls_last(), *tie], "_at")
    n = rows.count()
    out = whole.withColumn("shard", F.expr(f"CAST(_at * {shards} DIV {max(n, 1)} AS INT)"))
    first = F.expr(f"CAST(shard AS BIGINT) * {n} DIV {shards} + CASE WHEN CAST(shard AS BIGINT) * {n} % {shards} > 0 THEN 1 ELSE 0 END")
    return out.withColumn("slot", F.col("_at") - first).select("doc_id", "source", "size", "text_crc32", "shard", "slot")


def op9_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = shard(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
