"""Mixing sources to target weights.

Tokens are summed per source, targets and repetition rates derived from the sums, and each document is taken
floor(rate) times plus one copy drawn with probability equal to the fraction, from a hash of its id and a seed.

Defined cases: a null text has size 0; null sources are one source, last in order; sources of size 0 have
target 0 and rate 0; rows without id draw alike, as do rows with equal ids; empty tables give empty results;
other columns are carried along.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from winnow.llm.common import table
from winnow.plans.settle import settle

WEIGHTS = (5, 2, 1)
SHARE = 1.5
MOST = 2
SEED = "mix-1"
#: Sources up to this number are sent to every executor (some 10 MB); beyond it they are joined by shuffle.
SOURCES_BROADCAST = 100_000


def size_of(text: str) -> Column:
    return F.coalesce(F.regexp_count(F.col(text), F.lit(r"[^\x20\x09-\x0D]+")).cast("long"), F.lit(0).cast("long"))


def draw(id_col: str, seed: str) -> Column:
    """Uniform in [0, 1): the first 52 bits of the MD5 of id and seed."""
    bits = F.conv(F.substring(F.md5(F.concat(F.coalesce(F.col(id_col).cast("string"), F.lit("")), F.lit(f":{seed}")).cast("binary")), 1, 13), 16, 10)
    return bits.cast("long") / F.lit(float(1 << 52))


def targets(sizes: DataFrame, weights: tuple = WEIGHTS, share: float = SHARE, most: float = MOST) -> DataFrame:
    """(source, source_size) -> plus target: weights repeat over the sources by code point, null last.

    Sharing, cutting at ``most`` times the size and sharing the excess again ends at one level per unit of
    weight; sources whose cap per weight lies below it get their cap. With the sources in order of cap per weight,
    the level follows from running sums. There is one row per source here, so these windows hold no documents.
    """
    order = Window.orderBy(F.col("source").asc_nulls_last())
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.pmod(F.row_number().over(order) - 1, F.lit(len(weights))) + 1).cast("int"))
    capped = sizes.select("source", "source_size", weight.alias("w"), (F.col("source_size") * F.lit(float(most))).alias("cap"))
    by_cap = Window.orderBy((F.col("cap") / F.col("w")), F.col("source").asc_nulls_last())
    before = by_cap.rowsBetween(Window.unboundedPreceding, -1)
    every = Window.partitionBy()
    level = capped.select(
        "*",
        F.row_number().over(by_cap).alias("k"),
        (F.sum("source_size").over(every) * F.lit(float(share)) - F.coalesce(F.sum("cap").over(before), F.lit(0.0))).alias("left"),
        (F.sum("w").over(every) - F.coalesce(F.sum("w").over(before), F.lit(0.0))).alias("w_left"),
    ).withColumn("level", F.col("left") / F.col("w_left"))
    # the first source in that order that the level doesn't fill sets it for all that follow
    chosen = level.withColumn("at", F.min(F.when(F.col("level") * F.col("w") <= F.col("cap"), F.struct("k", "level"))).over(every)["level"])
    return chosen.select("source", "source_size", F.least(F.col("cap"), F.coalesce(F.col("at") * F.col("w"), F.col("cap"))).alias("target"))


def rates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", seed: str = SEED, **how) -> DataFrame:
    """``docs`` plus _mx_size, _mx_source_size, _mx_target and _mx_copies; columns of these names are replaced.

    Words are counted once to sum them by source and once on the rows that are returned; nothing is stored in between.
    """
    docs = docs.drop("_mx_size", "_mx_source_size", "_mx_target", "_mx_copies", "_mx_source")
    sized = docs.withColumn("_mx_size", size_of(text_col))
    sums = sized.groupBy(F.col(source_col).alias("source")).agg(F.sum("_mx_size").alias("source_size"))
    goal = settle(targets(sums, **how)).select(F.col("source").alias("_mx_source"), F.col("source_size").alias("_mx_source_size"), F.col("target").alias("_mx_target"))
    if goal.count() <= SOURCES_BROADCAST:
        goal = F.broadcast(goal)
    joined = sized.join(goal, F.col(source_col).eqNullSafe(F.col("_mx_source"))).drop("_mx_source")
    rate = F.when(F.col("_mx_source_size") > 0, F.col("_mx_target") / F.col("_mx_source_size")).otherwise(F.lit(0.0))
    whole = F.floor(rate)
    return joined.withColumn("_mx_copies", whole + (draw(id_col, seed) < rate - whole).cast("long"))


def mix(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", seed: str = SEED, **how) -> DataFrame:
    """``docs`` with its columns, every row as often as the mix takes it."""
    inner = docs.select(*[F.col(c).alias(f"d_{c}") for c in docs.columns])  # so that no column of theirs is one of ours
    found = rates(inner, f"d_{id_col}", f"d_{text_col}", f"d_{source_col}", seed, **how)
    return found.where("_mx_copies > 0").withColumn("_mx_copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("_mx_copies")))).select(*[F.col(f"d_{c}").alias(c) for c in docs.columns])


def op5_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = rates(table(spark, sf_dir, "documents").select("doc_id", "text", "source"))
    return found.select(
        "doc_id",
        F.col("_mx_size").alias("size"),
        F.col("_mx_source_size").alias("source_size"),
        F.col("_mx_target").alias("target"),
        (F.col("_mx_size") * F.col("_mx_copies")).alias("taken"),
    )


OP5_SQL = r"""
WITH d AS (
  SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size FROM documents
), s AS (
  SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source
), w AS (
  SELECT source, source_size, source_size * 2.0::DOUBLE AS cap,
         CASE (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 WHEN 0 THEN 5.0 WHEN 1 THEN 2.0 ELSE 1.0 END::DOUBLE AS w
  FROM s
), l AS (
  SELECT *, row_number() OVER o AS k,
         (sum(source_size) OVER ()::DOUBLE * 1.5::DOUBLE - coalesce(sum(cap) OVER (o ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
         / (sum(w) OVER () - coalesce(sum(w) OVER (o ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) AS level
  FROM w WINDOW o AS (ORDER BY cap / w, source NULLS LAST)
), t AS (
  SELECT source, source_size, least(cap, coalesce((SELECT min_by(level, k) FROM l WHERE level * w <= cap) * w, cap)) AS target FROM l
), r AS (
  SELECT doc_id, size, source_size, target, CASE WHEN source_size > 0 THEN target / source_size ELSE 0 END AS rate,
         ('0x' || substr(md5(coalesce(doc_id::VARCHAR, '') || ':mix-1'), 1, 13))::BIGINT / 4503599627370496.0::DOUBLE AS u
  FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source
)
SELECT doc_id, size, source_size, target,
       (size * (floor(rate) + CASE WHEN u < rate - floor(rate) THEN 1 ELSE 0 END))::BIGINT AS taken
FROM r
"""
