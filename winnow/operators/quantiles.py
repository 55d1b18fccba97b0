"""Scores turned into quantiles of 0 to 100, as a probability in (0, 1]."""

from __future__ import annotations

from bisect import bisect_right

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from winnow.operators.ranking import running_total

METHODS = ("exact", "percent_rank", "cutpoints101", "approx", "kll")


def levels(df: DataFrame, col: str, **sums: Column) -> DataFrame:
    """(_v, _n, _lt, _le): each distinct value, how many rows have it, lie below it and lie up to it; plus named sums of the rows at it.

    Ties are counted before anything is sorted, so a value that a third of the rows share is one row here; the values are
    range-partitioned. Null values are left out.
    """
    found = df.where(F.col(col).isNotNull()).groupBy(F.col(col).alias("_v")).agg(F.count(F.lit(1)).alias("_n"), *[F.sum(c).alias(n) for n, c in sums.items()])
    return running_total(found, [], ["_v"], "_n", "_le").withColumn("_lt", F.col("_le") - F.col("_n"))


def counts_up_to(df: DataFrame, col: str) -> DataFrame:
    """``df`` plus _le and _lt, for uses that need them on the row; ``stepped`` does without moving rows.

    A value that many rows share is a skewed key of this join, which adaptive execution splits.
    """
    return df.join(levels(df, col).select("_v", "_lt", "_le"), F.col(col) == F.col("_v"), "left").drop("_v")


def stepped(df: DataFrame, col: str, label: Column) -> Column:
    """``label``, a monotone expression over the _lt and _le of ``levels`` with few outcomes, as an expression over the row's own value.

    The least value of each outcome is all that reaches the driver, a hundred numbers for quantiles, so rows are neither
    joined nor moved. Null values get null.
    """
    steps = [(r["l"], r["lo"]) for r in levels(df, col).groupBy(label.alias("l")).agg(F.min("_v").alias("lo")).orderBy("lo").collect()]
    c = F.col(col)

    def search(lo: int, hi: int) -> Column:
        if lo == hi:
            return F.lit(steps[lo][0])
        mid = (lo + hi + 1) // 2
        return F.when(c >= F.lit(steps[mid][1]), search(mid, hi)).otherwise(search(lo, mid - 1))

    return F.when(c.isNotNull(), search(0, len(steps) - 1)) if steps else F.lit(None)


def grid(df: DataFrame, col: str, method: str = "approx", accuracy: int = 10_000) -> list[float]:
    """101 cut points, of which a mergeable sketch or an exact percentile sends only that many numbers to the driver."""
    shares = [i / 100 for i in range(101)]
    if method == "approx":
        return df.agg(F.percentile_approx(col, shares, accuracy).alias("g")).first()["g"]
    if method == "kll":
        sketch = df.agg(F.kll_sketch_agg_double(F.col(col)).alias("k"))
        return list(sketch.select(F.kll_sketch_get_quantile_double("k", F.array(*[F.lit(x) for x in shares])).alias("g")).first()["g"])
    return df.agg(F.percentile(col, F.array(*[F.lit(x) for x in shares])).alias("g")).first()["g"]


def from_grid(col: str | Column, cuts: list[float]) -> Column:
    """How many of the cut points 1 to 100 lie at or below a value, over 100, by binary search over a literal."""
    c = F.col(col) if isinstance(col, str) else col

    def search(lo: int, hi: int) -> Column:
        if lo == hi:
            return F.lit(lo / 100)
        mid = (lo + hi + 1) // 2
        return F.when(c >= F.lit(float(cuts[mid])), search(mid, hi)).otherwise(search(lo, mid - 1))

    return search(0, 100)


def lookup(value: float, cuts: list[float]) -> float:
    """The same for one number."""
    return bisect_right(cuts, value, 1) / 100 - 0.01


def normalise(df: DataFrame, col: str, method: str = "exact", name: str | None = None) -> DataFrame:
    """``df`` plus ``name`` (q_<col> by default). Null scores get a null quantile and count for nothing.

    exact: ceil(100 * share of values up to it) / 100, so ties share and the least is 0.01. percent_rank:
    floor(100 * (rank - 1) / (n - 1)) / 100. cutpoints101: cut points 1 to 100 at or below it, over 100.
    approx and kll: the same against sketched cut points.
    """
    name = name or f"q_{col}"
    if method not in METHODS:
        raise ValueError(f"method must be one of {METHODS}")
    some = df.where(F.col(col).isNotNull())
    if method in ("cutpoints101", "approx", "kll"):
        cuts = grid(some, col, "percentile" if method == "cutpoints101" else method)
        return df.withColumn(name, F.when(F.col(col).isNotNull(), from_grid(col, cuts)) if cuts else F.lit(None).cast("double"))
    n = some.count()
    if method == "exact":
        q = F.ceil(F.lit(100.0) * (F.col("_le") / F.lit(float(max(n, 1))))) / F.lit(100.0)
    else:
        q = F.floor(F.lit(100.0) * (F.col("_lt") / F.lit(float(max(n - 1, 1))))) / F.lit(100.0)
    return df.withColumn(name, stepped(df, col, q.cast("double")).cast("double"))
