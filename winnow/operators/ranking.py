"""Row numbers within groups, or over all rows, without a window that puts a group into one task."""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from winnow.functions.textops import spare
from winnow.plans.settle import settle

#: Up to so many runs (one per partition and group that meet) go to every executor; beyond it they are joined by shuffle.
RUNS_BROADCAST = 200_000


def ranked(df: DataFrame, by: Sequence[str], order: Sequence[Column | str], name: str = "rank") -> DataFrame:
    """``df`` plus ``name``: the row's position from 0 within ``by`` under ``order`` (nulls first, null groups count).

    Rows are range-partitioned by group and order, so a group of any size spans several sorted partitions;
    positions inside a partition come from the sort, and the start of each (partition, group) run from a
    running sum over the runs, of which there are at most partitions + groups. Helper columns get names that ``df`` doesn't have.
    """
    keys = [F.col(c) for c in by]
    at, part, p, first, n, start = (spare(df, f"_rk_{x}") for x in ("at", "part", "p", "first", "n", "start"))
    names = [spare(df, f"_rk_k{i}") for i in range(len(by))]
    placed = settle(df.repartitionByRange(*keys, *order).sortWithinPartitions(*keys, *order).withColumn(at, F.monotonically_increasing_id()))
    placed = placed.withColumn(part, F.shiftright(at, 33)).withColumn(at, F.col(at).bitwiseAND(F.lit((1 << 33) - 1)))
    runs = placed.groupBy(*[k.alias(x) for k, x in zip(keys, names, strict=True)], F.col(part).alias(p)).agg(F.min(at).alias(first), F.count(F.lit(1)).alias(n))
    ahead = Window.partitionBy(*names).orderBy(p).rowsBetween(Window.unboundedPreceding, -1)
    runs = runs.withColumn(start, F.coalesce(F.sum(n).over(ahead), F.lit(0).cast("long")))
    if by:  # without groups there is one run per partition
        runs = settle(runs)
    if not by or runs.count() <= RUNS_BROADCAST:
        runs = F.broadcast(runs)
    same = [F.col(part) == F.col(p)] + [k.eqNullSafe(F.col(x)) for k, x in zip(keys, names, strict=True)]
    return placed.join(runs, reduce(lambda x, y: x & y, same)).withColumn(name, F.col(start) + F.col(at) - F.col(first)).drop(at, part, p, first, n, start, *names)


def running_total(df: DataFrame, by: Sequence[str], order: Sequence[Column | str], value: str, name: str = "cum", upto: int | None = None) -> DataFrame:
    """``df`` plus ``name``: the sum of ``value`` over the rows of the group up to this one, for groups of any size.

    Like ``ranked``: rows are range-partitioned, summed within partitions, and the sums of earlier partitions added.
    With ``upto``, only rows whose partition begins at or below that sum go on, among them all whose own sum is at most it,
    so that a small budget sorts and sums little more than itself. Null values count 0; rows equal in everything stand
    next to each other in either order; helper columns get names that ``df`` doesn't have.
    """
    keys = [F.col(c) for c in by]
    at, part, p, n, start = (spare(df, f"_rt_{x}") for x in ("at", "part", "p", "n", "start"))
    names = [spare(df, f"_rt_k{i}") for i in range(len(by))]
    own = F.coalesce(F.col(value), F.lit(0))
    placed = settle(df.repartitionByRange(*keys, *order).sortWithinPartitions(*keys, *order).withColumns({at: F.monotonically_increasing_id(), part: F.spark_partition_id()}))
    runs = placed.groupBy(*[k.alias(x) for k, x in zip(keys, names, strict=True)], F.col(part).alias(p)).agg(F.sum(own).alias(n))
    ahead = Window.partitionBy(*names).orderBy(p).rowsBetween(Window.unboundedPreceding, -1)
    runs = runs.withColumn(start, F.coalesce(F.sum(n).over(ahead), F.lit(0).cast("long")))
    if upto is not None:
        runs = runs.where(F.col(start) <= upto)
    if by:  # without groups there is one run per partition
        runs = settle(runs)
    if not by or runs.count() <= RUNS_BROADCAST:
        runs = F.broadcast(runs)
    same = [F.col(part) == F.col(p)] + [k.eqNullSafe(F.col(x)) for k, x in zip(keys, names, strict=True)]
    within = Window.partitionBy(part, *by).orderBy(at).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return placed.join(runs, reduce(lambda x, y: x & y, same)).withColumn(name, F.col(start) + F.sum(own).over(within)).drop(at, part, p, n, start, *names)
