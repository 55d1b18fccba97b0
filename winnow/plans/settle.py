"""Cutting lineage in a way that survives lost executors."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def checkpoint_dir(spark: SparkSession) -> str:
    """The shared folder the cluster names in spark.checkpoint.dir; one of our own only where none is set and all runs in one process."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        named = sc.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
        if not named and not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="winnow-"))
    return sc.getCheckpointDir()


def remove(spark: SparkSession, path: str) -> None:
    """Deletes a folder of ours in any store that Spark reaches; a missing one is no error."""
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def settle(df: DataFrame) -> DataFrame:
    """Materialise ``df`` in the shared checkpoint folder, so later reads neither recompute it nor depend on one executor."""
    checkpoint_dir(df.sparkSession)
    return df.checkpoint()


def stored(df: DataFrame) -> DataFrame:
    """``settle`` for large tables: as compressed columns in the shared checkpoint folder, a fraction of a checkpoint's bytes. Not deleted."""
    path = f"{checkpoint_dir(df.sparkSession)}/stored-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


#: A table goes to every executor if its rows, as Spark holds them, take no more than this.
BROADCAST_BYTES = 64 << 20


def fits(df: DataFrame, most: int = BROADCAST_BYTES) -> bool:
    """Whether a settled or otherwise cheap table may go to every executor, by its counted size: bytes of strings, binaries and arrays and 16 for any other value."""

    def cost(name: str, kind: str):
        c = F.col(f"`{name}`")
        if kind in ("string", "binary"):
            return F.coalesce(F.octet_length(c), F.lit(0)) + 24
        if kind.startswith(("array", "map")):
            return F.octet_length(F.to_json(F.struct(c))) + 24
        return F.lit(16)

    size = df.agg(F.coalesce(F.sum(sum((cost(n, k) for n, k in df.dtypes), F.lit(32)).cast("long")), F.lit(0)).alias("b")).first()["b"]
    return size <= most


def bounded(df: DataFrame, most: int = BROADCAST_BYTES) -> DataFrame:
    """``df`` with a broadcast hint if it ``fits``; a larger table is left to the join's own choice."""
    return F.broadcast(df) if fits(df, most) else df


def spread_like(df: DataFrame, scan: DataFrame, key: str) -> DataFrame:
    """``df``, dealt out by ``key`` if ``scan``, the table it comes from, has fewer splits than there are cores.

    A small table in one row group would otherwise be scored by one core. Tables with enough splits, as all large ones have,
    are left where they are, and nothing is shuffled.
    """
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores, key) if scan.rdd.getNumPartitions() < cores else df
