"""Distributed connected components by alternating large-star and small-star rounds."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from winnow.operators.skew import salted_join
from winnow.plans.settle import settle


#: Edges per partition of a round: few edges take few tasks and few checkpoint files, many take many.
EDGES_PER_PART = 100_000
#: Up to so many edges (16 MB of longs) are joined up in one task; the driver plans a dozen rounds of joins otherwise, and their plans
#: and tasks are what its memory holds. More edges go by rounds.
ONE_TASK = 1_000_000
_ONE_TASK_KINDS = ("bigint", "int", "string")


def _sized(edges: DataFrame, n: int) -> DataFrame:
    """``edges`` in no more partitions than n edges need; a round never has more edges than twice the last one's."""
    return edges.coalesce(max(1, -(-2 * n // EDGES_PER_PART)))


def _signature(edges: DataFrame) -> tuple:
    r = edges.agg(
        F.count(F.lit(1)).alias("n"),
        F.bit_xor(F.xxhash64("u", "v")).alias("x"),
        F.sum(F.pmod(F.xxhash64("v", "u"), F.lit(1 << 31))).alias("s"),
    ).first()
    return tuple(r)


def _large_star(edges: DataFrame, n: int) -> DataFrame:
    """Every larger neighbour of a node is hung on the smallest node of the neighbourhood."""
    both = edges.select(F.col("u").alias("x"), F.col("v").alias("y")).unionAll(
        edges.select(F.col("v").alias("x"), F.col("u").alias("y"))
    )
    found = both.groupBy("x").agg(F.min("y").alias("m"), F.count(F.lit(1)).alias("n"))
    low = found.select("x", F.least("x", "m").alias("m"))
    return salted_join(both, low, ["x"], 2 * n, found.select("x", "n")).where("y > x").select(F.col("y").alias("u"), F.col("m").alias("v")).distinct()


def _small_star(edges: DataFrame, n: int) -> DataFrame:
    """A node and its smaller neighbours are hung on the smallest of them."""
    found = edges.groupBy("u").agg(F.min("v").alias("m"), F.count(F.lit(1)).alias("n"))
    low = found.select("u", "m")
    moved = salted_join(edges, low, ["u"], 2 * n, found.select("u", "n")).where("v > m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.unionAll(low.select("u", F.col("m").alias("v"))).distinct()


def _smallest_reachable(u: np.ndarray, v: np.ndarray, n: int) -> np.ndarray:
    """The smallest of the nodes 0 to n - 1 that each reaches over the edges (u, v): roots are hung on smaller roots, and paths halved, until no edge joins two."""
    root = np.arange(n)
    while len(u):
        np.minimum.at(root, np.maximum(root[u], root[v]), np.minimum(root[u], root[v]))
        while not np.array_equal(up := root[root], root):
            root = up
        apart = root[u] != root[v]
        u, v = u[apart], v[apart]
    return root


def _in_one_task(edges: DataFrame) -> DataFrame:
    """(u, v) with v the smallest node that u reaches, from few edges."""

    def joined_up(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(list(batches) or [], kind)
        ends = pa.concat_arrays([*t.column(0).chunks, *t.column(1).chunks]) if t.num_rows else pa.array([], kind.field(0).type)
        nodes = pc.unique(ends)
        nodes = nodes.take(pc.array_sort_indices(nodes))
        at = pc.index_in(ends, nodes).to_numpy(zero_copy_only=False).astype(np.int64)
        root = _smallest_reachable(at[: t.num_rows], at[t.num_rows :], len(nodes))
        own = np.flatnonzero(root != np.arange(len(nodes)))
        for k in range(0, len(own), 1 << 16):
            part = own[k : k + (1 << 16)]
            yield pa.RecordBatch.from_arrays([nodes.take(pa.array(part)), nodes.take(pa.array(root[part]))], names=["u", "v"])

    form = {"bigint": pa.int64(), "int": pa.int32(), "string": pa.string()}[edges.dtypes[0][1]]
    kind = pa.schema([("u", form), ("v", form)])
    return edges.repartition(1).mapInArrow(joined_up, edges.schema)


def connected_components(edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60, one_task: int = ONE_TASK) -> DataFrame:
    """(node, root) for every node with an edge; root is the smallest node reachable, and a root is not listed.

    Edges may repeat, run in either direction or be loops; null ends are left out. Up to ``one_task`` edges are joined up in one
    task. More of them go by rounds: each round is two joins with partially aggregated minima, in which the neighbours of a hub
    are dealt over many tasks, and a round is checkpointed. A handful of numbers per round reaches the driver, never nodes or edges.
    """
    edges = settle(
        edges.where(F.col(a) != F.col(b)).select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct()
    )
    before = _signature(edges)
    if 0 < before[0] <= one_task and all(kind in _ONE_TASK_KINDS for _, kind in edges.dtypes):
        edges, before = settle(_in_one_task(edges)), (0,)
    for _ in range(max_rounds):
        if before[0] == 0:
            break
        edges = settle(_sized(_small_star(_large_star(edges, before[0]), 2 * before[0]), before[0]))
        after = _signature(edges)
        if after == before:
            break
        before = after
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return edges.select(F.col("u").alias("node"), F.col("v").alias("root"))
