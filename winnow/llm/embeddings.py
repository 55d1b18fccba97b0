"""Embedding near-dedup: random-hyperplane sign hashing in several tables, exact cosine, connected components.

Equal vectors of a label are folded into one class first. Each class has one bucket per table, named by a hash of table, label,
length and the signs of its projections on that table's hyperplanes. Only class numbers and bucket names are shuffled to
find which buckets hold more than one class; vectors then travel to those alone. A bucket larger than ``block`` classes is
cut into blocks and every pair of blocks becomes a group of its own, so no task holds more than two blocks. Groups stream
through sorted partitions; cosines are taken in double precision, block by block. A pair counts in the first table where
it meets, so nothing is counted twice. Each group returns a count of links per class and a star per local cluster instead of
all its pairs.

The bits per table follow the number of rows, and the number of tables follows the bits, so that a pair
exactly at the threshold is missed with probability ``miss`` at most at every input size.

Defined cases: null labels, and vectors that are null, zero or hold null or non-finite components link with
nothing, not even with their copies; vectors of different lengths never link; rows with equal ids are rows of
their own; a row without id is counted as a partner and is never a component's id unless nothing else is in it; an empty
table gives none; other columns are not read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from winnow.llm.common import table
from winnow.operators.components import connected_components
from winnow.operators.skew import salted_join
from winnow.plans.settle import settle

THRESHOLD = 0.98
MISS = 0.002
BLOCK = 128
SEED = 20


def plan_tables(n: int, threshold: float = THRESHOLD, miss: float = MISS) -> tuple[int, int]:
    """(bits, tables) for n vectors: about a quarter of them would share a bucket by chance in one table."""
    bits = min(40, max(8, math.ceil(math.log2(max(n, 2))) + 2))
    agree = (1 - math.acos(threshold) / math.pi) ** bits
    return bits, math.ceil(math.log(miss) / math.log(1 - agree))


def _keyed(vectors: DataFrame, id_col: str, vec_col: str, label_col: str) -> DataFrame:
    """(vec_id, label, vec, c1, c2): c1 and c2 are one 128-bit name of label and vector, null where the vector can't link."""
    kind = dict(vectors.dtypes)[vec_col]
    v = F.col(vec_col) if kind == "array<float>" else F.col(vec_col).cast("array<double>")
    zero = F.lit(0.0).cast("float") if kind == "array<float>" else F.lit(0.0)
    usable = F.col(label_col).isNotNull() & F.col(vec_col).isNotNull() & ~F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))) & F.exists(v, lambda x: x != 0)
    # adding 0.0 makes the two zeros one, as they are in every cosine
    found = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.when(usable, F.col(label_col).cast("string")).alias("label"), F.when(usable, F.transform(v, lambda x: x + zero)).alias("vec"))
    names = [F.when(F.col("vec").isNotNull(), F.xxhash64(F.lit(k), "label", F.size("vec"), "vec")) for k in (1, 2)]
    return found.select("vec_id", "label", "vec", names[0].alias("c1"), names[1].alias("c2"))


def _planes(dim: int, bits: int, table: int, seed: int) -> np.ndarray:
    return np.random.default_rng([seed, dim, table]).standard_normal((dim, bits))


def _unit(flat: np.ndarray) -> np.ndarray:
    x = flat.astype(np.float64)
    x = x / np.abs(x).max(axis=1, keepdims=True)  # no overflow in the norm
    return x / np.linalg.norm(x, axis=1, keepdims=True)


_SIGNED = "c1 long, c2 long, label string, n long, least long, dim int, vec binary, sig binary, signs array<long>"


def _signed(classes: DataFrame, bits: int, tables: int, seed: int, wide: str) -> DataFrame:
    """Classes with their vector as bytes and their signs in every table; sig holds 32 bits of each, to tell where pairs met before."""

    def hashed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        power = 1 << np.arange(bits, dtype=np.int64)
        planes: dict[int, np.ndarray] = {}
        for b in batches:
            lists = b.column(0)
            lengths = lists.value_lengths().to_numpy(zero_copy_only=False)
            flat = lists.flatten().to_numpy(zero_copy_only=False)
            start = np.cumsum(lengths) - lengths
            for dim in np.unique(lengths).tolist():
                if dim not in planes:
                    planes[dim] = np.concatenate([_planes(dim, bits, t, seed) for t in range(tables)], axis=1)
                every = np.flatnonzero(lengths == dim)
                for lo in range(0, len(every), 2048):
                    at = every[lo : lo + 2048]
                    x = flat[start[at][:, None] + np.arange(dim)]
                    signs = (_unit(x) @ planes[dim] > 0).reshape(len(at), tables, bits) @ power
                    short = (signs ^ (signs >> 32)).astype("<u4")
                    yield pa.RecordBatch.from_arrays(
                        [*[c.take(pa.array(at)) for c in b.columns[1:]], pa.array(np.full(len(at), dim, np.int32)), pa.array([r.tobytes() for r in x.astype(wide)], pa.binary()), pa.array([r.tobytes() for r in short], pa.binary()), pa.array(list(signs), pa.list_(pa.int64()))],
                        names=[f.split()[0] for f in _SIGNED.split(", ")],
                    )

    return classes.select("vec", "c1", "c2", "label", "n", "least").mapInArrow(hashed, _SIGNED)


def _pairs(batches: Iterator[pa.RecordBatch], threshold: float, wide: str) -> Iterator[pa.RecordBatch]:
    """Sorted rows of groups (key, i, j, t, label, dim) -> (class, links, other): links met here first, and a star's edge."""

    def linked(rows: pa.Table | pa.RecordBatch) -> pa.RecordBatch | None:
        if rows.num_rows < 2:
            return None
        t, i, j = (rows.column(k)[0].as_py() for k in ("t", "i", "j"))
        sig = np.frombuffer(b"".join(rows.column("sig").to_pylist()), "<u4").reshape(rows.num_rows, -1)
        side, n, cls = (rows.column(k).to_numpy() for k in ("side", "n", "cls"))
        a = np.flatnonzero(side == i)
        b = np.flatnonzero(side == j)
        if not len(a) or not len(b):
            return None
        x = _unit(np.frombuffer(b"".join(rows.column("vec").to_pylist()), wide).reshape(rows.num_rows, -1))
        near = x[a] @ x[b].T >= threshold
        if i == j:
            np.fill_diagonal(near, False)
        p, q = np.nonzero(near)
        before = (sig[a[p], :t] == sig[b[q], :t]).any(axis=1)
        near[p[before], q[before]] = False
        if not near.any():
            return None
        links = np.zeros(rows.num_rows, np.int64)
        links[a] += near @ n[b]
        if i != j:
            links[b] += near.T @ n[a]
        # a star per local cluster: labels sink to the smallest position until they rest
        whole = np.zeros((rows.num_rows, rows.num_rows), bool)
        whole[np.ix_(a, b)] = near
        whole |= whole.T
        root = np.arange(rows.num_rows)
        while True:
            low = np.where(whole, root[None, :], rows.num_rows).min(axis=1)
            new = np.minimum(root, low)
            new = new[new]
            if (new == root).all():
                break
            root = new
        hit = np.flatnonzero(links)
        return pa.RecordBatch.from_arrays([pa.array(cls[hit]), pa.array(links[hit]), pa.array(cls[root[hit]])], names=["class", "links", "other"])

    names = ["key", "i", "j", "t", "label", "dim"]
    held: pa.Table | None = None  # rows of the last group so far; at most two blocks
    key = None
    for batch in batches:
        rows = pa.Table.from_batches([batch])
        keys = list(zip(*(rows.column(k).to_pylist() for k in names), strict=True))
        cuts = [0] + [r for r in range(1, len(keys)) if keys[r] != keys[r - 1]] + [len(keys)]
        for lo, hi in zip(cuts, cuts[1:], strict=False):
            if lo == hi:
                continue
            part = rows.slice(lo, hi - lo)
            if held is not None and keys[lo] == key:
                held = pa.concat_tables([held, part])
                continue
            if held is not None and (out := linked(held.combine_chunks())) is not None:
                yield out
            held, key = part, keys[lo]
    if held is not None and (out := linked(held.combine_chunks())) is not None:
        yield out


def near_duplicates(
    vectors: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", label_col: str = "label",
    threshold: float = THRESHOLD, miss: float = MISS, block: int = BLOCK, seed: int = SEED,
) -> DataFrame:
    """(vec_id, n_links, component_id, kept) of every row."""
    wide = "<f4" if dict(vectors.dtypes)[vec_col] == "array<float>" else "<f8"
    rows = _keyed(vectors, id_col, vec_col, label_col)
    total = vectors.count()
    grouped = rows.where(F.col("c1").isNotNull()).groupBy("c1", "c2").agg(F.first("label").alias("label"), F.first("vec").alias("vec"), F.count(F.lit(1)).alias("n"), F.min("vec_id").alias("least"))
    bits, tables = plan_tables(total, threshold, miss)
    classes = settle(_signed(grouped, bits, tables, seed, wide).withColumn("cls", F.monotonically_increasing_id()))
    # one row of two numbers per class and table
    key = F.xxhash64("t", "label", "dim", "sign")
    bucketed = classes.select("cls", "label", "dim", F.posexplode("signs").alias("t", "sign")).select(key.alias("key"), "cls", "t")
    shared = settle(bucketed.groupBy("key").agg(F.count(F.lit(1)).alias("size")).where("size > 1"))
    held = salted_join(bucketed, shared, ["key"], total * tables, shared.select("key", F.col("size").alias("n")))
    # a class in a crowded bucket meets every block of it
    blocks = F.ceil(F.col("size") / F.lit(float(block))).cast("int")
    dealt = held.withColumn("blocks", blocks).withColumn("side", F.pmod(F.xxhash64("cls"), F.col("blocks")).cast("int"))
    vector = classes.select("cls", "label", "dim", "n", "vec", "sig")
    spread = dealt.join(vector, "cls").withColumn("_o", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    groups = spread.select("key", F.least("side", "_o").alias("i"), F.greatest("side", "_o").alias("j"), "t", "label", "dim", "side", "cls", "n", "vec", "sig")
    met = settle(
        groups.repartition("key", "i", "j").sortWithinPartitions("key", "i", "j", "t", "label", "dim").mapInArrow(lambda it: _pairs(it, threshold, wide), "class long, links long, other long")
    )
    counts = met.groupBy(F.col("class").alias("cls")).agg(F.sum("links").alias("links"))
    # roots are joined as classes; the smallest id of a component follows from its classes' smallest ids
    joined = connected_components(met.select(F.col("class").alias("a"), F.col("other").alias("b")))
    named = classes.select("cls", "c1", "c2", "least", "n")
    rooted = named.join(joined, F.col("cls") == F.col("node"), "left").select("cls", "c1", "c2", "n", "least", F.coalesce("root", "cls").alias("root"))
    least = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    known = rooted.join(least, "root").join(counts, "cls", "left").select("c1", "c2", "n", "component_id", (F.coalesce("links", F.lit(0)) + F.col("n") - 1).alias("n_links"))
    linked = salted_join(rows.where(F.col("c1").isNotNull()).select("vec_id", "c1", "c2"), known.drop("n"), ["c1", "c2"], total, known.select("c1", "c2", "n")).select("vec_id", "n_links", "component_id")
    alone = rows.where(F.col("c1").isNull()).select("vec_id", F.lit(0).cast("long").alias("n_links"), F.lit(None).cast("long").alias("component_id"))
    component = F.coalesce("component_id", "vec_id")
    return linked.unionAll(alone).select("vec_id", F.col("n_links").cast("long").alias("n_links"), component.alias("component_id"), F.col("vec_id").eqNullSafe(component).alias("kept"))


def op6_embedding_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "embeddings"))


OP6_SQL = r"""
WITH RECURSIVE v AS (
  SELECT vec_id, label, embedding::DOUBLE[] AS e FROM embeddings
), pairs AS (
  SELECT a.vec_id AS a, b.vec_id AS b FROM v a JOIN v b ON a.label = b.label AND a.vec_id <> b.vec_id
  WHERE list_cosine_similarity(a.e, b.e) >= 0.98
), reach AS (
  SELECT vec_id, vec_id AS other FROM v
  UNION
  SELECT r.vec_id, p.b FROM reach r JOIN pairs p ON r.other = p.a
)
SELECT v.vec_id, (SELECT count(*) FROM pairs p WHERE p.a = v.vec_id) AS n_links,
       min(r.other) AS component_id, v.vec_id = min(r.other) AS kept
FROM v JOIN reach r ON v.vec_id = r.vec_id GROUP BY v.vec_id
"""
