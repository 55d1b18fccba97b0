"""SimHash near-dedup by meet-in-the-middle ball hashing.

Half of a radius of 3 bits is 1 bit and a half, and balls of whole bits around whole words either lose pairs at 3 bits or cost 2,146
rows per fingerprint (``links_whole`` does that, as the reference of tests). So each of three words is taken that leave one third of
the bits out in turn. Two fingerprints within 3 bits differ in at most 2 bits of one of them, as soon as a third that
holds one of the differing bits is out. Every distinct fingerprint emits all variants within 1 bit of each such word (131
rows), rows are shuffled on the variant, and two that meet in a variant are a pair: each lies at most 1 bit from it. Pairs that meet in several
ways are kept once; all are verified on the whole fingerprint. Chance meetings of n fingerprints number some 3e-10 * n^2.

Copies are folded into one fingerprint before anything is emitted. Where more than ``crowd`` distinct fingerprints share a
word exactly, as within a huge group of near copies, the buckets at all its variants (any bucket of more than 45 times
``crowd`` rows is among them) list no pairs: the left-out bits of their rows are ball-hashed in turn and every meeting point links its
members in a star, so links stay linear there.

Defined cases: null, empty and blank texts have fingerprint 0 and link like any other; fewer than three
words are one shingle; null ids are never a component's id unless nothing else is in it; rows with equal
ids are fingerprinted each; empty tables give empty results; other columns are carried along by ``keep_one`` alone, and helper
columns get names that the table doesn't have.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from winnow.functions.textops import spare
from winnow.llm.common import ASCII_LOWER, WORD_BYTES, table, text_key
from winnow.operators.components import connected_components
from winnow.plans.settle import settle

RADIUS = 3
SHINGLE = 3
SEED = 42
CROWD = 64
PARTS = 3
_CHUNK = 1 << 16  # shingles hashed at a time


def fingerprint(text: str | None) -> int:
    """Unsigned: bit i is 1 if it is set in over half of the shingles' XXH64."""
    words = WORD_BYTES.findall((text or "").encode().translate(ASCII_LOWER))
    if not words:
        return 0
    n = max(1, len(words) - SHINGLE + 1)
    ones = np.zeros(64, np.int64)
    digest = xxhash.xxh64_intdigest
    for at in range(0, n, _CHUNK):
        part = words[at : at + _CHUNK + SHINGLE - 1]
        if n == 1:
            h = [digest(b" ".join(words), SEED)]
        else:
            h = [digest(b"%b %b %b" % x, SEED) for x in zip(part, part[1:], part[2:], strict=False)]
        ones += np.unpackbits(np.array(h, ">u8").view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * ones > n).tobytes(), "big")


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, tkey, fp): fp is the 64-bit word as a signed long; tkey tells apart rows that share an id."""

    def hashed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fp = np.array([fingerprint(x) for x in b.column(2).to_pylist()], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(fp)], names=["doc_id", "tkey", "fp"])

    narrow = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_key(text_col).alias("tkey"), F.col(text_col).cast("string").alias("text"))
    return narrow.mapInArrow(hashed, "doc_id long, tkey long, fp long")


_EDGES = [64 * k // PARTS for k in range(PARTS + 1)]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def _longs(values: list[int]) -> Column:
    return F.array(*[F.lit(_signed(v)).cast("long") for v in values])


def _mask(h: int) -> int:
    """The bits that word ``h`` leaves out."""
    return (1 << _EDGES[h + 1]) - (1 << _EDGES[h])


def _flips(mask: int, radius: int) -> list[list[int]]:
    """Flips of 0, 1, ... ``radius`` of the bits in ``mask``."""
    bits = [1 << b for b in range(64) if mask >> b & 1]
    return [[0], bits, [x | y for k, x in enumerate(bits) for y in bits[:k]]][: radius + 1]


def _near(h: int, radius: int = 1) -> list[int]:
    """No flip and single flips of word ``h``."""
    return sum(_flips(~_mask(h) & ((1 << 64) - 1), min(1, radius)), [])


def _word(h: int, fp: str = "fp") -> Column:
    """Word ``h`` of a fingerprint; its number stands in the bits that are left out."""
    return F.col(fp).bitwiseAND(F.lit(_signed(~_mask(h) & ((1 << 64) - 1)))).bitwiseOR(F.lit(_signed(h + 1 << _EDGES[h])))


def _choose(h: Column, of) -> Column:
    return F.get(F.array(*[of(k) for k in range(PARTS)]), h.cast("int"))


def _variants(nodes: DataFrame, radius: int) -> DataFrame:
    """(v, d): every variant of every word within 1 bit; d holds the left-out bits, then which flip, then which word.

    A fingerprint can be put together from both, so the shuffle carries two numbers a row, one of them short. What differs from
    variant to variant is a table of constants, so that a row is a few bit operations.
    """
    one = lambda x: F.lit(_signed(x)).cast("long")
    table = [
        F.struct(one(~_mask(h) & ((1 << 64) - 1)).alias("keep"), one(flip ^ (h + 1 << _EDGES[h])).alias("turn"), one(_mask(h)).alias("out"), F.lit(_EDGES[h]).alias("low"), one((k << 24) + (h << 30)).alias("what"))
        for h in range(PARTS)
        for k, flip in enumerate(_near(h, radius))
    ]
    return nodes.select("fp", F.inline(F.array(*table))).select(F.expr("(fp & keep) ^ turn").alias("v"), F.expr("shiftrightunsigned(fp & out, low) + what").alias("d"))


def _fingerprint_of(v: str = "v", d: str = "d") -> Column:
    k = F.shiftright(d, 24).bitwiseAND(F.lit(63)).cast("int")

    def of(h: int) -> Column:
        word = F.col(v).bitwiseXOR(F.get(_longs(_near(h)), k)).bitwiseAND(F.lit(_signed(~_mask(h) & ((1 << 64) - 1))))
        return word.bitwiseOR(F.shiftleft(F.col(d).bitwiseAND(F.lit((1 << 24) - 1)), _EDGES[h]))

    return _choose(F.shiftright(d, 30), of)


def links(nodes: DataFrame, radius: int = RADIUS, crowd: int = CROWD) -> DataFrame:
    """(a, b): pairs of the distinct fingerprints in ``fp`` that connect all within ``radius`` (3 at most) bits.

    All such pairs are listed, except inside crowded buckets, where each meeting point lists a star instead.
    """
    if not 0 <= radius <= 3:
        raise ValueError("words without a third and one flipped bit reach a radius of 3")
    # so many fingerprints unfold to some two million rows, whatever their few bytes suggest
    nodes = settle(nodes)
    rows = _variants(nodes.repartition(-(-nodes.count() // 15_000) or 1, "fp"), radius)
    hot = nodes.select(F.posexplode(F.array(*[_word(h) for h in range(PARTS)])).alias("h", "v")).groupBy("h", "v").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > crowd)
    crowded = settle(hot.select(F.explode(F.transform(_choose(F.col("h"), lambda h: _longs(_near(h, radius))), lambda x: F.col("v").bitwiseXOR(x))).alias("v")).distinct())
    some = not crowded.isEmpty()
    calm = rows.join(crowded, "v", "left_anti") if some else rows
    # Spark sizes a table unfolded from a shuffle as if every row stayed one, and would send 131 times that to the driver for a broadcast
    met = calm.hint("merge").join(calm.withColumnRenamed("d", "e"), "v").where("d < e").select(_fingerprint_of().alias("x"), _fingerprint_of("v", "e").alias("y"))
    close = met.where((F.col("x") != F.col("y")) & (F.bit_count(F.col("x").bitwiseXOR(F.col("y"))) <= radius))
    found = close.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"))
    if some:
        full = rows.join(crowded, "v", "left_semi").select(F.shiftright("d", 30).cast("int").alias("h"), "v", _fingerprint_of().alias("fp"))
        found = found.unionAll(_stars(full, radius))
    return found.distinct()


def links_whole(nodes: DataFrame, radius: int = RADIUS) -> DataFrame:
    """The same pairs by balls around whole fingerprints: 1 bit on one side, 2 on the other, 65 and 2,081 rows for each. For small tables."""
    if not 0 <= radius <= 3:
        raise ValueError("balls of 1 and 2 bits reach a radius of 3")
    small, large = (nodes.select("fp", F.explode(F.transform(_longs(sum(_flips((1 << 64) - 1, r), [])), lambda x: F.col("fp").bitwiseXOR(x))).alias("v")) for r in (1, 2))
    near = F.bit_count(F.col("fp").bitwiseXOR(F.col("fp2"))) <= radius
    met = small.join(large.withColumnRenamed("fp", "fp2"), "v").where((F.col("fp") != F.col("fp2")) & near)
    return met.select(F.least("fp", "fp2").alias("a"), F.greatest("fp", "fp2").alias("b")).distinct()


def _stars(rows: DataFrame, radius: int) -> DataFrame:
    """Links of crowded buckets, from rows (h, v, fp) that lie t = 0 or 1 bits off the bucket's word.

    Rows emit the variants of their left-out bits: those with t = 0 within 2 bits, the others within 1. A row is a hub at a
    variant if it has t = 0 and lies within 1 bit of it, or t = 1 and lies on it: then every row there is its true neighbour, since
    the bits of both sides add up to 3 at most. Of two neighbours in a bucket one is a hub where they meet: they differ in t + t' bits
    of the word at most, so in 3, 2 or 1 bits of the rest. So a star around one hub of each meeting point loses nothing, and
    where there is no hub, no two members need be neighbours.
    """
    off = rows.withColumn("t", (F.col("v") != _choose(F.col("h"), _word)).cast("int"))
    off = off.withColumn("o", F.col("fp").bitwiseAND(_choose(F.col("h"), lambda h: F.lit(_signed(_mask(h))))))
    far = lambda k: F.explode(F.transform(_choose(F.col("h"), lambda h: _longs(_flips(_mask(h), 2)[k])), lambda x: F.col("o").bitwiseXOR(x))).alias("p")
    points = off.select("h", "v", "fp", F.lit(True).alias("hub"), F.col("o").alias("p"))
    points = points.unionAll(off.select("h", "v", "fp", (F.col("t") == 0).alias("hub"), far(1)))
    points = points.unionAll(off.where("t = 0").select("h", "v", "fp", F.lit(False).alias("hub"), far(2)))
    hubs = points.where("hub").groupBy("h", "v", "p").agg(F.min("fp").alias("centre"))
    near = points.hint("merge").join(hubs, ["h", "v", "p"]).where("fp <> centre").where(F.bit_count(F.col("fp").bitwiseXOR(F.col("centre"))) <= radius)
    return near.select(F.least("fp", "centre").alias("a"), F.greatest("fp", "centre").alias("b"))


def components(prints: DataFrame, radius: int = RADIUS, crowd: int = CROWD) -> DataFrame:
    """``prints`` plus component_id, the smallest doc_id reachable over links, the row's own included, and root, one fingerprint of the component."""
    nodes = prints.groupBy("fp").agg(F.min("doc_id").alias("least_id"))  # cheap to do again from the settled fingerprints
    joined = connected_components(links(nodes.select("fp"), radius, crowd))
    rooted = nodes.join(joined, nodes.fp == joined.node, "left").select("fp", "least_id", F.coalesce("root", "fp").alias("root"))
    least = rooted.groupBy("root").agg(F.min("least_id").alias("component_id"))
    named = rooted.join(least, "root").select(F.col("fp").alias("_fp"), "root", "component_id")
    return prints.join(named, prints.fp == named["_fp"]).drop("_fp")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = RADIUS, crowd: int = CROWD) -> DataFrame:
    """(doc_id, tkey, fp, root, component_id) of every row."""
    return components(settle(fingerprints(docs, id_col, text_col)), radius, crowd)


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` with its columns and one row of each component: of the rows with the smallest id, the one with the smallest key."""
    found = near_duplicates(docs, id_col, text_col)
    first = found.groupBy("root").agg(F.min(F.struct(F.col("doc_id").isNull(), "doc_id", "tkey")).alias("f"))
    name, key, own = (spare(docs, f"_sh_{x}") for x in ("id", "key", "tkey"))
    chosen = first.select(F.col("f.doc_id").alias(name), F.col("f.tkey").alias(key))
    same = F.col(id_col).cast("long").eqNullSafe(F.col(name)) & (F.col(own) == F.col(key))
    return docs.withColumn(own, text_key(text_col)).join(chosen, same, "left_semi").dropDuplicates([id_col, own]).select(*docs.columns)


def op4_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicates(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
