"""Exact and near-duplicate removal of the paper's curation step, and repeated lines."""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from winnow.functions.textops import once, spare, words
from winnow.operators.components import connected_components
from winnow.operators.ranking import ranked
from winnow.plans.settle import settle

#: Bits of a gram's hash by which its frequency is bounded; the order of grams needs it, the result doesn't depend on it.
SPOT_BITS = 20


def _digest(text: str = "text") -> Column:
    return F.sha2(F.col(text).cast("binary"), 256)


def exact_clusters(docs: DataFrame) -> DataFrame:
    """(doc_id, keeper, copies): the smallest id with the same text, and how many rows have it.

    Only ids and 32-byte digests are shuffled, pre-aggregated where many copies share one. Null texts are copies of each
    other; a null id is a keeper only where no other row has the text; repeated rows are listed and counted each.
    """
    keyed = docs.select("doc_id", _digest().alias("digest"))
    groups = keyed.groupBy(F.col("digest").alias("_d")).agg(F.min("doc_id").alias("keeper"), F.count(F.lit(1)).alias("copies"))
    return keyed.join(groups, F.col("digest").eqNullSafe(F.col("_d"))).select("doc_id", "keeper", "copies")


def exact(docs: DataFrame) -> DataFrame:
    """``docs`` with one row of each text: of the rows with the smallest id (a null id comes last), the first by hash of the other columns.

    Keepers are found from ids, digests and hashes; texts meet them by these keys, so copies of one text spread over tasks.
    Null texts are one text; rows equal in every column leave one; an empty table stays empty; helper columns clash with none.
    """
    d, i, h, kd, ki, kh, r = (spare(docs, f"_ex_{x}") for x in ("d", "i", "h", "kd", "ki", "kh", "r"))
    others = [c for c, kind in docs.dtypes if c not in ("doc_id", "text") and "map<" not in kind and kind != "variant"]
    hashed = F.xxhash64(*others) if others else F.lit(0).cast("long")
    keyed = docs.withColumns({d: F.coalesce(_digest(), F.lit("")), i: F.col("doc_id"), h: hashed})
    first = keyed.groupBy(F.col(d).alias(kd)).agg(F.min(F.struct(F.col(i).isNull().alias("n"), F.col(i).alias("i"), F.col(h).alias("h"))).alias(r))
    keepers = first.select(kd, F.col(f"{r}.i").alias(ki), F.col(f"{r}.h").alias(kh))
    same = (F.col(d) == F.col(kd)) & F.col(i).eqNullSafe(F.col(ki)) & (F.col(h) == F.col(kh))
    return keyed.join(keepers, same, "left_semi").dropDuplicates([d, i, h]).select(*docs.columns)


def grams_of(docs: DataFrame, k: int = 5, text: str = "text") -> DataFrame:
    """(doc_id, grams): a text's word k-grams in order; a shorter text is one, an empty one has none."""
    w = docs.select("doc_id", words(text).alias("w")).where(F.size("w") > 0)  # words become a column before the lambda reads them
    return w.select("doc_id", F.transform(F.sequence(F.lit(1), F.greatest(F.size("w") - k + 1, F.lit(1))), lambda i: F.array_join(F.slice("w", i, F.lit(k)), " ")).alias("grams"))


def gram_sets(docs: DataFrame, k: int = 5, text: str = "text", least: int = 1) -> DataFrame:
    """(doc_id, grams): the set of a text's word k-grams as sorted 64-bit hashes; a text of fewer than ``least`` words has no row. Words are hashed first and a gram is a hash of hashes, so no gram is ever a string."""
    w = once(docs.select("doc_id", text), w=F.transform(words(text), lambda x: F.xxhash64(x))).where(F.size("w") >= least)
    grams = F.transform(F.sequence(F.lit(1), F.greatest(F.size("w") - k + 1, F.lit(1))), lambda i: F.xxhash64(F.slice("w", i, F.lit(k))))
    return w.select("doc_id", F.array_sort(F.array_distinct(grams)).alias("grams"))


def set_digests(sets: DataFrame, hashes: int = 0) -> DataFrame:
    """(doc_id, digest, sig): a 128-bit name of the gram set and its min-hashes, by multiply-shift hashing; ``hashes`` may be 0.

    What a document needs to be grouped and banded is a few hundred bytes; gram sets are made again where two must be compared.
    """
    rng = np.random.default_rng(7)
    mult = rng.integers(1 << 63, size=hashes, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    plus = rng.integers(1 << 63, size=hashes, dtype=np.uint64)

    def signed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            names, sigs = [], []
            for g in b.column(1):
                x = g.values.to_numpy(zero_copy_only=False).view(np.uint64)
                names.append(hashlib.blake2b(x.tobytes(), digest_size=16).digest())
                low = np.full(hashes, np.uint64(0xFFFFFFFFFFFFFFFF))
                for at in range(0, len(x) if hashes else 0, 4096):  # a long text is hashed piece by piece
                    low = np.minimum(low, (x[at : at + 4096, None] * mult + plus).min(axis=0))
                sigs.append((low >> np.uint64(32)).astype(np.uint32).view(np.int32))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(names, pa.binary()), pa.array(sigs, pa.list_(pa.int32()))], names=["doc_id", "digest", "sig"])

    return sets.select("doc_id", "grams").mapInArrow(signed, "doc_id long, digest binary, sig array<int>")


def near(docs: DataFrame, k: int = 5, hashes: int = 64, bands: int = 16, threshold: float = 0.8, block: int = 512) -> DataFrame:
    """(doc_id, keeper) of documents with a near copy: MinHash bands, exact Jaccard of what meets, components.

    Equal gram sets fold into their smallest document first. Every pair that shares a band is then either compared or already
    linked: the members of a bucket are dealt into blocks and all pairs of blocks meet, a hub and the neighbour by id first, so
    that a crowd of near copies is linked by a number of comparisons in proportion to it and only members that are still in
    different components, and share enough of their rarest grams, are compared after that. No bucket is capped.

    Defined cases: null texts and texts without words are copies of nothing; ids name documents (run ``exact`` first), and a
    row without id is left out; an empty table gives none; other columns are not read.
    """
    rows = hashes // bands
    some = docs.where(F.col("doc_id").isNotNull()).select("doc_id", "text")
    sets = gram_sets(some, k)
    prints = settle(set_digests(sets, hashes))
    reps = prints.groupBy("digest").agg(F.min("doc_id").alias("rep"), F.min_by("sig", "doc_id").alias("sig"))
    unique = settle(reps.select("digest", F.col("rep").alias("doc_id"), "sig"))
    members = settle(prints.select("doc_id", "digest").join(unique.select("digest", F.col("doc_id").alias("rep")), "digest").select("doc_id", "rep"))
    keys = F.array(*[F.struct(F.lit(b).alias("band"), F.xxhash64(F.slice("sig", b * rows + 1, rows)).alias("key")) for b in range(bands)])
    banded = unique.select("doc_id", F.explode(keys).alias("at")).select("doc_id", "at.band", "at.key")
    hub = banded.groupBy("band", "key").agg(F.min("doc_id").alias("hub"), F.count(F.lit(1)).alias("n")).where("n > 1")
    met = settle(banded.join(hub, ["band", "key"]))
    hubs = met.where("doc_id <> hub").select(F.col("hub").alias("a"), F.col("doc_id").alias("b"))
    # neighbours by id in a bucket: range partitions, so a crowded bucket is sorted by many tasks
    placed = ranked(met.where("n > 2").select("band", "key", "doc_id"), ["band", "key"], ["doc_id"], "place")
    own, after = placed.select("band", "key", "place", F.col("doc_id").alias("a")), placed.select("band", "key", (F.col("place") - 1).alias("place"), F.col("doc_id").alias("b"))
    chain = own.join(after, ["band", "key", "place"]).select("a", "b")
    close = settle(_measured(hubs.unionAll(chain).distinct(), sets, threshold).select("a", "b"))
    # what shares a bucket of three or more and is not linked yet
    crowd = settle(met.where("n > 2").select("doc_id").distinct())
    if not crowd.isEmpty():
        first = connected_components(close)
        rooted = settle(crowd.join(first, F.col("doc_id") == F.col("node"), "left").select("doc_id", F.coalesce("root", "doc_id").alias("root")))
        mixed = met.where("n > 2").join(rooted, "doc_id").groupBy("band", "key").agg(F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo < hi")
        open_ = settle(met.join(mixed, ["band", "key"], "left_semi").select("doc_id").distinct().join(rooted, "doc_id"))
        if not open_.isEmpty():
            among = sets.join(open_, "doc_id").select("doc_id", "grams", "root")
            close = close.unionAll(_measured(_sharing(among, threshold, apart="root", block=block), sets, threshold).select("a", "b"))
    joined = connected_components(close)
    rooted = members.join(joined, F.col("rep") == F.col("node"), "left").select("doc_id", F.coalesce("root", "rep").alias("keeper"))
    sizes = rooted.groupBy(F.col("keeper").alias("_k")).agg(F.count(F.lit(1)).alias("_n")).where("_n > 1")
    return rooted.join(sizes, F.col("keeper") == F.col("_k"), "left_semi")


def drop_near(docs: DataFrame, **how) -> DataFrame:
    """``docs`` with one document of each near-duplicate group."""
    gone = near(docs, **how).where("doc_id <> keeper").select("doc_id")
    return docs.join(gone, "doc_id", "left_anti")


def _spots(grams: pa.Array, bits: int = SPOT_BITS) -> np.ndarray:
    return (grams.to_numpy(zero_copy_only=False).view(np.uint64) >> np.uint64(64 - bits)).astype(np.int64)


def _crowding(sets: DataFrame, parts: int = 256, bits: int = SPOT_BITS) -> np.ndarray:
    """How many grams of ``sets`` fall on each of a fixed number of hash spots: an upper bound of how many documents hold a gram."""

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = np.zeros(1 << bits, np.int64)
        for b in batches:
            held += np.bincount(_spots(b.column(0).flatten(), bits), minlength=len(held))
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(parts, dtype=np.int32)), pa.array([x.tobytes() for x in np.split(held, parts)], pa.binary())], names=["part", "held"])

    def summed(t: pa.Table) -> pa.Table:
        total = sum(np.frombuffer(x, np.int64) for x in t.column("held").to_pylist())
        return pa.table({"part": pa.array([t.column("part")[0].as_py()], pa.int32()), "held": pa.array([total.tobytes()], pa.binary())})

    rows = sets.select("grams").mapInArrow(counted, "part int, held binary").groupBy("part").applyInArrow(summed, "part int, held binary").collect()  # 8 bytes a spot, whatever the input
    found = {r["part"]: np.frombuffer(r["held"], np.int64) for r in rows}
    return np.concatenate([found[i] for i in range(parts)]) if found else np.zeros(1 << bits, np.int64)


def _sharing(sets: DataFrame, threshold: float, among: DataFrame | None = None, apart: str | None = None, block: int = 512) -> DataFrame:
    """(a, b) of every pair of ``sets`` (doc_id, grams) that can reach ``threshold``, and of some that don't.

    With the grams of all documents in one order, a pair that reaches the threshold shares one of the first
    n - ceil(n * threshold) + 1 of each side, so only these are joined; the order puts rare ones first. No gram is left out
    for being common: the holders of a crowded one are dealt into blocks, and every pair of blocks meets. Pairs whose
    lengths or places already rule the threshold out are dropped, and with ``apart`` those that agree in that column.
    ``among`` (doc_id) leaves the other documents out.
    """
    extra = [apart] if apart else []
    crowding = _crowding(sets)

    def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            at, n, place, g = [], [], [], []
            for i, grams in enumerate(b.column(0)):
                size = len(grams.values) if grams.is_valid else 0
                if size:
                    take = size - math.ceil(size * threshold - 1e-6) + 1
                    x = grams.values.to_numpy(zero_copy_only=False)
                    g.append(x[np.lexsort((x, crowding[_spots(grams.values)]))[:take]])
                    at.append(np.full(take, i))
                    n.append(np.full(take, size, np.int32))
                    place.append(np.arange(1, take + 1, dtype=np.int32))
            if at:
                which = pa.array(np.concatenate(at))
                yield pa.RecordBatch.from_arrays([*[c.take(which) for c in b.columns[1:]], *[pa.array(np.concatenate(c)) for c in (n, place, g)]], names=["doc_id", *extra, "n", "place", "g"])

    prefix = sets.select("grams", "doc_id", *extra).mapInArrow(first, ", ".join(["doc_id long", *[f"{c} long" for c in extra], "n int, place int, g long"]))
    prefix = settle(prefix.join(among, "doc_id", "left_semi") if among is not None else prefix)
    blocks = prefix.groupBy("g").agg(F.ceil(F.count(F.lit(1)) / block).cast("int").alias("blocks"), F.count(F.lit(1)).alias("m")).where("m > 1").drop("m")
    sided = prefix.join(blocks, "g").withColumn("side", F.pmod(F.xxhash64("doc_id"), F.col("blocks")).cast("int"))
    dealt = sided.withColumn("o", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).withColumn("i", F.least("side", "o")).withColumn("j", F.greatest("side", "o"))
    a, b = (dealt.select("g", "i", "j", *[F.col(c).alias(f"{c}_{x}") for c in ("doc_id", "n", "place", "side", *extra)]) for x in "ab")
    fits = (F.least("n_a", "n_b") >= F.greatest("n_a", "n_b") * threshold - 1e-6) & (
        (F.least(F.col("n_a") - F.col("place_a"), F.col("n_b") - F.col("place_b")) + 1) * (1 + threshold) >= (F.col("n_a") + F.col("n_b")) * threshold - 1e-6
    )
    met = (F.col("doc_id_a") < F.col("doc_id_b")) & ((F.col("i") == F.col("j")) | (F.col("side_a") != F.col("side_b"))) & fits
    if apart:
        met &= F.col(f"{apart}_a") != F.col(f"{apart}_b")
    return a.join(b, ["g", "i", "j"]).where(met).select(F.col("doc_id_a").alias("a"), F.col("doc_id_b").alias("b")).distinct()


def _measured(pairs: DataFrame, sets: DataFrame, threshold: float) -> DataFrame:
    """(a, b, jaccard) of the pairs that reach ``threshold``, over the whole gram sets."""
    pairs = settle(pairs)
    named = pairs.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct()
    sets = settle(sets.join(named, "doc_id", "left_semi").select("doc_id", "grams"))
    left, right = (sets.select(F.col("doc_id").alias(x), F.col("grams").alias(f"g{x}")) for x in "ab")
    both = F.size(F.array_intersect("ga", "gb"))
    return pairs.join(left, "a").join(right, "b").select("a", "b", (both / (F.size("ga") + F.size("gb") - both)).alias("jaccard")).where(F.col("jaccard") >= threshold)


def resembling_pairs(docs: DataFrame, k: int = 5, threshold: float = 0.8) -> DataFrame:
    """(a, b, jaccard) of all pairs whose k-gram sets reach ``threshold``, however many documents hold a gram: the exact reference for ``near``.

    Grams are 64-bit hashes. Equal sets fold into their smallest document, which is compared for all of them. The result
    itself grows with the square of a group of near copies.
    """
    sets = gram_sets(docs.where(F.col("doc_id").isNotNull()), k)
    keyed = settle(set_digests(sets).select("doc_id", "digest"))
    reps = keyed.groupBy("digest").agg(F.min("doc_id").alias("rep"))
    members = settle(keyed.join(reps, "digest").select("doc_id", "rep"))
    close = _measured(_sharing(sets, threshold, members.where("doc_id = rep").select("doc_id")), sets, threshold)
    own, other = (members.select(F.col("rep").alias(x), F.col("doc_id").alias(f"d{x}")) for x in "ab")
    across = close.join(own, "a").join(other, "b").select(F.least("da", "db").alias("a"), F.greatest("da", "db").alias("b"), F.round("jaccard", 6).alias("jaccard"))
    alike = own.join(other, F.col("a") == F.col("b")).where("da < db").select(F.col("da").alias("a"), F.col("db").alias("b"), F.lit(1.0).alias("jaccard"))
    return across.unionAll(alike)


def repeated_lines(docs: DataFrame, min_docs: int = 3, min_chars: int = 10) -> DataFrame:
    """(doc_id, text, dropped): texts without the lines that at least ``min_docs`` documents hold.

    Lines travel as 128-bit hashes and come back as positions; texts are shuffled once, to meet the positions of their own
    document. A common line is counted after its documents are made distinct and meets a table of one row per line.

    Defined cases: a null or empty text is one empty line; documents are rows told apart by id and text, and a line counts
    once per id, rows without id together; repeated rows are returned each; empty tables give empty results.
    """
    keyed = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).withColumn("_t", F.xxhash64("text"))
    lines = keyed.select("doc_id", "_t", F.posexplode(F.split("text", "\n")).alias("pos", "line")).where(F.length("line") >= min_chars).select("doc_id", "_t", "pos", F.unhex(F.md5(F.col("line").cast("binary"))).alias("key"))
    shared = lines.select("key", "doc_id").distinct().groupBy("key").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= min_docs).select("key")
    drops = lines.join(shared, "key").groupBy(F.col("doc_id").alias("_d"), F.col("_t").alias("_u")).agg(F.collect_set("pos").alias("gone"))
    met = keyed.join(drops, F.col("doc_id").eqNullSafe(F.col("_d")) & (F.col("_t") == F.col("_u")), "left").select("doc_id", "text", "gone")
    held = F.array_except(F.sequence(F.lit(0), F.size(F.split("text", "\n")) - 1), "gone")
    kept = F.array_join(F.transform("held", lambda i: F.get("parts", i)), "\n")
    some = once(met.where("gone IS NOT NULL"), parts=F.split("text", "\n"), held=held).select("doc_id", kept.alias("text"), F.size("gone").cast("long").alias("dropped"))
    return some.unionAll(met.where("gone IS NULL").select("doc_id", "text", F.lit(0).cast("long").alias("dropped")))
