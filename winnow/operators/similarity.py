"""Closeness of documents to a task's unlabelled text.

Defined cases, for every way of pooling: null and empty texts, and texts without words, have similarity 0; a seed text without
words takes part in no mean and no norm; a seed without any words is an error where a centroid is scored; every row is scored under its key, and rows that share
a key are scored as one text where words are summed by key (run ``dedup.exact`` first); a null key is a key; empty tables give
empty results; other columns are not read, so their names can't clash.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from winnow.functions import vectors
from winnow.functions.textops import sum_of_squared_counts, words
from winnow.plans.settle import bounded, fits, settle

POOLS = ("centroid", "max", "mean", "per_task_max")
#: Seed terms up to this number, if their bytes fit as well, are sent to every executor; a seed is a task's text, some 10^5 words.
SEED_BROADCAST = 1_000_000
#: Weights of all seed texts together up to which they go to every task as arrays, some 60 MB.
SEED_ENTRIES = 5_000_000


def sparse_tf(texts: DataFrame, key: str = "doc_id", text: str = "text", idf: DataFrame | None = None) -> DataFrame:
    """(key, term, w): counts, times inverse document frequency where (term, idf) is given."""
    tf = texts.select(F.col(key), F.explode(words(text)).alias("term")).groupBy(key, "term").agg(F.count(F.lit(1)).cast("double").alias("w"))
    if idf is None:
        return tf
    return tf.join(idf, "term").select(key, "term", (F.col("w") * F.col("idf")).alias("w"))


def inverse_frequency(docs: DataFrame) -> DataFrame:
    """(term, idf) with idf = ln((1 + N) / (1 + df)) + 1."""
    n = docs.count()
    df = docs.select(F.explode(F.array_distinct(words("text"))).alias("term")).groupBy("term").agg(F.count(F.lit(1)).alias("df"))
    return df.select("term", (F.log(F.lit(1.0 + n) / (F.col("df") + 1)) + 1).alias("idf"))


def unit(tf: DataFrame, key: str) -> DataFrame:
    norms = tf.groupBy(key).agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("_n"))
    return tf.join(norms, key).withColumn("w", F.col("w") / F.col("_n")).drop("_n")


def centroid(seed: DataFrame, key: str = "seed_id", weighting: str = "by_document", idf: DataFrame | None = None, by: str | None = None) -> DataFrame:
    """(term, w): mean of the seed texts' unit vectors; by_task gives every task equal say; ``by`` keeps tasks apart."""
    if weighting not in ("by_document", "by_task"):
        raise ValueError("task_weighting is by_document or by_task")
    u = unit(sparse_tf(seed, key, idf=idf), key)
    if by is None and weighting == "by_document":
        n = seed.where(F.size(words("text")) > 0).count()
        return u.groupBy("term").agg((F.sum("w") / F.lit(float(max(n, 1)))).alias("w"))
    tasks = seed.select(F.col(key), F.col(by or "task").alias("task"))
    sizes = tasks.groupBy("task").agg(F.count(F.lit(1)).alias("_s"))
    each = u.join(tasks, key).join(sizes, "task").groupBy("task", "term").agg((F.sum("w") / F.first("_s")).alias("w"))
    if by is not None:
        return each
    n = sizes.count()
    return each.groupBy("term").agg((F.sum("w") / F.lit(float(max(n, 1)))).alias("w"))


def score(docs: DataFrame, centre: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, n_tokens, similarity): cosine of term counts with a centroid; 0 for a text without words.

    The document's norm comes from its own row and the dot product from a broadcast join of its words with the
    centroid's terms, summed where they were exploded; nothing the size of the corpus's words is shuffled.
    """
    centre = settle(centre)
    norm = centre.agg(F.coalesce(F.sqrt(F.sum(F.col("w") * F.col("w"))), F.lit(0.0)).alias("n"), F.count(F.lit(1)).alias("c")).first()
    if not norm["n"]:
        raise ValueError("the seed has no words")
    terms = F.broadcast(centre) if norm["c"] <= SEED_BROADCAST and fits(centre) else centre
    w = words(text)
    rows = docs.select(F.col(key), w.alias("_w")).select(key, "_w", F.sqrt(sum_of_squared_counts(F.col("_w")).cast("double")).alias("_norm"))
    words_of = rows.select(key, "_norm", F.explode_outer("_w").alias("term"))
    dots = words_of.join(terms, "term", "left").groupBy(key).agg(F.count("term").alias("n_tokens"), F.sum("w").alias("_dot"), F.max("_norm").alias("_norm"))
    cos = F.when(F.col("_norm") > 0, F.coalesce("_dot", F.lit(0.0)) / (F.col("_norm") * F.lit(norm["n"]))).otherwise(F.lit(0.0))
    return dots.select(key, "n_tokens", cos.alias("similarity"))


def score_each(docs: DataFrame, seed: DataFrame, pool: str, key: str = "doc_id", seed_key: str = "seed_id") -> DataFrame:
    """(key, similarity): max or mean over the seed texts of the cosine with each; 0 for a text without words.

    The seed's unit vectors go to every task as arrays, and a document's cosines are summed within its row, so nothing is shuffled.
    A seed of more than SEED_ENTRIES weights is joined by its terms instead.
    """
    u = settle(unit(sparse_tf(seed, seed_key), seed_key))
    size = u.agg(F.count(F.lit(1)).alias("n"), F.count_distinct(seed_key).alias("k")).first()
    if size["n"] > SEED_ENTRIES:
        d = unit(sparse_tf(docs, key), key)
        dots = d.join(u.select(seed_key, "term", F.col("w").alias("v")), "term").groupBy(key, seed_key).agg(F.sum(F.col("w") * F.col("v")).alias("cos"))
        best = dots.groupBy(key).agg(F.max("cos").alias("top"), (F.sum("cos") / F.lit(float(size["k"]))).alias("mean"))
        return docs.select(key).join(best, key, "left").select(key, F.coalesce("top" if pool == "max" else "mean", F.lit(0.0)).alias("similarity"))
    number: dict = {}
    by_term: dict[str, tuple[list, list]] = {}
    for r in u.toLocalIterator():
        rows, values = by_term.setdefault(r["term"], ([], []))
        rows.append(number.setdefault(r[seed_key], len(number)))
        values.append(r["w"])
    seeds = {t: (np.array(a, np.int32), np.array(b)) for t, (a, b) in by_term.items()}
    shared, k = docs.sparkSession.sparkContext.broadcast(seeds), max(len(number), 1)

    @F.pandas_udf("double")
    def pooled(lists: pd.Series) -> pd.Series:
        known = shared.value

        def one(found) -> float:
            n = Counter(found)
            hits = [(known[t], c) for t, c in n.items() if t in known]
            if not hits:
                return 0.0
            dots = np.bincount(np.concatenate([h[0] for h, _ in hits]), np.concatenate([h[1] * c for h, c in hits]), k)
            return float(dots.max() if pool == "max" else dots.sum() / k) / math.sqrt(sum(c * c for c in n.values()))

        return lists.map(one).astype(float)

    return docs.select(F.col(key), pooled(words("text")).alias("similarity"))


def score_weighted(docs: DataFrame, centre: DataFrame, idf: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, similarity) with counts times idf: a text's terms are counted within its row, and its norm and dot product are summed together."""
    kind = dict(docs.dtypes)[key]

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 512):  # bounds what one batch unfolds to
                part = b.slice(at, 512)
                rows = [(i, t, float(n)) for i, w in enumerate(part.column(1).to_pylist()) for t, n in (Counter(w) or {None: 0}).items()]
                which, term, n = zip(*rows, strict=True) if rows else ((), (), ())
                yield pa.RecordBatch.from_arrays([part.column(0).take(pa.array(which, pa.int64())), pa.array(term, pa.string()), pa.array(n, pa.float64())], names=["k", "term", "n"])

    centre = settle(centre)
    norm = centre.agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("n")).first()["n"]
    table = settle(idf.join(centre.select("term", F.col("w").alias("v")), "term", "left"))
    each = docs.select(F.col(key), words(text).alias("w")).mapInArrow(counted, f"k {kind}, term string, n double").join(bounded(table), "term", "left")
    sums = each.groupBy("k").agg(F.sum(F.col("n") * F.col("idf") * F.coalesce("v", F.lit(0.0))).alias("dot"), F.sqrt(F.sum(F.pow(F.col("n") * F.col("idf"), 2))).alias("size"))
    return sums.select(F.col("k").alias(key), F.coalesce(F.try_divide(F.col("dot"), F.col("size") * F.lit(norm)), F.lit(0.0)).alias("similarity"))


def similarity(docs: DataFrame, seed: DataFrame, pool: str = "centroid", weighting: str = "by_document", idf: DataFrame | None = None) -> DataFrame:
    """(doc_id, similarity) under any way of pooling the seed."""
    if pool not in POOLS:
        raise ValueError(f"pool must be one of {POOLS}")
    if pool in ("max", "mean"):
        return score_each(docs, seed, pool)
    if idf is not None:
        return score_weighted(docs, centroid(seed, weighting=weighting, idf=idf), idf)
    if pool == "per_task_max":
        c = settle(centroid(seed, by="task"))
        out = None
        for t in [r["task"] for r in c.select("task").distinct().orderBy("task").collect()]:  # a handful of tasks
            s = score(docs, c.where(F.col("task").eqNullSafe(F.lit(t))).select("term", "w")).select("doc_id", "similarity")
            out = s if out is None else out.unionByName(s)
        return out.groupBy("doc_id").agg(F.max("similarity").alias("similarity"))
    return score(docs, centroid(seed, weighting=weighting)).select("doc_id", "similarity")


DIMS = 64


def hashed_term(term) -> list:
    """64 signs from the bits of the term's md5, first half."""
    bits = [F.conv(F.substring(F.md5(term.cast("binary")), 1 + 8 * k, 8), 16, 10).cast("long") for k in (0, 1)]
    return [F.when(F.shiftright(bits[i // 32], 31 - i % 32).bitwiseAND(F.lit(1)) == 1, 1.0).otherwise(-1.0) for i in range(DIMS)]


def hashed_mean(texts: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, vec): mean over a text's words of hashed +-1 vectors, in one Arrow pass over the rows."""
    import hashlib

    @F.pandas_udf("array<double>")
    def mean(lists: pd.Series) -> pd.Series:
        known: dict[str, np.ndarray] = {}

        def one(tokens) -> list[float]:
            total = np.zeros(DIMS)
            for t in tokens:
                v = known.get(t)
                if v is None:
                    if len(known) > 100_000:
                        known.clear()
                    v = known[t] = np.unpackbits(np.frombuffer(hashlib.md5(t.encode()).digest()[:8], np.uint8)) * 2.0 - 1
                total += v
            return (total / max(1, len(tokens))).tolist()

        return lists.map(one)

    return texts.select(F.col(key), mean(words(text)).alias("vec"))


def dense_similarity(docs: DataFrame, seed: DataFrame, seed_key: str = "seed_id") -> DataFrame:
    """(doc_id, similarity) of hashed vectors with the seed's centroid, a 64-number literal."""
    unit_vec = vectors.scale("vec", F.try_divide(F.lit(1.0), vectors.norm("vec")))
    means = hashed_mean(seed, seed_key).where(vectors.norm("vec") > 0).select(unit_vec.alias("u")).agg(*vectors.mean("u", DIMS)).first()
    fixed = [means[f"_v{i}"] or 0.0 for i in range(DIMS)]
    size = sum(x * x for x in fixed) ** 0.5
    d = hashed_mean(docs)
    n = vectors.norm("vec") * F.lit(size)
    return d.select("doc_id", F.when(n > 0, vectors.against("vec", fixed) / n).otherwise(0.0).alias("similarity"))


def chunked(docs: DataFrame, centre: DataFrame, chunk: int = 128, pool: str = "mean") -> DataFrame:
    """(doc_id, similarity) pooled over windows of ``chunk`` words, which takes the advantage of long texts away."""
    w = words("text")
    n = F.greatest(F.ceil(F.size(w) / F.lit(chunk)).cast("int"), F.lit(1))
    windows = docs.select("doc_id", w.alias("w"), n.alias("n")).select("doc_id", F.posexplode(F.transform(F.sequence(F.lit(0), F.col("n") - 1), lambda i: F.array_join(F.slice("w", i * chunk + 1, F.lit(chunk)), " "))).alias("no", "text"))
    keyed = windows.select("doc_id", F.concat_ws(":", "doc_id", "no").alias("chunk_id"), "text")
    s = score(keyed.select("chunk_id", "text"), centre, key="chunk_id")
    doc = F.substring_index("chunk_id", ":", 1).cast("long")
    agg = F.avg("similarity") if pool == "mean" else F.max("similarity")
    return s.groupBy(doc.alias("doc_id")).agg(agg.alias("similarity"))
