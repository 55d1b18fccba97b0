"""n-gram language models as count tables: training is counting, continued training adds counts.

Defined cases: null and empty texts have no words, add nothing to a model and have no likelihood, so they are left out of its
results; a model of no text gives every word the probability of the unknown one; rows that share a key are scored as one text,
a null key being a key; repeated rows count each time in training; a very long text is many words of one row, summed where it is
exploded; other columns are not read.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from winnow.functions.textops import words
from winnow.operators.skew import salted_join
from winnow.plans.settle import fits, settle

#: Up to so many distinct terms, and if their bytes fit as well, a model is sent to every executor; beyond it terms are joined by shuffle.
TERMS_BROADCAST = 1_000_000


@dataclass(frozen=True)
class Model:
    """Unigram counts (term, c), bigram counts (prev, term, c) for order 2, and the totals scoring needs."""

    unigrams: DataFrame
    bigrams: DataFrame | None
    total: int
    vocabulary: int
    alpha: float = 1.0
    lam: float = 0.5
    small: bool = True  # whether the unigram table may be broadcast

    @property
    def order(self) -> int:
        return 1 if self.bigrams is None else 2

    def p1(self, count: Column) -> Column:
        return (F.coalesce(count, F.lit(0)) + F.lit(self.alpha)) / F.lit(self.total + self.alpha * (self.vocabulary + 1))

    def sized(self) -> DataFrame:
        """The unigram table, with a broadcast hint if its number of terms and their bytes allow it."""
        return F.broadcast(self.unigrams) if self.small else self.unigrams

    def looked_up(self, rows: DataFrame) -> DataFrame:
        """``rows`` with a column term, plus c, its count or null. A large model is joined by shuffle with its frequent words dealt out."""
        if self.small:
            return rows.join(F.broadcast(self.unigrams), "term", "left")
        return salted_join(rows, self.unigrams, ["term"], max(self.total, 1), self.unigrams.select("term", F.col("c").alias("n")), how="left")


def unigram_counts(texts: DataFrame, text: str = "text") -> DataFrame:
    return texts.select(F.explode(words(text)).alias("term")).groupBy("term").agg(F.count(F.lit(1)).alias("c"))


def bigram_counts(texts: DataFrame, text: str = "text") -> DataFrame:
    w = words(text)
    pairs = F.zip_with(F.slice(w, F.lit(1), F.greatest(F.size(w) - 1, F.lit(0))), F.slice(w, F.lit(2), F.greatest(F.size(w) - 1, F.lit(0))), lambda a, b: F.struct(a.alias("prev"), b.alias("term")))
    return texts.select(F.explode(pairs).alias("p")).groupBy("p.prev", "p.term").agg(F.count(F.lit(1)).alias("c"))


def _model(unigrams: DataFrame, bigrams: DataFrame | None, alpha: float, lam: float) -> Model:
    unigrams = settle(unigrams)
    t = unigrams.agg(F.coalesce(F.sum("c"), F.lit(0)).alias("n"), F.count(F.lit(1)).alias("v")).first()
    small = int(t["v"]) <= TERMS_BROADCAST and fits(unigrams)
    return Model(unigrams, None if bigrams is None else settle(bigrams), int(t["n"]), int(t["v"]), alpha, lam, small)


def train(texts: DataFrame, order: int = 1, alpha: float = 1.0, lam: float = 0.5, min_count: int = 1, text: str = "text") -> Model:
    """Counts of ``texts``; terms below ``min_count`` are treated as unseen."""
    uni = unigram_counts(texts, text)
    if min_count > 1:
        uni = uni.where(F.col("c") >= min_count)
    return _model(uni, bigram_counts(texts, text) if order == 2 else None, alpha, lam)


def continue_training(base: Model, texts: DataFrame, gamma: float = 1.0, text: str = "text") -> Model:
    """One epoch: gamma times the counts of ``texts`` are added. gamma 0 is the base."""
    if gamma == 0:
        return base

    def added(old: DataFrame, new: DataFrame, keys: list[str]) -> DataFrame:
        both = old.unionByName(new.withColumn("c", F.col("c") * F.lit(gamma) if gamma != int(gamma) else F.col("c") * F.lit(int(gamma))))
        return both.groupBy(*keys).agg(F.sum("c").alias("c"))

    uni = added(base.unigrams, unigram_counts(texts, text), ["term"])
    bi = None if base.bigrams is None else added(base.bigrams, bigram_counts(texts, text), ["prev", "term"])
    return _model(uni, bi, base.alpha, base.lam)


def exact_sum(x: Column) -> Column:
    """The sum of logarithms as a double that doesn't depend on the order of the rows, as a plain sum of doubles does in its last digits.

    Each value is split into two whole numbers, down to 2^-62, whose sums are exact, so texts whose words have the same probabilities
    get the same sum; a perplexity in the millions would show the difference at nine decimals and break their tie. Null values are left out.
    """
    high = F.floor(x * F.lit(2.0**30))
    low = F.floor((x * F.lit(2.0**30) - high) * F.lit(2.0**32))
    return (F.sum(high) + F.sum(low) / F.lit(2.0**32)) / F.lit(2.0**30)


def log_likelihood(texts: DataFrame, model: Model, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, n_tokens, ll): summed ln p of a text's words; texts without words are left out.

    Words are exploded, joined and summed back. The rows of a text leave the explode together, so partial
    aggregation hands about one row per text to the shuffle. For order 2 the pairs of a text are counted within its row first, so
    each of its distinct pairs is one row of the join; a bigram table that doesn't fit a broadcast is joined with frequent pairs dealt out.
    """
    if model.order == 1:
        terms = texts.select(F.col(key).alias("_k"), F.explode(words(text)).alias("term"))
        p = model.looked_up(terms).select("_k", F.lit(1).cast("long").alias("n"), F.log(model.p1(F.col("c"))).alias("lp"))
    else:
        pairs = _counted_pairs(texts, key, text)
        prior = model.unigrams.select(F.col("term").alias("prev"), F.col("c").alias("c_prev"))
        bi = model.bigrams.select("prev", "term", F.col("c").alias("c2"))
        j = model.looked_up(pairs)
        if model.small:
            j = j.join(F.broadcast(prior), "prev", "left")
        else:
            j = salted_join(j, prior, ["prev"], max(model.total, 1), prior.select("prev", F.col("c_prev").alias("n")), how="left")
        j = j.join(F.broadcast(bi), ["prev", "term"], "left") if fits(bi) else salted_join(j, bi, ["prev", "term"], max(model.total, 1), bi.select("prev", "term", F.col("c2").alias("n")), how="left")
        p1 = model.p1(F.col("c"))
        p2 = F.lit(model.lam) * F.coalesce("c2", F.lit(0)) / F.col("c_prev") + F.lit(1 - model.lam) * p1
        p = j.select("_k", F.col("times").alias("n"), F.log(F.when(F.col("c_prev") > 0, p2).otherwise(p1)).alias("lp"))
    return p.groupBy(F.col("_k").alias(key)).agg(F.sum("n").alias("n_tokens"), exact_sum(F.col("n") * F.col("lp")).alias("ll"))


def _counted_pairs(texts: DataFrame, key: str, text: str) -> DataFrame:
    """(_k, prev, term, times): the distinct pairs of neighbouring words of each text, the first word's with no prev."""
    kind = dict(texts.dtypes)[key]

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 512):  # bounds what one batch unfolds to
                part = b.slice(at, 512)
                rows = [(k, x, y, n) for k, w in enumerate(part.column(1).to_pylist()) for (x, y), n in Counter(zip([None, *w], w, strict=False)).items()]
                which, prev, term, times = zip(*rows, strict=True) if rows else ((), (), (), ())
                yield pa.RecordBatch.from_arrays([part.column(0).take(pa.array(which, pa.int64())), pa.array(prev, pa.string()), pa.array(term, pa.string()), pa.array(times, pa.int64())], names=["_k", "prev", "term", "times"])

    return texts.select(F.col(key), words(text).alias("w")).mapInArrow(counted, f"_k {kind}, prev string, term string, times long")


#: Up to so many distinct pairs a bigram table is sent to every worker as sorted numbers of 16 bytes.
PAIRS_BROADCAST = 8_000_000


def both_likelihoods(texts: DataFrame, model: Model, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, n_tokens, ll1, ll2): ``log_likelihood`` under the unigrams alone and under the whole bigram model, in one pass.

    Terms become numbers and pairs of them sorted numbers, which every worker holds, so no pair of the texts is shuffled; a
    model that is too large for that is joined. Sums are exact, as those of ``exact_sum``.
    """
    if not model.small or model.bigrams.count() > PAIRS_BROADCAST:
        one = Model(model.unigrams, None, model.total, model.vocabulary, model.alpha, model.lam, model.small)
        x, y = log_likelihood(texts, one, key, text), log_likelihood(texts, model, key, text)
        return x.withColumnRenamed("ll", "ll1").join(y.select(key, F.col("ll").alias("ll2")), key)
    sc = texts.sparkSession.sparkContext
    terms = model.unigrams.select("term", "c").toArrow()
    number = {t: i for i, t in enumerate(terms.column(0).to_pylist())}
    numbers = sc.broadcast(number)
    wide = len(number) + 1

    def keyed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at = numbers.value
        for b in batches:
            prev, term = (np.array([at[t] for t in c.to_pylist()], np.int64) for c in b.columns[:2])
            yield pa.RecordBatch.from_arrays([pa.array(prev * wide + term), b.column(2)], names=["pair", "c"])

    pairs = model.bigrams.select("prev", "term", "c").mapInArrow(keyed, "pair long, c long").toArrow()
    pair = pairs.column(0).to_numpy()
    by = np.argsort(pair)
    held = sc.broadcast((np.append(terms.column(1).to_numpy(), 0), pair[by], pairs.column(1).to_numpy()[by]))
    alpha, lam, total = model.alpha, model.lam, model.total + model.alpha * (model.vocabulary + 1)
    kind = dict(texts.dtypes)[key]

    def split(lp: np.ndarray) -> tuple[int, int]:
        high = np.floor(lp * 2.0**30)
        return int(high.sum()), int(np.floor((lp * 2.0**30 - high) * 2.0**32).sum())

    def scored(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, (c, pair, times) = numbers.value, held.value
        lp1, unknown = np.log((c + alpha) / total), wide - 1
        for b in batches:
            rows = []
            for start in range(0, b.num_rows, 64):  # bounds the word lists held at a time
                for w in b.column(1).slice(start, 64).to_pylist():
                    i = np.array([at.get(t, unknown) for t in w or ()], np.int64)
                    first = np.append(unknown, i[:-1])[: len(i)]
                    p, base = (c[i] + alpha) / total, c[first]
                    k = first * wide + i
                    found = np.minimum(np.searchsorted(pair, k), max(len(pair) - 1, 0))
                    n = np.where(pair[found] == k, times[found], 0) if len(pair) else np.zeros(len(i))
                    lp2 = np.log(np.where(base > 0, lam * n / np.maximum(base, 1) + (1 - lam) * p, p))
                    rows.append((len(i), *split(lp1[i]), *split(lp2)))
            cols = list(zip(*rows, strict=True)) or [()] * 5
            yield pa.RecordBatch.from_arrays([b.column(0), *[pa.array(x, pa.int64()) for x in cols]], names=[key, "n", "h1", "l1", "h2", "l2"])

    out = texts.select(F.col(key), words(text).alias("w")).mapInArrow(scored, f"{key} {kind}, n long, h1 long, l1 long, h2 long, l2 long").where("n > 0")
    whole = lambda i: ((F.sum(f"h{i}") + F.sum(f"l{i}") / F.lit(2.0**32)) / F.lit(2.0**30)).alias(f"ll{i}")
    return out.groupBy(key).agg(F.sum("n").alias("n_tokens"), whole(1), whole(2))


def perplexity(texts: DataFrame, model: Model, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, n_tokens, perplexity)."""
    ll = log_likelihood(texts, model, key, text)
    return ll.select(key, "n_tokens", F.exp(-F.col("ll") / F.col("n_tokens")).alias("perplexity"))


def corpus_perplexity(texts: DataFrame, model: Model, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row: perplexity of all words together."""
    ll = log_likelihood(texts, model, key, text)
    return ll.agg(F.sum("n_tokens").alias("n_tokens"), F.exp(-F.sum("ll") / F.sum("n_tokens")).alias("perplexity"))


def normalised(ll: DataFrame, how: str, texts: DataFrame | None = None, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Log likelihood as it is, per word or per byte."""
    if how == "none":
        return ll.withColumn("score", F.col("ll"))
    if how == "tokens":
        return ll.withColumn("score", F.col("ll") / F.col("n_tokens"))
    if how == "bytes":
        sizes = texts.select(F.col(key).alias("_b"), F.octet_length(text).alias("_n"))
        return ll.join(sizes, F.col(key) == F.col("_b")).withColumn("score", F.col("ll") / F.col("_n")).drop("_b", "_n")
    raise ValueError("normalise by none, tokens or bytes")


def pack(model: Model, bits: int = 20) -> list[float]:
    """ln p of each of 2^bits hash buckets, for scoring whole documents without a join. The size is fixed by ``bits``."""
    buckets = model.unigrams.groupBy(F.pmod(F.xxhash64("term"), F.lit(1 << bits)).alias("b")).agg(F.sum("c").alias("c"))
    table = np.zeros(1 << bits)
    for r in buckets.toLocalIterator():
        table[r["b"]] = r["c"]
    return np.log((table + model.alpha) / (model.total + model.alpha * (model.vocabulary + 1)))


def perplexity_packed(texts: DataFrame, packed, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, n_tokens, perplexity) by bucket lookups in one pass; terms that share a bucket share its count."""
    size = len(packed)
    shared = texts.sparkSession.sparkContext.broadcast(np.asarray(packed, np.float32))

    @F.pandas_udf("double")
    def mean_lp(buckets: pd.Series) -> pd.Series:
        table = shared.value
        return buckets.map(lambda b: float(table[np.asarray(b, np.int64)].mean(dtype=np.float64)) if len(b) else None).astype(float)

    w = words(text)
    b = F.transform(w, lambda t: F.pmod(F.xxhash64(t), F.lit(size)).cast("int"))
    out = texts.select(F.col(key), F.size(w).cast("long").alias("n_tokens"), mean_lp(b).alias("m"))
    return out.where("n_tokens > 0").select(key, "n_tokens", F.exp(-F.col("m")).alias("perplexity"))


def surrogate_check(docs: DataFrame, big: Model, small: Model, share: float = 0.2, seed: int = 7) -> DataFrame:
    """One row: how the two models' perplexities correlate over a hash sample (values, logarithms and ranks)."""
    from winnow.functions.textops import hash_uniform

    sample = docs.where(hash_uniform("doc_id", seed) < share)
    a = perplexity(sample, big).select("doc_id", F.col("perplexity").alias("a"))
    b = perplexity(sample, small).select("doc_id", F.col("perplexity").alias("b"))
    both = a.join(b, "doc_id")
    # the rank correlation is taken on the sample only; its size is the caller's choice
    ranks = both.select("a", "b", F.rank().over(Window.orderBy("a")).alias("ra"), F.rank().over(Window.orderBy("b")).alias("rb"))
    return ranks.agg(
        F.count(F.lit(1)).alias("docs"),
        F.round(F.corr("a", "b"), 6).alias("pearson"),
        F.round(F.corr(F.log("a"), F.log("b")), 6).alias("pearson_log"),
        F.round(F.corr("ra", "rb"), 6).alias("spearman"),
    )
