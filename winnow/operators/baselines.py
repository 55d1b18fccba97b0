"""Selections to compare with: none, all, random, task text, importance resampling, a representative subset.

Defined cases: all rest on ``select.hard``, so null keys, repeated keys, ties and empty tables are chosen from as stated there;
null keys draw alike; documents without words have no density ratio and no likelihood gap and are not drawn by these two, but count in the
budget; other columns come back untouched where the whole row is returned.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from winnow.functions.textops import hash_uniform, once, spare, words
from winnow.operators import lm, quantiles, select
from winnow.operators.ranking import running_total
from winnow.plans.settle import settle

BUCKETS = 10_000

#: Selector, metrics, and whether it uses domain text, task text and task labels.
REQUIREMENTS = (
    ("base_only", (), False, False, False),
    ("full_domain", (), True, False, False),
    ("uniform_budget", (), True, False, False),
    ("task_only", (), False, True, False),
    ("task_similar", ("similarity",), True, True, False),
    ("novelty", ("perplexity",), True, False, False),
    ("diversity", ("entropy",), True, False, False),
    ("blended", ("similarity", "perplexity", "entropy"), True, True, False),
    ("importance_resample", ("density_ratio",), True, True, False),
    ("representative_subset", ("likelihood_gap",), True, False, False),
    ("supervised_tuning", (), False, True, True),
    ("domain_from_scratch", (), True, False, False),
)


def requirements(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(
        [(s, list(m), d, t, y) for s, m, d, t, y in REQUIREMENTS],
        "selector string, metrics array<string>, uses_domain_text boolean, uses_task_text boolean, uses_task_labels boolean",
    )


def check_inputs(selector: str, seed: DataFrame | None) -> None:
    """A selector that uses task text needs a seed, and one that doesn't refuses it."""
    needs = {s: t for s, _, _, t, _ in REQUIREMENTS}[selector]
    if needs and seed is None:
        raise ValueError(f"{selector} needs a seed")
    if not needs and seed is not None:
        raise ValueError(f"{selector} takes no seed")


def base_only(docs: DataFrame) -> DataFrame:
    return docs.where(F.lit(False))


def full_domain(docs: DataFrame) -> DataFrame:
    return docs


def uniform_budget(docs: DataFrame, fraction: float, seed: int = 7, tokens: str = "n_tokens") -> DataFrame:
    """Random documents to the token budget: the same draw with equal weights."""
    order = spare(docs, "_order")
    return select.hard(docs.withColumn(order, -hash_uniform("doc_id", seed)), order, select.budget(docs, fraction, tokens), tokens).drop(order)


def task_only(seed: DataFrame) -> DataFrame:
    return seed


def domain_from_scratch(docs: DataFrame) -> lm.Model:
    return lm.train(docs)


def gram_buckets(texts: DataFrame, key: str, buckets: int = BUCKETS, text: str = "text") -> DataFrame:
    """(key, bucket): one row per unigram and bigram of a text, as a hash bucket."""
    w = once(texts.select(key, text), _w=words(text))
    shorter = F.greatest(F.size("_w") - 1, F.lit(0))
    bi = F.zip_with(F.slice("_w", F.lit(1), shorter), F.slice("_w", F.lit(2), shorter), lambda a, b: F.concat(a, F.lit(" "), b))
    bucket = F.pmod(F.conv(F.substring(F.md5(F.col("g").cast("binary")), 1, 8), 16, 10).cast("long"), F.lit(buckets)).cast("int")
    return w.select(key, F.explode(F.concat("_w", bi)).alias("g")).select(key, bucket.alias("bucket"))


def importance_weights(docs: DataFrame, seed: DataFrame, buckets: int = BUCKETS, seed_key: str = "seed_id") -> DataFrame:
    """(doc_id, log_weight): sum over grams of ln(share in the seed / share in the corpus), add-one smoothed buckets.

    Grams are exploded twice, once to count buckets and once to sum gains, so that only bucket counts and one
    row per document are shuffled. The bucket table has a fixed number of rows and is always broadcast.
    """
    d = gram_buckets(docs, "doc_id", buckets)
    c = d.groupBy("bucket").agg(F.count(F.lit(1)).alias("cn"))
    s = gram_buckets(seed, seed_key, buckets).groupBy("bucket").agg(F.count(F.lit(1)).alias("sn"))
    both = docs.sparkSession.range(buckets).select(F.col("id").cast("int").alias("bucket")).join(c, "bucket", "left").join(s, "bucket", "left").na.fill(0)
    both = settle(both)
    t = both.agg(F.sum("cn").alias("c"), F.sum("sn").alias("s")).first()
    gain = F.log((F.col("sn") + 1) / F.lit(float(t["s"] + buckets))) - F.log((F.col("cn") + 1) / F.lit(float(t["c"] + buckets)))
    return d.join(F.broadcast(both.select("bucket", gain.alias("gain"))), "bucket").groupBy("doc_id").agg(F.sum("gain").alias("log_weight"))


def perturbed(weights: DataFrame, seed_no: int = 7) -> DataFrame:
    """``weights`` plus perturbed, the log weight with Gumbel noise."""
    u = F.greatest(hash_uniform("doc_id", seed_no), F.lit(2.0**-53))
    return weights.withColumn("perturbed", F.round(F.col("log_weight") - F.log(-F.log(u)), 9))


def importance_resample(docs: DataFrame, seed: DataFrame, fraction: float, buckets: int = BUCKETS, seed_no: int = 7, tokens: str = "n_tokens") -> DataFrame:
    """Gumbel noise on the log weights and the top of that ranking to the budget: a weighted draw without replacement.

    ``docs`` has doc_id, text and the token count.
    """
    w = perturbed(importance_weights(docs, seed, buckets), seed_no)
    rows = docs.select("doc_id", tokens).join(w, "doc_id")
    return select.hard(rows, "perturbed", select.budget(docs, fraction, tokens), tokens)


def likelihood_gap(docs: DataFrame, a: lm.Model, b: lm.Model) -> DataFrame:
    """(doc_id, n_tokens, gap): mean ln p per word under a less that under b."""
    x = lm.log_likelihood(docs, a).select("doc_id", "n_tokens", (F.col("ll") / F.col("n_tokens")).alias("x"))
    y = lm.log_likelihood(docs, b).select("doc_id", (F.col("ll") / F.col("n_tokens")).alias("y"))
    return x.join(y, "doc_id").select("doc_id", "n_tokens", F.round(F.col("x") - F.col("y"), 9).alias("gap"))


def gap_of_orders(docs: DataFrame, model: lm.Model) -> DataFrame:
    """``likelihood_gap`` between a bigram model's unigrams and the whole model, from one pass over the texts."""
    both = lm.both_likelihoods(docs, model)
    return both.select("doc_id", "n_tokens", F.round(F.col("ll1") / F.col("n_tokens") - F.col("ll2") / F.col("n_tokens"), 9).alias("gap"))


def representative_subset(docs: DataFrame, a: lm.Model, b: lm.Model, fraction: float, strata: int = 100, seed: int = 7) -> DataFrame:
    """Quantile strata of the gap, each filled in hash order to its share of the budget, so the subset keeps the gap's distribution.

    Running sums are taken on range-partitioned rows, so a stratum that ties make large is no single task.
    """
    return by_strata(settle(likelihood_gap(docs, a, b)), fraction, strata, seed)


def by_strata(gaps: DataFrame, fraction: float, strata: int = 100, seed: int = 7) -> DataFrame:
    """``representative_subset`` of settled rows (doc_id, n_tokens, gap)."""
    q = quantiles.normalise(gaps, "gap", "exact").withColumn("stratum", F.ceil(F.col("q_gap") * strata).cast("int"))
    share = q.groupBy("stratum").agg(F.sum("n_tokens").alias("_t"))
    placed = q.withColumn("_u", hash_uniform("doc_id", seed))
    filled = running_total(placed, ["stratum"], ["_u", "doc_id"], "n_tokens", "cum_tokens")
    filled = filled.join(F.broadcast(share), "stratum")
    return filled.where(F.col("cum_tokens") <= F.floor(F.lit(fraction) * F.col("_t"))).select("doc_id", "n_tokens", "gap", "stratum")
