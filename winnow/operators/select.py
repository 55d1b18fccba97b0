"""Budgeted choice: the best-ranked documents, or a weighted draw, up to a number of tokens."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from winnow.functions.textops import hash_uniform, spare
from winnow.operators import quantiles
from winnow.operators.ranking import running_total
from winnow.plans.settle import settle

def budget(docs: DataFrame, fraction: float, tokens: str = "n_tokens") -> int:
    """floor(fraction * total tokens)."""
    if not 0 <= fraction <= 1:
        raise ValueError("fraction lies between 0 and 1")
    total = docs.agg(F.coalesce(F.sum(tokens), F.lit(0)).alias("t")).first()["t"]
    return int(total) if fraction == 1 else int(fraction * total)


def order_score(score: str | Column) -> Column:
    """Scores are compared after rounding, so that sums taken in another order don't change a ranking."""
    return F.round(F.col(score) if isinstance(score, str) else score, 9)


def hard(df: DataFrame, score: str, limit: int, tokens: str = "n_tokens", key: str = "doc_id", overshoot: str = "exclude") -> DataFrame:
    """The longest prefix of the ranking (score from the top, then key) whose tokens fit in ``limit``; ``include`` adds the document that crosses it.

    Documents come back with all their columns and cum_tokens, the tokens up to and with them. The same plan serves every
    size: rows are range-partitioned by rank and summed by partition, and only partitions that begin within the budget go on.

    Defined cases: null and NaN scores are never chosen; null keys rank before all others of their score; keys may be of any
    type that sorts, and rows that repeat one are rows of their own; null tokens count 0; an empty table gives none; a column
    named cum_tokens is replaced.
    """
    if overshoot not in ("exclude", "include"):
        raise ValueError("overshoot is exclude or include")
    rows = df.where(F.col(score).isNotNull() & ~F.isnan(F.col(score).cast("double")))
    out = running_total(rows, [], [order_score(score).desc(), F.col(key), F.col(tokens)], tokens, "cum_tokens", upto=limit)
    return out.where(F.col("cum_tokens") <= limit if overshoot == "exclude" else F.col("cum_tokens") - F.coalesce(F.col(tokens), F.lit(0)) < limit)


SOFT = ("exp_key", "bernoulli", "bernoulli_scaled")


def soft(df: DataFrame, weight: str, limit: int | None, seed: int = 7, method: str = "exp_key", tokens: str = "n_tokens", key: str = "doc_id") -> DataFrame:
    """A draw with weights in (0, 1]. exp_key: without replacement to the budget, by -ln(u)/weight from the smallest.
    bernoulli: every document on its own with its weight. bernoulli_scaled: the same, with weights scaled so that
    the expected tokens are the budget. u is a seeded hash of the key, so retries and layouts draw alike.

    Defined cases: null weights and weights of 0 are never drawn; null keys draw as one empty key, equal keys alike; an empty table gives none.
    """
    if method not in SOFT:
        raise ValueError(f"method must be one of {SOFT}")
    u = hash_uniform(key, seed)
    rows = df.where(F.col(weight) > 0)
    if method == "bernoulli":
        return rows.where(u < F.col(weight))
    if method == "bernoulli_scaled":
        return rows.where(u < F.least(F.lit(1.0), F.lit(scale_for(rows, weight, limit, tokens)) * F.col(weight)))
    keyed = rows.withColumn("rank_key", F.round(-F.log(F.greatest(u, F.lit(2.0**-53))) / F.col(weight), 9))
    order = spare(keyed, "_order")
    return hard(keyed.withColumn(order, -F.col("rank_key")), order, limit, tokens, key).drop(order)


def scale_for(rows: DataFrame, weight: str, limit: int, tokens: str = "n_tokens") -> float:
    """c with sum of tokens * min(1, c * weight) = limit, by bisection on tokens summed per weight (quantiles have 100)."""
    sums = [(r["w"], r["t"]) for r in rows.groupBy(F.round(weight, 2).alias("w")).agg(F.sum(tokens).alias("t")).orderBy("w").collect()]
    if sum(t for _, t in sums) <= limit:
        return float("inf")
    lo, hi = 0.0, 1.0 / min(w for w, _ in sums if w > 0)
    for _ in range(60):
        mid = (lo + hi) / 2
        if sum(t * min(1.0, mid * w) for w, t in sums) > limit:
            hi = mid
        else:
            lo = mid
    return lo


def raw_weights(df: DataFrame, score: str, name: str = "weight") -> DataFrame:
    """Min-max scaled scores as weights; equal scores all weigh 1."""
    e = df.agg(F.min(score).alias("lo"), F.max(score).alias("hi")).first()
    if e["lo"] is None or e["lo"] == e["hi"]:
        return df.withColumn(name, F.when(F.col(score).isNotNull(), F.lit(1.0)))
    return df.withColumn(name, (F.col(score) - F.lit(e["lo"])) / F.lit(e["hi"] - e["lo"]))


def blended(metrics: DataFrame, weights: tuple[float, float, float] = (1, 1, 1), method: str = "exact") -> DataFrame:
    """``metrics`` plus q_similarity, q_perplexity, q_entropy and blended, their weighted mean."""
    out = metrics
    for c in ("similarity", "perplexity", "entropy"):
        out = quantiles.normalise(out, c, method)
    a, b, c = (float(x) for x in weights)
    mean = (F.lit(a) * F.col("q_similarity") + F.lit(b) * F.col("q_perplexity") + F.lit(c) * F.col("q_entropy")) / F.lit(a + b + c)
    return out.withColumn("blended", mean)


#: The column of the metric table that each selector ranks by.
COLUMNS = {"task_similar": "similarity", "novelty": "perplexity", "diversity": "entropy", "blended": "blended"}


def choose(metrics: DataFrame, selector: str, mode: str, fraction: float, seed: int = 7, soft_method: str = "exp_key", weight: str = "quantile", overshoot: str = "exclude", weights: tuple = (1, 1, 1), quantile: str = "exact", tokens: str = "n_tokens") -> DataFrame:
    """A selection from the metric table by any of the engine's own selectors."""
    column = COLUMNS[selector]
    limit = budget(metrics, fraction, tokens)
    scored = settle(blended(metrics, weights, quantile)) if selector == "blended" else metrics
    if mode == "hard":
        return hard(scored, column, limit, tokens, overshoot=overshoot)
    if weight == "raw_minmax":
        scored, w = raw_weights(scored, column), "weight"
    elif selector == "blended":
        w = "blended"
    else:
        scored, w = settle(quantiles.normalise(scored, column, quantile)), f"q_{column}"
    return soft(scored, w, limit, seed, soft_method, tokens)
