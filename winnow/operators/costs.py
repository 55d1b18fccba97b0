"""Token and compute accounting."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Reported scale. Tokens in billions, days on one instance, parameters in billions.
BASE_TOKENS_B = 300.0
DAYS = {"1B": 3.0, "6.9B": 18.0}
PARAMS_B = {"surrogate": 0.07, "1B": 1.0, "6.9B": 6.9}
#: Reading a token costs about a quarter of training on it.
INFERENCE_SHARE = 0.25


def tokens_used(selected: DataFrame, docs: DataFrame, tokens: str = "n_tokens") -> DataFrame:
    """One row: tokens of the choice and of all, and the share."""
    a = selected.agg(F.coalesce(F.sum(tokens), F.lit(0)).alias("tokens"))
    b = docs.agg(F.coalesce(F.sum(tokens), F.lit(0)).alias("all_tokens"))
    return a.crossJoin(b).withColumn("share", F.coalesce(F.try_divide(F.col("tokens").cast("double"), F.col("all_tokens")), F.lit(0.0)))


def share_of_pretraining(tokens_b: float, base_b: float = BASE_TOKENS_B) -> float:
    return tokens_b / base_b


def estimate(tokens: float, params_b: float, kind: str = "train") -> float:
    """Floating-point operations: 6 per parameter and token to train, a quarter of it to score."""
    work = 6.0 * params_b * 1e9 * tokens
    return work if kind == "train" else INFERENCE_SHARE * work


def throughput(tokens_b: float, days: float) -> float:
    """Tokens a second."""
    return tokens_b * 1e9 / (days * 86400)


def ledger(corpus: DataFrame, base: DataFrame, tokens: str = "n_tokens") -> DataFrame:
    """The costs of training on ``corpus``, whose base model has seen ``base``: one row (item, value) per item.

    Shares are of the base text; a rate is what the reported days on one instance ask for; floating-point operations are of one pass.
    """
    counted = [df.agg(F.coalesce(F.sum(tokens), F.lit(0)).cast("double").alias(n)) for df, n in ((corpus, "c"), (base, "b"))]
    c, b = F.col("c"), F.col("b")

    def flops(size: str, kind: str):
        return F.lit(estimate(1.0, PARAMS_B[size], kind)) * c

    items = [
        ("corpus_share_of_pretraining", F.try_divide(c, b)),
        ("subset_share_of_pretraining", F.try_divide(c * 0.1, b)),
        *[(f"tokens_per_second_{k}", c / F.lit(days * 86400)) for k, days in DAYS.items()],
        ("surrogate_over_full_scoring", F.try_divide(flops("surrogate", "score"), flops("1B", "score"))),
        ("full_scoring_over_training", F.try_divide(flops("1B", "score"), flops("1B", "train"))),
    ]
    rows = F.array(*[F.struct(F.lit(k).alias("item"), F.round(v, 9).alias("value")) for k, v in items])
    return counted[0].crossJoin(counted[1]).select(F.inline(rows))
