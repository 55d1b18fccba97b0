"""The metric table: tokens, similarity, perplexity and entropy of every document from one scan of the text."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from winnow.functions.textops import once, sum_of_squared_counts, words
from winnow.operators import diversity, lm, similarity
from winnow.operators.skew import salted_join
from winnow.plans.settle import fits, settle, spread_like


def score_all(docs: DataFrame, centre: DataFrame, model: lm.Model, tagset: str = "pos") -> DataFrame:
    """(doc_id, n_tokens, similarity, perplexity, entropy), rounded to 9 decimals.

    Entropy and the norm come from the row itself; similarity and perplexity share one explode, one join with a
    term table that holds centroid weights and model counts, and one partial aggregation. A document without
    words has similarity 0, no perplexity and no entropy unless it has other pieces.
    """
    terms = settle(model.unigrams.join(centre, "term", "full_outer").select("term", F.col("c").alias("_c"), F.col("w").alias("_wt")))
    size = terms.agg(F.sqrt(F.sum(F.col("_wt") * F.col("_wt"))).alias("norm"), F.count(F.lit(1)).alias("n")).first()
    if not size["norm"]:
        raise ValueError("the seed has no words")
    rows = once(docs.select("doc_id", "text").withColumn("_h", diversity.entropy_column("text", tagset)), _w=words("text"))
    rows = rows.select("doc_id", "_w", "_h", F.sqrt(sum_of_squared_counts(F.col("_w")).cast("double")).alias("_norm"))
    each = rows.select("doc_id", "_h", "_norm", F.explode_outer("_w").alias("term"))
    if size["n"] <= lm.TERMS_BROADCAST and fits(terms):
        met = each.join(F.broadcast(terms), "term", "left")
    else:
        met = salted_join(each, terms, ["term"], max(model.total, 1), model.unigrams.select("term", F.col("c").alias("n")), how="left")
    lp = F.when(F.col("term").isNotNull(), F.log(model.p1(F.col("_c"))))
    agg = met.groupBy("doc_id").agg(
        F.count("term").alias("n_tokens"), F.sum("_wt").alias("_dot"), F.max("_norm").alias("_norm"), lm.exact_sum(lp).alias("_ll"), F.max("_h").alias("entropy")
    )
    cos = F.when(F.col("_norm") > 0, F.coalesce("_dot", F.lit(0.0)) / (F.col("_norm") * F.lit(size["norm"]))).otherwise(F.lit(0.0))
    ppl = F.when(F.col("n_tokens") > 0, F.exp(-F.col("_ll") / F.col("n_tokens")))
    return agg.select("doc_id", "n_tokens", F.round(cos, 9).alias("similarity"), F.round(ppl, 9).alias("perplexity"), F.round("entropy", 9).alias("entropy"))


def standard(spark, folder: str, docs: DataFrame | None = None) -> DataFrame:
    """The metric table of the given tables: exactly deduplicated documents, benchmark passages as seed, conversations as base text."""
    from winnow.operators.dedup import exact
    from winnow.sources.tables import read_table

    if docs is None:
        table = read_table(spark, folder, "documents")
        docs = spread_like(exact(table), table, "doc_id")
    seed = read_table(spark, folder, "benchmark").select(F.lit("benchmark").alias("task"), F.col("item_id").alias("seed_id"), "text")
    model = lm.train(read_table(spark, folder, "conversations"))
    return settle(score_all(docs, similarity.centroid(seed), model))
