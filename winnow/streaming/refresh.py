"""Refreshing a selection as documents arrive, and event-time operators.

Every function maps a streaming (or batch) DataFrame to one; ``drain`` runs a stream over what is there.
"""

from __future__ import annotations

import math
import uuid
from collections import Counter
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from winnow.functions.textops import hash_uniform, n_tokens, once, words
from winnow.operators import diversity, lm, quantiles
from winnow.plans.settle import checkpoint_dir, settle


def file_stream(spark: SparkSession, path: str, schema: str, per_trigger: int = 4) -> DataFrame:
    """New files of a table, which may be a folder or one file: as a pattern, both are listed alike."""
    folder, _, name = path.rpartition("/")
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(f"{folder}/[{name[0]}]{name[1:]}")


def arrivals(docs: DataFrame) -> DataFrame:
    """Documents with an arrival time a minute apart per id."""
    return docs.withColumn("arrival", F.timestamp_seconds(F.lit(1_704_067_200) + F.col("doc_id") * 60))


def event_time(events: DataFrame) -> DataFrame:
    """Zone-free times become timestamps, which watermarks need."""
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def scored(docs: DataFrame) -> DataFrame:
    """Type entropy and tokens, without state."""
    return once(diversity.with_entropy(docs), n_tokens=n_tokens("text")).withColumn("entropy", F.round("entropy", 9))


def admit_hard(docs: DataFrame, threshold: float) -> DataFrame:
    """The frozen cut of a batch selection by type entropy, as a filter."""
    return scored(docs).where(F.col("entropy") >= threshold)


def admit_soft(docs: DataFrame, cuts: list[float], scale: float, seed: int = 7) -> DataFrame:
    """Seeded coin flips against a frozen quantile grid of entropy: what a batch draw with the same grid would take."""
    q = quantiles.from_grid("entropy", cuts)
    return scored(docs).where(hash_uniform("doc_id", seed) < F.least(F.lit(1.0), F.lit(scale) * q))


#: Terms of a model and a centroid that may be frozen into a stream; a larger model is scored through lm.pack.
FROZEN_TERMS = 2_000_000
SCORES = {"task_similar": "similarity", "novelty": "perplexity", "diversity": "entropy", "blended": "blended"}


@dataclass(frozen=True)
class Frozen:
    """What a batch run fixes for the stream: ln p of known terms and of unknown ones, centroid weights and norm, and a grid of each score."""

    log_p: dict[str, float]
    unknown: float
    weights: dict[str, float]
    norm: float
    grids: dict[str, list[float]]


def freeze(model: lm.Model, centre: DataFrame, metrics: DataFrame) -> Frozen:
    """From a trained model, a centroid (term, w) and the metric table of the batch. Raises where the terms are too many to go to every task."""
    centre = settle(centre)
    if model.order != 1 or model.vocabulary > FROZEN_TERMS or centre.count() > FROZEN_TERMS:
        raise ValueError(f"only unigram models and centroids of at most {FROZEN_TERMS} terms can be frozen")
    p = model.unigrams.select("term", F.log(model.p1(F.col("c"))).alias("lp"))
    weights = {r["term"]: r["w"] for r in centre.toLocalIterator()}
    grids = {c: quantiles.grid(metrics.where(F.col(c).isNotNull()), c, "percentile") for c in ("similarity", "perplexity", "entropy")}
    unknown = math.log(model.alpha / (model.total + model.alpha * (model.vocabulary + 1)))
    return Frozen({r["term"]: r["lp"] for r in p.toLocalIterator()}, unknown, weights, math.sqrt(math.fsum(w * w for w in weights.values())), grids)


def scored_by(docs: DataFrame, frozen: Frozen) -> DataFrame:
    """``docs`` plus n_tokens, similarity, perplexity, entropy and blended, row by row and without state, as the batch would score them.

    Similarity and perplexity come from one Arrow pass over the words with the frozen tables.
    """
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast((frozen.log_p, frozen.unknown, frozen.weights, frozen.norm))

    @F.pandas_udf("similarity double, perplexity double")
    def both(lists: pd.Series) -> pd.DataFrame:
        log_p, unknown, weights, norm = shared.value
        sim, ppl = [], []
        for found in lists:
            n = Counter(found)
            size = math.sqrt(sum(k * k for k in n.values()))
            sim.append(math.fsum(k * weights[t] for t, k in n.items() if t in weights) / (size * norm) if size and norm else 0.0)
            ppl.append(math.exp(-math.fsum(k * log_p.get(t, unknown) for t, k in n.items()) / len(found)) if len(found) else None)
        return pd.DataFrame({"similarity": sim, "perplexity": pd.Series(ppl, dtype=float)})

    rows = once(scored(docs), _both=both(words("text")))
    out = rows.withColumns({c: F.round(F.col(f"_both.{c}"), 9) for c in ("similarity", "perplexity")}).drop("_both")
    q = [F.when(F.col(c).isNotNull(), quantiles.from_grid(c, frozen.grids[c])) for c in ("similarity", "perplexity", "entropy")]
    return out.withColumn("blended", (q[0] + q[1] + q[2]) / F.lit(3.0))


def admit(docs: DataFrame, frozen: Frozen, selector: str, threshold: float) -> DataFrame:
    """The frozen cut of any selector, as a filter: rows whose score reaches the threshold. Null scores are never admitted."""
    return scored_by(docs, frozen).where(F.col(SCORES[selector]) >= threshold)


def admit_drawn(docs: DataFrame, frozen: Frozen, selector: str, scale: float, seed: int = 7) -> DataFrame:
    """Seeded coin flips, a document's chance being ``scale`` times its frozen quantile under any selector."""
    column = SCORES[selector]
    weight = F.col("blended") if column == "blended" else F.when(F.col(column).isNotNull(), quantiles.from_grid(column, frozen.grids[column]))
    return scored_by(docs, frozen).where(hash_uniform("doc_id", seed) < F.least(F.lit(1.0), F.lit(scale) * weight))


def dedup_within(docs: DataFrame, horizon: str = "2 days") -> DataFrame:
    """Exact copies that arrive within the horizon of the first are dropped; state is a digest."""
    return docs.withWatermark("arrival", horizon).withColumn("digest", F.sha2(F.col("text").cast("binary"), 256)).dropDuplicatesWithinWatermark(["digest"])


def token_rate(docs: DataFrame, every: str = "1 hour", late: str = "1 hour") -> DataFrame:
    w = docs.withWatermark("arrival", late).groupBy(F.window("arrival", every).alias("w"))
    return w.agg(F.count(F.lit(1)).alias("docs"), F.sum(n_tokens("text")).alias("tokens")).select(F.col("w.start").alias("start"), "docs", "tokens")


def tumbling(events: DataFrame, every: str = "1 day", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", every).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame, length: str = "1 day", step: str = "6 hours", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", length, step).alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("s")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("s.start").alias("start"), "n")


def views_to_purchases(events: DataFrame, within: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """Interval join of two streams: a view and a purchase of the user at most ``within`` later."""
    v = events.where("event_type = 'view'").select(F.col("event_id").alias("view_id"), F.col("user_id").alias("view_user"), F.col("ts").alias("view_ts")).withWatermark("view_ts", late)
    p = events.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "user_id", "ts").withWatermark("ts", late)
    return v.join(p, F.expr(f"view_user = user_id AND ts >= view_ts AND ts <= view_ts + INTERVAL {within}")).select("view_id", "purchase_id")


def budgeted(docs: DataFrame, tokens_per_period: int, period: str = "day", late: str = "1 hour") -> DataFrame:
    """Admits documents of each period in order of arrival, each one that still fits, until the period's tokens are spent.

    The whole budget is one counter per period, so any document up to the budget can be admitted; a period's rows are ids and
    lengths, never texts. The counter is dropped when the watermark passes the period's end, and later rows of it are too late.
    Rows of one batch are ordered by arrival, then id. Null texts have no tokens and always fit.
    """
    end = {"hour": 3600, "day": 86400}[period]

    def go(key, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        spent = state.get[0] if state.exists else 0
        rows = pd.concat(list(batches)).sort_values(["arrival", "doc_id"])
        keep = []
        for n in rows["n_tokens"]:
            ok = spent + int(n) <= tokens_per_period
            spent += int(n) if ok else 0
            keep.append(ok)
        state.update((spent,))
        state.setTimeoutTimestamp(max(int(key[0].timestamp() + end) * 1000, state.getCurrentWatermarkMs() + 1))
        yield rows.loc[keep, ["doc_id", "n_tokens"]].assign(period=key[0])[["period", "doc_id", "n_tokens"]]

    rows = docs.withWatermark("arrival", late).select("doc_id", "arrival", n_tokens("text").alias("n_tokens"), F.date_trunc(period, "arrival").alias("period"))
    return rows.groupBy("period").applyInPandasWithState(go, "period timestamp, doc_id long, n_tokens long", "spent long", "append", "EventTimeTimeout")


def drifting_grid(spark: SparkSession, docs: DataFrame, folder: str) -> Callable[[], DataFrame]:
    """Runs the stream through foreachBatch: a batch's KLL sketch of entropy joins the one merged sketch of all before it, and the merged grid is stored.

    Each step reads one earlier row and writes one; a batch done again overwrites itself. Returns a function that reads (batch, drift).
    """
    shares = F.array(*[F.lit(i / 100) for i in range(101)])
    schema = "k binary, grid array<double>"

    def step(batch: DataFrame, no: int) -> None:
        own = batch.agg(F.kll_sketch_agg_double("entropy").alias("k")).where("k IS NOT NULL")
        every = own if no == 0 else own.unionByName(batch.sparkSession.read.schema(schema).parquet(f"{folder}/grids/batch={no - 1}").select("k"))
        merged = every.agg(F.kll_merge_agg_double("k").alias("k"))
        merged.select("k", F.kll_sketch_get_quantile_double("k", shares).alias("grid")).write.mode("overwrite").parquet(f"{folder}/grids/batch={no}")

    q = scored(docs).select("doc_id", "entropy").writeStream.foreachBatch(step).option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).start()
    q.awaitTermination()

    def read() -> DataFrame:
        from pyspark.sql import Window

        g = spark.read.schema("grid array<double>, batch int").parquet(f"{folder}/grids")
        before = F.lag("grid").over(Window.orderBy("batch"))
        shift = F.array_max(F.zip_with("grid", before, lambda x, y: F.abs(x - y)))
        return g.select("batch", F.coalesce(shift, F.lit(0.0)).alias("drift"))

    return read


def drain(stream: DataFrame, mode: str = "append", name: str | None = None) -> DataFrame:
    """Runs a stream over all available input into Parquet files in the shared checkpoint folder and returns what is there.

    In complete mode every batch writes the whole result and the last one is read. A batch done again overwrites itself.
    """
    spark = stream.sparkSession
    folder = f"{checkpoint_dir(spark)}/{name or f'drained-{uuid.uuid4().hex}'}"
    done: list[int] = []

    def put(batch: DataFrame, no: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/out/batch={no}")
        done.append(no)

    q = stream.writeStream.foreachBatch(put).outputMode(mode).option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).start()
    q.awaitTermination()
    if not done:
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(f"{folder}/out" if mode == "append" else f"{folder}/out/batch={done[-1]}").select(*stream.columns)


def to_parquet(stream: DataFrame, path: str, checkpoint: str) -> None:
    """Appends all available input to a Parquet sink; a restart with the same checkpoint adds only what is new."""
    q = stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()


def frozen_grid(docs: DataFrame, method: str = "approx") -> list[float]:
    """101 cut points of entropy from a batch, to be frozen into a stream."""
    return quantiles.grid(settle(scored(docs).select("entropy")).where("entropy IS NOT NULL"), "entropy", method)
