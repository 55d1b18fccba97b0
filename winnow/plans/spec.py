"""A selection job as a recipe, its routes and its run."""

from __future__ import annotations

from dataclasses import asdict, dataclass

from pyspark.sql import DataFrame, SparkSession

from winnow.operators import dedup, lm, metrics_table, select, similarity
from winnow.operators.analysis import guarded, noise_flags
from winnow.operators.baselines import check_inputs
from winnow.plans.settle import settle
from winnow.sources import tables


@dataclass(frozen=True)
class SelectionSpec:
    """Everything a run needs to know; the defaults are the best reported recipe."""

    selector: str = "task_similar"
    mode: str = "hard"
    fraction: float = 0.10
    tagset: str = "pos"
    quantile: str = "exact"
    weights: tuple[float, float, float] = (1, 1, 1)
    overshoot: str = "exclude"
    soft_method: str = "exp_key"
    weight: str = "quantile"
    seed: int = 7
    near_dedup: bool = False
    noise_guard: bool = False
    min_tokens: int = 0
    gamma: float = 1.0


def choose_route(terms: int, seed_terms: int) -> dict[str, str]:
    """Which physical form the joins take, from counts that are known before they run. Cuts and quantiles have one form at every size."""
    return {
        "model": "broadcast" if terms <= lm.TERMS_BROADCAST else "shuffle or packed",
        "centroid": "broadcast" if seed_terms <= similarity.SEED_BROADCAST else "shuffle",
    }


def run(spark: SparkSession, spec: SelectionSpec, docs: DataFrame, seed: DataFrame | None, general: DataFrame, sink: str | None = None, tokens_per_shard: int = 1_000_000) -> DataFrame:
    """Curated documents -> dedup -> one scoring pass -> choice -> shards and manifest where ``sink`` is given.

    The metric table is materialised after scoring, so texts are read once for scores and once for the sink.
    """
    check_inputs(spec.selector, seed if spec.selector in ("task_similar", "blended") else None)
    corpus = dedup.exact(docs)
    if spec.near_dedup:
        corpus = dedup.drop_near(corpus)
    model = lm.train(general)
    centre = similarity.centroid(seed) if seed is not None else model.unigrams.select("term", (model.unigrams.c * 1.0).alias("w"))
    metrics = settle(metrics_table.score_all(corpus, centre, model, spec.tagset))
    if spec.min_tokens:
        metrics = metrics.where(metrics.n_tokens >= spec.min_tokens)
    candidates = guarded(metrics, noise_flags(corpus)) if spec.noise_guard else metrics
    chosen = settle(select.choose(candidates, spec.selector, spec.mode, spec.fraction, spec.seed, spec.soft_method, spec.weight, spec.overshoot, spec.weights, spec.quantile).select("doc_id", "n_tokens"))
    if sink:
        shards = tables.write_shards(corpus.join(chosen, "doc_id"), f"{sink}/shards", tokens_per_shard, spec.seed)
        tables.write_manifest(spark, f"{sink}/manifest", asdict(spec), shards)
    return chosen
