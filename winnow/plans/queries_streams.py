"""Streaming queries: every stream is drained over what its folder holds."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from winnow.plans.catalog import query
from winnow.plans.oracle import sql, uniform
from winnow.plans.settle import checkpoint_dir
from winnow.sources.tables import SCHEMAS, read_table
from winnow.streaming import refresh

THRESHOLD = 2.0


def _docs(spark, d):
    return refresh.arrivals(refresh.file_stream(spark, f"{d}/documents.parquet", SCHEMAS["documents"]))


def _events(spark, d):
    return refresh.event_time(refresh.file_stream(spark, f"{d}/events.parquet", SCHEMAS["events"]))


@query("stream_admit_hard", sql(f"SELECT doc_id, round(e, 6) AS entropy FROM (SELECT doc_id, ent.entropy AS e FROM documents d JOIN corpus c ON c.text = d.text JOIN (SELECT doc_id AS k, entropy FROM ent) ent ON ent.k = c.doc_id WHERE ent.entropy >= {THRESHOLD})".replace("SELECT doc_id, ent.entropy AS e FROM documents d", "SELECT d.doc_id, ent.entropy AS e FROM documents d")))
def stream_admit_hard(spark, d):
    out = refresh.drain(refresh.admit_hard(_docs(spark, d), THRESHOLD).select("doc_id", "entropy"))
    return out.select("doc_id", F.round("entropy", 6).alias("entropy"))


#: Entropy of every arriving document: a copy has that of the text's first row.
_ARRIVING = "SELECT d.doc_id, m.n_tokens, m.similarity, m.perplexity, m.entropy FROM documents d JOIN corpus c ON c.text = d.text JOIN metrics m ON m.doc_id = c.doc_id"


@query(
    "stream_admit_soft",
    sql(
        f"SELECT doc_id, n_tokens FROM (SELECT a.doc_id, a.n_tokens, (SELECT count(*) FROM cuts WHERE i > 0 AND cut <= a.entropy) / 100e0 AS q FROM arriving a WHERE a.entropy IS NOT NULL) WHERE {uniform('doc_id', 7)} < least(1e0, 0.2e0 * q)",
        arriving=_ARRIVING,
        cuts="SELECT unnest(range(0, 101)) AS i, unnest(quantile_cont(entropy, [x / 100e0 for x in range(0, 101)])) AS cut FROM arriving",
    ),
)
def stream_admit_soft(spark, d):
    cuts = refresh.frozen_grid(read_table(spark, d, "documents"), "percentile")
    return refresh.drain(refresh.admit_soft(_docs(spark, d), cuts, 0.2).select("doc_id", "n_tokens"))


def _frozen(spark, d):
    from winnow.operators import lm, metrics_table, similarity
    from winnow.plans.queries_scores import general, seed_of

    return refresh.freeze(lm.train(general(spark, d)), similarity.centroid(seed_of(spark, d)), metrics_table.standard(spark, d))


def _register(selector: str, threshold: float) -> None:
    column = refresh.SCORES[selector]

    @query(f"stream_admit_{column}", sql(f"SELECT doc_id FROM arriving WHERE {column} >= {threshold}", arriving=_ARRIVING))
    def admitted(spark, d):
        """The frozen cut of a selector other than entropy on arriving documents, each scored without state."""
        return refresh.drain(refresh.admit(_docs(spark, d), _frozen(spark, d), selector, threshold).select("doc_id"))


_register("task_similar", 0.4)
_register("novelty", 6000.0)


@query("stream_admit_blended")
def stream_admit_blended(spark, d):
    return refresh.drain(refresh.admit(_docs(spark, d), _frozen(spark, d), "blended", 0.6).select("doc_id"))


@query("stream_admit_drawn")
def stream_admit_drawn(spark, d):
    """Coin flips by the blended score."""
    return refresh.drain(refresh.admit_drawn(_docs(spark, d), _frozen(spark, d), "blended", 0.2).select("doc_id"))


@query("stream_dedup", "SELECT count(DISTINCT text) AS docs FROM documents")
def stream_dedup(spark, d):
    """With a horizon beyond all arrivals, what stays is one row per text."""
    return refresh.drain(refresh.dedup_within(_docs(spark, d), "10000 days").select("doc_id")).agg(F.count(F.lit(1)).alias("docs"))


@query("stream_token_rate", r"SELECT TIMESTAMP '2024-01-01' + INTERVAL 1 HOUR * (doc_id // 60) AS start, count(*) AS docs, sum(len(regexp_extract_all(lower(text), '[\p{L}\p{N}]+')))::BIGINT AS tokens FROM documents GROUP BY 1")
def stream_token_rate(spark, d):
    return refresh.drain(refresh.token_rate(_docs(spark, d)), "complete").select(F.col("start").cast("timestamp_ntz").alias("start"), "docs", "tokens")


@query("stream_tumbling", "SELECT time_bucket(INTERVAL 1 DAY, ts) AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
def stream_tumbling(spark, d):
    return refresh.drain(refresh.tumbling(_events(spark, d)), "complete").select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n")


@query("stream_sliding", "SELECT start, count(*) AS n FROM (SELECT time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 6 HOUR * k AS start FROM events CROSS JOIN (SELECT unnest(range(0, 4)) AS k)) GROUP BY start")
def stream_sliding(spark, d):
    return refresh.drain(refresh.sliding(_events(spark, d)), "complete").select(F.col("start").cast("timestamp_ntz").alias("start"), "n")


@query(
    "stream_session",
    "WITH g AS (SELECT user_id, ts, sum(CASE WHEN before IS NULL OR ts >= before + INTERVAL 30 MINUTE THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM (SELECT user_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS before FROM events))"
    " SELECT user_id, min(ts) AS start, count(*) AS n FROM g GROUP BY user_id, k HAVING max(ts) + INTERVAL 30 MINUTE <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR",
)
def stream_session(spark, d):
    return refresh.drain(refresh.sessions(_events(spark, d)), "append").select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), "n")


@query("stream_interval_join", "SELECT v.event_id AS view_id, p.event_id AS purchase_id FROM events v JOIN events p ON v.user_id = p.user_id AND v.event_type = 'view' AND p.event_type = 'purchase' AND p.ts >= v.ts AND p.ts <= v.ts + INTERVAL 1 HOUR")
def stream_interval_join(spark, d):
    return refresh.drain(refresh.views_to_purchases(_events(spark, d)))


@query("stream_budget")
def stream_budget(spark, d):
    return refresh.drain(refresh.budgeted(_docs(spark, d), 100_000)).select(F.col("period").cast("timestamp_ntz").alias("period"), "doc_id", "n_tokens")


@query("stream_grid_drift")
def stream_grid_drift(spark, d):
    folder = f"{checkpoint_dir(spark)}/drift-{uuid.uuid4().hex}"
    return refresh.drifting_grid(spark, _docs(spark, d), folder)().select("batch", F.round("drift", 6).alias("drift"))


@query("stream_static_join", "SELECT e.event_id, n.n_name FROM events e JOIN nation n ON n.n_nationkey = e.user_id % 25")
def stream_static_join(spark, d):
    n = read_table(spark, d, "nation").select("n_nationkey", "n_name")
    j = _events(spark, d).join(F.broadcast(n), F.pmod("user_id", F.lit(25)) == F.col("n_nationkey"))  # 25 nations
    return refresh.drain(j.select("event_id", "n_name"))


@query("stream_restart", "SELECT doc_id FROM documents")
def stream_restart(spark, d):
    """Two runs with one checkpoint add every document once."""
    folder = f"{checkpoint_dir(spark)}/restart-{uuid.uuid4().hex}"
    for _ in range(2):
        refresh.to_parquet(_docs(spark, d).select("doc_id"), f"{folder}/out", f"{folder}/checkpoint")
    return spark.read.schema("doc_id long").parquet(f"{folder}/out")


@query("source_replay", "SELECT doc_id, md5(text) AS text_md5, n_chars FROM documents")
def source_replay(spark, d):
    from winnow.sources import replay

    replay.register(spark)
    return spark.read.format("document_replay").option("path", f"{d}/documents.parquet").load().select("doc_id", F.md5(F.col("text").cast("binary")).alias("text_md5"), "n_chars")
