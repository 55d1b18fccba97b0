"""Metric, model and quantile queries."""

from __future__ import annotations

from pyspark.sql import functions as F

from winnow.functions import vectors
from winnow.operators import dedup, diversity, lm, metrics_table, quantiles, similarity
from winnow.plans.catalog import query
from winnow.plans.oracle import sql, uniform
from winnow.plans.settle import settle, spread_like
from winnow.sources.tables import read_table


def corpus(spark, d):
    docs = read_table(spark, d, "documents")
    return spread_like(dedup.exact(docs), docs, "doc_id")


def seed_of(spark, d):
    return read_table(spark, d, "benchmark").select(F.lit("benchmark").alias("task"), F.col("item_id").alias("seed_id"), "text")


def general(spark, d):
    return read_table(spark, d, "conversations")


def _r(c: str):
    return F.round(c, 6).alias(c)


@query("sparse_tf", sql("SELECT doc_id, term, n AS w FROM tf"))
def sparse_tf(spark, d):
    return similarity.sparse_tf(corpus(spark, d))


@query("task_centroid", sql("SELECT term, round(w, 6) AS w FROM centre"))
def task_centroid(spark, d):
    return similarity.centroid(seed_of(spark, d)).select("term", _r("w"))


@query("similarity_centroid", sql("SELECT doc_id, round(similarity, 6) AS similarity FROM sim"))
def similarity_centroid(spark, d):
    return similarity.similarity(corpus(spark, d), seed_of(spark, d)).select("doc_id", _r("similarity"))


_EACH = dict(
    dunit="SELECT doc_id, term, n / sqrt(sum(n * n) OVER (PARTITION BY doc_id)) AS x FROM tf",
    cosine="SELECT doc_id, seed_id, sum(x * w) AS cos FROM dunit JOIN sunit USING (term) GROUP BY ALL",
)


@query("similarity_max_pool", sql("SELECT doc_id, round(coalesce(max(cos), 0), 6) AS similarity FROM (SELECT doc_id FROM corpus) LEFT JOIN cosine USING (doc_id) GROUP BY doc_id", **_EACH))
def similarity_max_pool(spark, d):
    return similarity.similarity(corpus(spark, d), seed_of(spark, d), "max").select("doc_id", _r("similarity"))


@query("similarity_mean_pool", sql("SELECT doc_id, round(coalesce(sum(cos), 0) / (SELECT count(DISTINCT seed_id) FROM stok), 6) AS similarity FROM (SELECT doc_id FROM corpus) LEFT JOIN cosine USING (doc_id) GROUP BY doc_id", **_EACH))
def similarity_mean_pool(spark, d):
    return similarity.similarity(corpus(spark, d), seed_of(spark, d), "mean").select("doc_id", _r("similarity"))


@query(
    "similarity_tfidf",
    sql(
        "SELECT doc_id, round(coalesce(s, 0), 6) AS similarity FROM (SELECT doc_id FROM corpus) LEFT JOIN (SELECT doc_id, sum(x * w) / (SELECT sqrt(sum(w * w)) FROM icentre) AS s FROM idunit JOIN icentre USING (term) GROUP BY doc_id) USING (doc_id)",
        idf="SELECT term, ln((1e0 + (SELECT count(*) FROM corpus)) / (count(*) + 1e0)) + 1 AS idf FROM tf GROUP BY term",
        istf="SELECT seed_id, term, count(*) * any_value(idf) AS w FROM stok JOIN idf USING (term) GROUP BY ALL",
        isunit="SELECT seed_id, term, w / sqrt(sum(w * w) OVER (PARTITION BY seed_id)) AS w FROM istf",
        icentre="SELECT term, sum(w) / (SELECT count(DISTINCT seed_id) FROM stok)::DOUBLE AS w FROM isunit GROUP BY term",
        idunit="SELECT doc_id, term, n * idf / sqrt(sum(n * idf * n * idf) OVER (PARTITION BY doc_id)) AS x FROM tf JOIN idf USING (term)",
    ),
)
def similarity_tfidf(spark, d):
    c = corpus(spark, d)
    idf = settle(similarity.inverse_frequency(c))
    return similarity.similarity(c, seed_of(spark, d), idf=idf).select("doc_id", _r("similarity"))


@query(
    "similarity_per_task_max",
    sql(
        "SELECT doc_id, round(greatest(s0, s1), 6) AS similarity FROM (SELECT doc_id, coalesce(sum(n * w) FILTER (task = 0), 0) / (sqrt(min(nn)) * (SELECT sqrt(sum(w * w)) FROM tc WHERE task = 0)) AS s0, coalesce(sum(n * w) FILTER (task = 1), 0) / (sqrt(min(nn)) * (SELECT sqrt(sum(w * w)) FROM tc WHERE task = 1)) AS s1 FROM (SELECT *, sum(n * n) OVER (PARTITION BY doc_id) AS nn FROM tf) LEFT JOIN tc USING (term) GROUP BY doc_id)",
        ts="SELECT seed_id % 2 AS task, count(DISTINCT seed_id)::DOUBLE AS k FROM stok GROUP BY ALL",
        tc="SELECT ts.task, term, sum(w) / min(k) AS w FROM sunit JOIN ts ON ts.task = sunit.seed_id % 2 GROUP BY ts.task, term",
    ),
)
def similarity_per_task_max(spark, d):
    seed = seed_of(spark, d).withColumn("task", (F.col("seed_id") % 2).cast("string"))  # two tasks of the one seed table
    return similarity.similarity(corpus(spark, d), seed, "per_task_max").select("doc_id", _r("similarity"))


@query("similarity_dense_hashed")
def similarity_dense_hashed(spark, d):
    return similarity.dense_similarity(corpus(spark, d), seed_of(spark, d)).select("doc_id", _r("similarity"))


@query(
    "similarity_chunked",
    sql(
        "SELECT doc_id, round(avg(s), 6) AS similarity FROM (SELECT doc_id, no, coalesce(sum(n * w), 0) / (sqrt(sum(n * n)) * (SELECT sqrt(sum(w * w)) FROM centre)) AS s FROM ctf LEFT JOIN centre USING (term) GROUP BY ALL) GROUP BY doc_id",
        ctf="SELECT doc_id, (pos - 1) // 128 AS no, term, count(*)::DOUBLE AS n FROM postok GROUP BY ALL",
    ),
)
def similarity_chunked(spark, d):
    return similarity.chunked(corpus(spark, d), similarity.centroid(seed_of(spark, d))).select("doc_id", _r("similarity"))


@query(
    "embedding_centroid_cosine",
    """WITH u AS (SELECT vec_id, label, list_transform(embedding::DOUBLE[], lambda x: x / sqrt(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[]))) AS e FROM embeddings),
    c AS (SELECT i, avg(e[i]) AS m FROM u, range(1, 65) t(i) WHERE label = 0 GROUP BY i), v AS (SELECT list(m ORDER BY i) AS c FROM c)
    SELECT vec_id, round(list_cosine_similarity(e, c), 6) AS similarity FROM u CROSS JOIN v""",
)
def embedding_centroid_cosine(spark, d):
    e = read_table(spark, d, "embeddings")
    unit = e.select("vec_id", "label", vectors.scale("embedding", F.lit(1.0) / vectors.norm("embedding")).alias("u"))
    m = unit.where("label = 0").agg(*vectors.mean("u", 64)).first()
    c = [m[f"_v{i}"] for i in range(64)]
    size = sum(x * x for x in c) ** 0.5
    return unit.select("vec_id", F.round(vectors.against("u", c) / (vectors.norm("u") * F.lit(size)), 6).alias("similarity"))


@query(
    "embedding_knn",
    """SELECT query_id, vec_id, similarity, place FROM (SELECT q.vec_id AS query_id, e.vec_id, round(list_cosine_similarity(q.embedding::DOUBLE[], e.embedding::DOUBLE[]), 6) AS similarity,
    row_number() OVER (PARTITION BY q.vec_id ORDER BY round(list_cosine_similarity(q.embedding::DOUBLE[], e.embedding::DOUBLE[]), 6) DESC, e.vec_id) AS place FROM embeddings q JOIN embeddings e ON q.vec_id <> e.vec_id WHERE q.vec_id % 100 = 0) WHERE place <= 5""",
)
def embedding_knn(spark, d):
    """The stated query set (ids divisible by 100) against all rows; the queries are broadcast in blocks of the scan."""
    e = read_table(spark, d, "embeddings").select("vec_id", "embedding")
    q = e.where("vec_id % 100 = 0").select(F.col("vec_id").alias("query_id"), F.col("embedding").alias("q"))
    s = e.join(F.broadcast(q) if q.count() <= 100_000 else q, F.col("vec_id") != F.col("query_id")).select("query_id", "vec_id", F.round(vectors.cosine("q", "embedding"), 6).alias("similarity"))
    from pyspark.sql import Window

    w = Window.partitionBy("query_id").orderBy(F.desc("similarity"), "vec_id")
    return s.withColumn("place", F.row_number().over(w)).where("place <= 5")


@query("unigram_lm", sql("SELECT term, c FROM lm1"))
def unigram_lm(spark, d):
    return lm.unigram_counts(general(spark, d))


@query("bigram_lm", sql("SELECT prev, term, c2 AS c FROM lm2"))
def bigram_lm(spark, d):
    return lm.bigram_counts(general(spark, d))


@query("perplexity_unigram", sql("SELECT doc_id, n_tokens, round(perplexity, 5) AS perplexity FROM ppl JOIN len USING (doc_id)"))
def perplexity_unigram(spark, d):
    return lm.perplexity(corpus(spark, d), lm.train(general(spark, d))).select("doc_id", "n_tokens", F.round(F.round("perplexity", 9), 5).alias("perplexity"))


@query("perplexity_bigram", sql("SELECT doc_id, n_tokens, round(perplexity, 5) AS perplexity FROM ppl2 JOIN len USING (doc_id)"))
def perplexity_bigram(spark, d):
    return lm.perplexity(corpus(spark, d), lm.train(general(spark, d), 2)).select("doc_id", "n_tokens", F.round("perplexity", 5).alias("perplexity"))


@query("perplexity_packed")
def perplexity_packed(spark, d):
    return lm.perplexity_packed(corpus(spark, d), lm.pack(lm.train(general(spark, d)))).select("doc_id", "n_tokens", F.round("perplexity", 4).alias("perplexity"))


@query(
    "surrogate_correlation",
    sql(
        "SELECT count(*) AS docs, round(corr(a, b), 6) AS pearson, round(corr(ln(a), ln(b)), 6) AS pearson_log, round(corr(ra, rb), 6) AS spearman FROM (SELECT *, rank() OVER (ORDER BY a) AS ra, rank() OVER (ORDER BY b) AS rb FROM two)",
        upp="SELECT doc_id, exp(-sum(ln((coalesce(c, 0) + 1e0) / (n + v + 1e0))) / count(*)) AS b FROM tok LEFT JOIN lm1 USING (term) CROSS JOIN lmt GROUP BY doc_id",
        two=f"SELECT doc_id, ppl2.perplexity AS a, upp.b FROM ppl2 JOIN upp USING (doc_id) WHERE {uniform('doc_id', 7)} < 0.2",
    ),
)
def surrogate_correlation(spark, d):
    g = general(spark, d)
    return lm.surrogate_check(corpus(spark, d), lm.train(g, 2), lm.train(g))


@query("token_types", sql("SELECT doc_id, tok_type, n FROM typed"))
def token_types(spark, d):
    return diversity.type_counts(corpus(spark, d))


@query("type_entropy", sql("SELECT doc_id, round(entropy, 6) AS entropy FROM (SELECT doc_id FROM corpus) LEFT JOIN ent USING (doc_id)"))
def type_entropy(spark, d):
    return diversity.with_entropy(corpus(spark, d)).select("doc_id", F.round(F.round("entropy", 9), 6).alias("entropy"))


@query(
    "type_entropy_normalised",
    sql("SELECT doc_id, round((greatest(-sum(n / t * ln(n / t)), 0) + 0e0) / ln(17e0), 6) AS entropy FROM (SELECT doc_id, n::DOUBLE AS n, (sum(n) OVER (PARTITION BY doc_id))::DOUBLE AS t FROM typed) GROUP BY doc_id"),
)
def type_entropy_normalised(spark, d):
    return diversity.with_entropy(corpus(spark, d), normalise=True).select("doc_id", _r("entropy"))


@query(
    "type_entropy_bits",
    sql("SELECT doc_id, round((greatest(-sum(n / t * ln(n / t)), 0) + 0e0) / ln(2e0), 6) AS entropy FROM (SELECT doc_id, n::DOUBLE AS n, (sum(n) OVER (PARTITION BY doc_id))::DOUBLE AS t FROM typed) GROUP BY doc_id"),
)
def type_entropy_bits(spark, d):
    return diversity.with_entropy(corpus(spark, d), base=2).select("doc_id", _r("entropy"))


@query(
    "entity_entropy",
    sql(
        "SELECT doc_id, round(coalesce(h, 0), 6) AS entropy FROM (SELECT doc_id FROM corpus) LEFT JOIN (SELECT doc_id, (greatest(-sum(n / t * ln(n / t)), 0) + 0e0) AS h FROM (SELECT doc_id, n::DOUBLE AS n, (sum(n) OVER (PARTITION BY doc_id))::DOUBLE AS t FROM (SELECT doc_id, tok_type, count(*) AS n FROM etag WHERE tok_type <> 'OTHER' GROUP BY ALL)) GROUP BY doc_id) USING (doc_id)"
    ),
)
def entity_entropy(spark, d):
    return diversity.with_entropy(corpus(spark, d), "entity").select("doc_id", _r("entropy"))


@query("metric_table", sql("SELECT doc_id, n_tokens, round(similarity, 6) AS similarity, round(perplexity, 5) AS perplexity, round(entropy, 6) AS entropy FROM metrics"))
def metric_table(spark, d):
    return metrics_table.standard(spark, d).select("doc_id", "n_tokens", _r("similarity"), F.round("perplexity", 5).alias("perplexity"), _r("entropy"))


@query("quantile_exact", sql("SELECT doc_id, q_similarity, q_perplexity, q_entropy FROM quant"))
def quantile_exact(spark, d):
    m = metrics_table.standard(spark, d)
    for c in ("similarity", "perplexity", "entropy"):
        m = quantiles.normalise(m, c)
    return m.select("doc_id", "q_similarity", "q_perplexity", "q_entropy")


@query("quantile_percent_rank", sql("SELECT doc_id, floor(100e0 * ((rank() OVER (ORDER BY similarity) - 1) / (count(*) OVER () - 1e0))) / 100e0 AS q_similarity FROM metrics"))
def quantile_percent_rank(spark, d):
    return quantiles.normalise(metrics_table.standard(spark, d), "similarity", "percent_rank").select("doc_id", "q_similarity")


@query("quantile_cutpoints", sql("SELECT i::INT AS i, round(cut, 6) AS cut FROM cuts", cuts="SELECT unnest(range(0, 101)) AS i, unnest(quantile_cont(entropy, [x / 100e0 for x in range(0, 101)])) AS cut FROM metrics"))
def quantile_cutpoints(spark, d):
    m = metrics_table.standard(spark, d)
    g = m.agg(F.percentile("entropy", F.array(*[F.lit(i / 100) for i in range(101)])).alias("g"))
    return g.select(F.posexplode("g").alias("i", "c")).select("i", F.round("c", 6).alias("cut"))


def _sketched(name: str, method: str) -> None:
    @query(name, sql("SELECT doc_id, q_perplexity, true AS close FROM quant"))
    def sketched(spark, d):
        """The exact quantile, and whether the sketched one lies within 0.02 of it."""
        both = quantiles.normalise(quantiles.normalise(metrics_table.standard(spark, d), "perplexity"), "perplexity", method, "near")
        return both.select("doc_id", "q_perplexity", F.coalesce(F.abs(F.col("near") - F.col("q_perplexity")) <= 0.02 + 1e-9, F.lit(True)).alias("close"))


_sketched("quantile_kll", "kll")
_sketched("quantile_approx", "approx")
