"""Selector, baseline and analysis queries."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import functions as F

from winnow.functions.textops import n_tokens
from winnow.operators import analysis, baselines, lm, metrics, metrics_table, select
from winnow.plans.catalog import query
from winnow.plans.experiments import selections_at
from winnow.plans.oracle import hard_body, soft_body, sql, uniform
from winnow.plans.queries_scores import corpus, general, seed_of
from winnow.plans.settle import settle

FRACTION = 0.1
_COLUMN = {"similarity": ("task_similar", "similarity", "metrics"), "perplexity": ("novelty", "perplexity", "metrics"), "entropy": ("diversity", "entropy", "metrics"), "blended": ("blended", "blended", "blend")}


def _ids(df, *more):
    return df.select("doc_id", "n_tokens", *more)


def _register_pair(name: str) -> None:
    selector, column, source = _COLUMN[name]
    weight = "blended" if name == "blended" else f"q_{column}"

    @query(f"hard_{name}", sql(hard_body(column, source)))
    def hard(spark, d):
        return _ids(select.choose(metrics_table.standard(spark, d), selector, "hard", FRACTION), "cum_tokens")

    @query(f"soft_{name}", sql(soft_body(weight, "blend" if name == "blended" else "quant")))
    def soft(spark, d):
        return _ids(select.choose(metrics_table.standard(spark, d), selector, "soft", FRACTION), "cum_tokens")


for _name in _COLUMN:
    _register_pair(_name)


@query("hard_similarity_include", sql(hard_body("similarity", overshoot="include")))
def hard_similarity_include(spark, d):
    return _ids(select.choose(metrics_table.standard(spark, d), "task_similar", "hard", FRACTION, overshoot="include"), "cum_tokens")


@query("soft_bernoulli", sql(f"SELECT doc_id, n_tokens FROM quant WHERE {uniform('doc_id', 7)} < q_similarity"))
def soft_bernoulli(spark, d):
    return _ids(select.choose(metrics_table.standard(spark, d), "task_similar", "soft", FRACTION, soft_method="bernoulli"))


#: The scale solves sum n * min(1, c * w) = budget: weights sorted from the top, the first k are certain, the rest share what is left.
_SCALED = dict(
    lev="SELECT q_similarity AS w, sum(n_tokens)::DOUBLE AS t FROM quant GROUP BY q_similarity",
    cum="SELECT w, coalesce(sum(t) OVER (ORDER BY w DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS sure, sum(t * w) OVER (ORDER BY w ROWS UNBOUNDED PRECEDING) AS rest FROM lev",
    scale="SELECT max((b - sure) / rest) AS c FROM cum CROSS JOIN (SELECT floor(0.1e0 * sum(n_tokens)) AS b FROM metrics) WHERE (b - sure) / rest * w <= 1",
)


@query("soft_bernoulli_scaled", sql(f"SELECT doc_id, n_tokens FROM quant CROSS JOIN scale WHERE {uniform('doc_id', 7)} < least(1, c * q_similarity)", **_SCALED))
def soft_bernoulli_scaled(spark, d):
    return _ids(select.choose(metrics_table.standard(spark, d), "task_similar", "soft", FRACTION, soft_method="bernoulli_scaled"))


@query(
    "soft_raw_weight",
    sql(soft_body("weight", "raw"), raw="SELECT *, (similarity - (SELECT min(similarity) FROM metrics)) / ((SELECT max(similarity) FROM metrics) - (SELECT min(similarity) FROM metrics)) AS weight FROM metrics"),
)
def soft_raw_weight(spark, d):
    return _ids(select.choose(metrics_table.standard(spark, d), "task_similar", "soft", FRACTION, weight="raw_minmax"), "cum_tokens")


@query("blended_scores", sql("SELECT doc_id, round(blended, 6) AS blended FROM blend"))
def blended_scores(spark, d):
    return select.blended(metrics_table.standard(spark, d)).select("doc_id", F.round("blended", 6).alias("blended"))


@query("token_budget", sql("SELECT f AS fraction, floor(f * t)::BIGINT AS tokens FROM (SELECT unnest([0.01e0, 0.05e0, 0.1e0, 0.2e0, 0.5e0]) AS f) CROSS JOIN (SELECT sum(n_tokens)::DOUBLE AS t FROM len)"))
def token_budget(spark, d):
    docs = settle(corpus(spark, d).select("doc_id", n_tokens("text").alias("n_tokens")))
    return spark.createDataFrame([(f, select.budget(docs, f)) for f in (0.01, 0.05, 0.1, 0.2, 0.5)], "fraction double, tokens long")


@query("base_only", sql("SELECT doc_id, n_tokens FROM metrics WHERE false"))
def base_only(spark, d):
    return _ids(baselines.base_only(metrics_table.standard(spark, d)))


@query("full_domain", sql("SELECT doc_id, n_tokens FROM metrics"))
def full_domain(spark, d):
    return _ids(baselines.full_domain(metrics_table.standard(spark, d)))


@query("uniform_budget", sql(hard_body("score", f"(SELECT doc_id, n_tokens, -{uniform('doc_id', 7)} AS score FROM metrics)")))
def uniform_budget(spark, d):
    return _ids(baselines.uniform_budget(metrics_table.standard(spark, d), FRACTION), "cum_tokens")


@query("task_only", sql("SELECT seed_id, count(*) AS n_tokens FROM stok GROUP BY seed_id"))
def task_only(spark, d):
    return baselines.task_only(seed_of(spark, d)).select("seed_id", n_tokens("text").alias("n_tokens"))


_GRAM = dict(
    dgram=r"SELECT doc_id, ('0x' || substr(md5(g), 1, 8))::BIGINT % 10000 AS bucket FROM (SELECT doc_id, term AS g FROM tok UNION ALL SELECT doc_id, prev || ' ' || term FROM (SELECT doc_id, term, lag(term) OVER (PARTITION BY doc_id ORDER BY pos) AS prev FROM postok) WHERE prev IS NOT NULL)",
    spos=r"SELECT item_id, unnest(regexp_extract_all(lower(text), '[\p{L}\p{N}]+')) AS term, generate_subscripts(regexp_extract_all(lower(text), '[\p{L}\p{N}]+'), 1) AS pos FROM benchmark",
    sgram=r"SELECT ('0x' || substr(md5(g), 1, 8))::BIGINT % 10000 AS bucket FROM (SELECT term AS g FROM spos UNION ALL SELECT prev || ' ' || term FROM (SELECT term, lag(term) OVER (PARTITION BY item_id ORDER BY pos) AS prev FROM spos) WHERE prev IS NOT NULL)",
    gain="SELECT b.bucket, ln((coalesce(sn, 0) + 1e0) / ((SELECT count(*) FROM sgram) + 10000e0)) - ln((coalesce(cn, 0) + 1e0) / ((SELECT count(*) FROM dgram) + 10000e0)) AS gain FROM (SELECT unnest(range(0, 10000)) AS bucket) b LEFT JOIN (SELECT bucket, count(*) AS cn FROM dgram GROUP BY bucket) c USING (bucket) LEFT JOIN (SELECT bucket, count(*) AS sn FROM sgram GROUP BY bucket) s USING (bucket)",
    lw="SELECT doc_id, sum(gain) AS log_weight FROM dgram JOIN gain USING (bucket) GROUP BY doc_id",
)


@query("importance_log_weights", sql("SELECT doc_id, round(log_weight, 4) AS log_weight FROM lw", **_GRAM))
def importance_log_weights(spark, d):
    return baselines.importance_weights(corpus(spark, d), seed_of(spark, d)).select("doc_id", F.round("log_weight", 4).alias("log_weight"))


@query(
    "importance_resample",
    sql(hard_body("score", f"(SELECT doc_id, n_tokens, round(log_weight - ln(-ln(greatest({uniform('doc_id', 7)}, pow(2e0, -53)))), 9) AS score FROM lw JOIN len USING (doc_id))"), **_GRAM),
)
def importance_resample(spark, d):
    docs = corpus(spark, d).select("doc_id", "text", n_tokens("text").alias("n_tokens"))
    return _ids(baselines.importance_resample(docs, seed_of(spark, d), FRACTION), "cum_tokens")


@query(
    "representative_subset",
    sql(
        f"SELECT doc_id, n_tokens, stratum FROM (SELECT doc_id, n_tokens, stratum, sum(n_tokens) OVER (PARTITION BY stratum ORDER BY {uniform('doc_id', 7)}, doc_id ROWS UNBOUNDED PRECEDING) AS cum, sum(n_tokens) OVER (PARTITION BY stratum) AS t FROM strat) WHERE cum <= floor(0.1e0 * t)",
        l1="SELECT doc_id, count(*) AS n_tokens, sum(ln((coalesce(c, 0) + 1e0) / (n + v + 1e0))) / count(*) AS x FROM tok LEFT JOIN lm1 USING (term) CROSS JOIN lmt GROUP BY doc_id",
        l2="SELECT doc_id, sum(ln(p)) / count(*) AS y FROM bip GROUP BY doc_id",
        gap="SELECT doc_id, n_tokens, round(x - y, 9) AS gap FROM l1 JOIN l2 USING (doc_id)",
        strat="SELECT *, ceil(ceil(100e0 * (cume_dist() OVER (ORDER BY gap))) / 100e0 * 100)::INT AS stratum FROM gap",
    ),
)
def representative_subset(spark, d):
    g = general(spark, d)
    return baselines.representative_subset(corpus(spark, d), lm.train(g), lm.train(g, 2), FRACTION).select("doc_id", "n_tokens", "stratum")


@query("domain_from_scratch", sql("SELECT term, count(*) AS c FROM tok GROUP BY term"))
def domain_from_scratch(spark, d):
    return baselines.domain_from_scratch(corpus(spark, d)).unigrams


_PAIRS = "SELECT '{a}' AS a, '{b}' AS b, round(corr({x}, {y}), 6) AS r FROM metrics WHERE perplexity IS NOT NULL AND entropy IS NOT NULL"


def _correlation_sql(expr):
    names = (("similarity", "perplexity"), ("similarity", "entropy"), ("perplexity", "entropy"))
    return " UNION ALL ".join(_PAIRS.format(a=a, b=b, x=expr(a), y=expr(b)) for a, b in names)


@query("metric_correlations", sql(_correlation_sql(lambda c: c)))
def metric_correlations(spark, d):
    return analysis.correlations(metrics_table.standard(spark, d))


@query("metric_correlations_log", sql(_correlation_sql(lambda c: "ln(perplexity)" if c == "perplexity" else c)))
def metric_correlations_log(spark, d):
    return analysis.correlations(metrics_table.standard(spark, d), "pearson_log")


@query(
    "metric_correlations_rank",
    sql(
        _correlation_sql(lambda c: c).replace("FROM metrics", "FROM mranks"),
        mranks="SELECT " + ", ".join(f"rank() OVER (ORDER BY {c}) + (count(*) OVER (PARTITION BY {c}) - 1) / 2e0 AS {c}" for c in ("similarity", "perplexity", "entropy")) + " FROM metrics WHERE perplexity IS NOT NULL AND entropy IS NOT NULL",
    ),
)
def metric_correlations_rank(spark, d):
    return analysis.correlations(metrics_table.standard(spark, d), "spearman")


_FLAGS = r"""SELECT doc_id, coalesce((length(text) - length(regexp_replace(text, '[|]', '', 'g'))) / nullif(length(text), 0) > 0.03e0, false) AS table_like,
 coalesce((length(text) - length(regexp_replace(text, '[\p{Lu}]', '', 'g'))) / nullif(length(text) - length(regexp_replace(text, '[\p{L}]', '', 'g')), 0) > 0.5e0, false) AS shouted,
 coalesce((length(text) - length(regexp_replace(text, '[#$%&*]', '', 'g'))) / nullif(length(text), 0) > 0.03e0, false) AS symbolic FROM corpus"""


@query("noise_flags", sql(_FLAGS))
def noise_flags(spark, d):
    return analysis.noise_flags(corpus(spark, d))


@query("noise_guarded_novelty", sql(hard_body("perplexity", "calm").replace("FROM metrics)", "FROM calm)"), flags=_FLAGS, calm="SELECT m.* FROM metrics m JOIN flags f USING (doc_id) WHERE NOT table_like AND NOT shouted AND NOT symbolic"))
def noise_guarded_novelty(spark, d):
    m = settle(analysis.guarded(metrics_table.standard(spark, d), analysis.noise_flags(corpus(spark, d))))
    return _ids(select.choose(m, "novelty", "hard", FRACTION), "cum_tokens")


@query(
    "band_profile",
    sql(
        "SELECT CASE WHEN s <= 0.01e0 THEN 0 WHEN s <= 0.05e0 THEN 1 WHEN s <= 0.1e0 THEN 2 ELSE 3 END AS band, count(*) AS docs, round(avg(table_like::INT), 6) AS table_share, round(avg(shouted::INT), 6) AS shouted_share, round(avg(n_tokens), 6) AS mean_tokens FROM pos JOIN flags USING (doc_id) GROUP BY band",
        flags=_FLAGS,
        pos="SELECT doc_id, n_tokens, ((count(*) OVER ()) - (rank() OVER (ORDER BY perplexity) - 1)) / (count(*) OVER ())::DOUBLE AS s FROM metrics WHERE perplexity IS NOT NULL",
    ),
)
def band_profile(spark, d):
    return analysis.band_profile(metrics_table.standard(spark, d), analysis.noise_flags(corpus(spark, d)), "perplexity")


def _chosen(spark, d, mode="hard"):
    m = metrics_table.standard(spark, d)
    parts = [select.choose(m, _COLUMN[n][0], mode, FRACTION).select(F.lit(_COLUMN[n][0]).alias("selector"), "doc_id", "n_tokens") for n in _COLUMN]
    return settle(reduce(lambda a, b: a.unionByName(b), parts))


_FOUR = {s: hard_body(c, src) for s, c, src in _COLUMN.values()}
_ALL_FOUR = " UNION ALL ".join(f"SELECT '{s}' AS selector, doc_id, n_tokens FROM c_{s}" for s in _FOUR)
_FOUR_CTE = {f"c_{s}": body for s, body in _FOUR.items()} | {"four": _ALL_FOUR}


@query(
    "selection_overlap",
    sql(
        "SELECT x.a, x.b, coalesce(c, 0) AS common, round(coalesce(c, 0) / (na + nb - coalesce(c, 0))::DOUBLE, 6) AS jaccard FROM (SELECT p.selector AS a, q.selector AS b, p.n AS na, q.n AS nb FROM fsize p JOIN fsize q ON p.selector < q.selector) x LEFT JOIN (SELECT p.selector AS a, q.selector AS b, count(*) AS c FROM four p JOIN four q ON p.doc_id = q.doc_id AND p.selector < q.selector GROUP BY ALL) y ON x.a = y.a AND x.b = y.b",
        **_FOUR_CTE,
        fsize="SELECT selector, count(*) AS n FROM four GROUP BY selector",
    ),
)
def selection_overlap(spark, d):
    return analysis.overlap(_chosen(spark, d))


@query("composition_cube", sql("SELECT lang, source, count(*) AS docs, sum(n_chars)::BIGINT AS chars, grouping_id(lang, source)::BIGINT AS level FROM corpus JOIN c_diversity USING (doc_id) GROUP BY CUBE (lang, source)", **_FOUR_CTE))
def composition_cube(spark, d):
    return analysis.composition_cube(select.choose(metrics_table.standard(spark, d), "diversity", "hard", FRACTION), corpus(spark, d))


@query(
    "composition_by_source",
    sql(
        "SELECT source, count(c.doc_id) AS chosen, count(*) AS all_docs, round(count(c.doc_id) / (sum(count(c.doc_id)) OVER ())::DOUBLE, 6) AS share, round(count(*) / (sum(count(*)) OVER ())::DOUBLE, 6) AS share_all FROM corpus d LEFT JOIN c_task_similar c USING (doc_id) GROUP BY source",
        **_FOUR_CTE,
    ),
)
def composition_by_source(spark, d):
    return analysis.composition(select.choose(metrics_table.standard(spark, d), "task_similar", "hard", FRACTION), corpus(spark, d))


@query(
    "hard_minus_soft",
    sql(
        "SELECT doc_id, n_tokens FROM h WHERE doc_id NOT IN (SELECT doc_id FROM s)",
        h=hard_body("entropy"),
        s=soft_body("q_entropy", "quant"),
    ),
)
def hard_minus_soft(spark, d):
    m = metrics_table.standard(spark, d)
    h, s = (_ids(select.choose(m, "diversity", mode, FRACTION)) for mode in ("hard", "soft"))
    return h.join(s.select("doc_id"), "doc_id", "left_anti")


_FRACTIONS = (0.01, 0.05, 0.1, 0.2, 0.5, 1.0)


@query(
    "size_ablation",
    sql(
        " UNION ALL ".join(
            f"SELECT '{s}' AS selector, f AS fraction, count(*) FILTER (cum <= floor(f * t)) AS docs, coalesce(sum(n_tokens) FILTER (cum <= floor(f * t)), 0)::BIGINT AS tokens FROM (SELECT n_tokens, sum(n_tokens) OVER (ORDER BY round({c}, 9) DESC, doc_id ROWS UNBOUNDED PRECEDING) AS cum FROM {src} WHERE {c} IS NOT NULL) CROSS JOIN (SELECT sum(n_tokens)::DOUBLE AS t FROM metrics) CROSS JOIN (SELECT unnest({list(_FRACTIONS)}::DOUBLE[]) AS f) GROUP BY f"
            for s, c, src in (("task_similar", "similarity", "metrics"), ("novelty", "perplexity", "metrics"), ("diversity", "entropy", "metrics"), ("uniform_budget", "u", f"(SELECT *, -{uniform('doc_id', 7)} AS u FROM metrics)"))
        )
    ),
)
def size_ablation(spark, d):
    return selections_at(metrics_table.standard(spark, d), _FRACTIONS)


@query("new_term_rate", sql(r"SELECT count(*) AS terms, round(avg((term NOT IN (SELECT term FROM lm1))::INT), 6) AS new_rate FROM (SELECT DISTINCT term FROM tok JOIN c_diversity USING (doc_id))", **_FOUR_CTE))
def new_term_rate(spark, d):
    chosen = select.choose(metrics_table.standard(spark, d), "diversity", "hard", FRACTION)
    r = metrics.new_term_rate(corpus(spark, d).join(chosen.select("doc_id"), "doc_id", "left_semi"), lm.unigram_counts(general(spark, d)))
    return r.select("terms", F.round("new_rate", 6).alias("new_rate"))


@query(
    "quality_guard_report",
    sql("SELECT selector, count(*) AS docs, sum(n_tokens)::BIGINT AS tokens, round(avg(n_tokens), 6) AS mean_tokens FROM four GROUP BY selector", **_FOUR_CTE),
)
def quality_guard_report(spark, d):
    """Realised size and mean length of each hard selection: length bias at a glance."""
    return _chosen(spark, d).groupBy("selector").agg(F.count(F.lit(1)).alias("docs"), F.sum("n_tokens").alias("tokens"), F.round(F.avg("n_tokens"), 6).alias("mean_tokens"))
