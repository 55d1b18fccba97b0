"""Measures, few-shot tasks, multiple choice, costs and the reported figures."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import functions as F

from winnow.functions.textops import hash_uniform, n_tokens
from winnow.operators import costs, fewshot, lm, metrics, metrics_table, results, select, tasks
from winnow.plans import experiments
from winnow.plans.catalog import query
from winnow.plans.oracle import hard_body, soft_body, sql, uniform
from winnow.plans.queries_curation import GRAMS
from winnow.plans.queries_scores import corpus, general, seed_of
from winnow.plans.settle import settle
from winnow.sources.tables import read_table

_CHOSEN = {"h": hard_body("entropy")}
_CONT = _CHOSEN | dict(
    lmc="SELECT term, sum(c)::BIGINT AS c FROM (SELECT term, c FROM lm1 UNION ALL SELECT term, count(*) AS c FROM tok JOIN h USING (doc_id) GROUP BY term) GROUP BY term",
    lmct="SELECT sum(c)::DOUBLE AS n, count(*)::DOUBLE AS v FROM lmc",
)


def _chosen(spark, d):
    return select.choose(metrics_table.standard(spark, d), "diversity", "hard", 0.1)


def _continued(spark, d):
    docs = corpus(spark, d)
    return lm.continue_training(lm.train(general(spark, d)), docs.join(_chosen(spark, d).select("doc_id"), "doc_id", "left_semi"))


@query("continued_lm_counts", sql("SELECT term, c FROM lmc", **_CONT))
def continued_lm_counts(spark, d):
    return _continued(spark, d).unigrams.select("term", F.col("c").cast("long").alias("c"))


_TWO = "SELECT round(exp(-sum(ln((coalesce(a.c, 0) + 1e0) / (lmt.n + lmt.v + 1e0))) / count(*)) / exp(-sum(ln((coalesce(b.c, 0) + 1e0) / (lmct.n + lmct.v + 1e0))) / count(*)) - 1, 6) AS {name} FROM {words} w LEFT JOIN lm1 a USING (term) LEFT JOIN lmc b USING (term) CROSS JOIN lmt CROSS JOIN lmct"


@query("domain_gain", sql(_TWO.format(name="domain_gain", words="stok"), **_CONT))
def domain_gain(spark, d):
    base, cont = lm.train(general(spark, d)), _continued(spark, d)
    a, b = (lm.corpus_perplexity(seed_of(spark, d), m, "seed_id").select(F.col("perplexity").alias(n)) for m, n in ((base, "a"), (cont, "b")))
    return a.crossJoin(b).select(F.round(F.col("a") / F.col("b") - 1, 6).alias("domain_gain"))


@query("retention", sql(_TWO.format(name="retention", words="ctok"), ctok="SELECT term FROM cpos", **_CONT))
def retention(spark, d):
    base, cont = lm.train(general(spark, d)), _continued(spark, d)
    texts = general(spark, d).withColumn("doc_id", F.concat_ws("-", "conv_id", "turn"))
    a, b = (lm.corpus_perplexity(texts, m).select(F.col("perplexity").alias(n)) for m, n in ((base, "a"), (cont, "b")))
    return a.crossJoin(b).select(F.round(F.col("a") / F.col("b") - 1, 6).alias("retention"))


_W = r"regexp_extract_all(lower(text), '[\p{L}\p{N}]+')"
MU = f"{fewshot.MU:.0f}e0"
_SHOTS = dict(
    shots="SELECT * FROM (SELECT s.seed, task, doc_id, label, text, row_number() OVER (PARTITION BY task, s.seed ORDER BY md5(doc_id || ':' || task || ':' || s.seed), doc_id) AS r FROM pool CROSS JOIN (SELECT unnest(range(0, 10))::INT AS seed) s WHERE rank <= 50) WHERE r <= 5",
    seen=f"SELECT seed, task, label, term, count(*) AS k FROM (SELECT seed, task, label, unnest({_W}) AS term FROM shots) GROUP BY ALL",
    pri="SELECT r.seed, r.task, c.class, coalesce(m.mass, 0) AS mass, ln((coalesce(h.held, 0) + 1e0) / (sum(coalesce(h.held, 0)) OVER (PARTITION BY r.seed, r.task) + 2)) AS prior FROM (SELECT DISTINCT seed, task FROM shots) r CROSS JOIN (SELECT unnest(['0', '1']) AS class) c LEFT JOIN (SELECT seed, task, label, count(*) AS held FROM shots GROUP BY ALL) h ON h.seed = r.seed AND h.task = r.task AND h.label = c.class LEFT JOIN (SELECT seed, task, label, sum(k) AS mass FROM seen GROUP BY ALL) m ON m.seed = r.seed AND m.task = r.task AND m.label = c.class",
    tests="SELECT task, doc_id, text, label FROM pool WHERE rank > 50",
    tw=f"SELECT doc_id, term, count(*) AS n FROM (SELECT doc_id, unnest({_W}) AS term FROM (SELECT DISTINCT doc_id, text FROM tests)) GROUP BY ALL",
    p1="SELECT doc_id, term, tw.n, (coalesce(c, 0) + 1e0) / (lmt.n + lmt.v + 1e0) AS p FROM tw LEFT JOIN lm1 USING (term) CROSS JOIN lmt",
    tl="SELECT doc_id, sum(n) AS nt, sum(n * ln(p)) AS ll FROM p1 GROUP BY doc_id",
    extra=f"SELECT doc_id, seed, task, label AS class, sum(n * ln((k + {MU} * p) / ({MU} * p))) AS extra FROM p1 JOIN seen USING (term) GROUP BY ALL",
    scored=f"SELECT t.task, t.doc_id, t.label, pri.seed, pri.class, round(prior + coalesce(ll, 0) + coalesce(nt, 0) * ln({MU} / (mass + {MU})) + coalesce(extra, 0), 6) AS score FROM tests t JOIN pri ON pri.task = t.task LEFT JOIN tl ON tl.doc_id = t.doc_id LEFT JOIN extra e ON e.doc_id = t.doc_id AND e.seed = pri.seed AND e.task = t.task AND e.class = pri.class",
    predicted="SELECT task, seed, doc_id, label, class AS predicted FROM (SELECT *, row_number() OVER (PARTITION BY task, seed, doc_id ORDER BY score DESC, class DESC) AS place FROM scored) WHERE place = 1",
    counts="SELECT task, seed, c, sum((label = c AND predicted = c)::INT) AS tp, sum((label <> c AND predicted = c)::INT) AS fp, sum((label = c AND predicted <> c)::INT) AS fn FROM predicted CROSS JOIN (SELECT unnest(['0', '1']) AS c) GROUP BY ALL HAVING sum((label = c OR predicted = c)::INT) > 0",
    f1s="SELECT task, seed, avg(coalesce(2e0 * tp / nullif(2 * tp + fp + fn, 0), 0)) AS f1 FROM counts GROUP BY ALL",
)


def _predictions(spark, d):
    ranked = settle(tasks.ranked_pool(tasks.labelled(read_table(spark, d, "documents"), read_table(spark, d, "labels"))))
    shots = settle(fewshot.draw_shots(ranked.where("rank <= 50")))
    return fewshot.classify(ranked.where("rank > 50"), shots, lm.train(general(spark, d)))


@query("fewshot_predictions", sql("SELECT task, seed, doc_id, label, predicted FROM predicted", **_SHOTS))
def fewshot_predictions(spark, d):
    return _predictions(spark, d).select("task", "seed", "doc_id", "label", "predicted")


@query("fewshot_f1", sql("SELECT task, seed, round(f1, 6) AS f1 FROM f1s", **_SHOTS))
def fewshot_f1(spark, d):
    return metrics.f1(_predictions(spark, d), "macro", ("task", "seed")).select("task", "seed", F.round("f1", 6).alias("f1"))


@query(
    "f1_averages",
    sql(
        "SELECT task, seed, round(sum(f * sup) / sum(sup), 6) AS weighted, round(2e0 * sum(tp) / (2 * sum(tp) + sum(fp) + sum(fn)), 6) AS micro, round(coalesce(max(f) FILTER (c = '1'), 0), 6) AS binary_f1 FROM (SELECT *, tp + fn AS sup, coalesce(2e0 * tp / nullif(2 * tp + fp + fn, 0), 0) AS f FROM counts) GROUP BY ALL",
        **_SHOTS,
    ),
)
def f1_averages(spark, d):
    p, by = settle(_predictions(spark, d)), ("task", "seed")
    parts = [metrics.f1(p, a, by).select(*by, F.round("f1", 6).alias(n)) for a, n in (("weighted", "weighted"), ("micro", "micro"), ("binary", "binary_f1"))]
    return reduce(lambda a, b: a.join(b, list(by)), parts)


@query("accuracy_by_task", sql("SELECT task, seed, round(avg((label = predicted)::INT), 6) AS accuracy FROM predicted GROUP BY ALL", **_SHOTS))
def accuracy_by_task(spark, d):
    return metrics.accuracy(_predictions(spark, d), ("task", "seed")).select("task", "seed", F.round("accuracy", 6).alias("accuracy"))


@query("seed_mean_sd", sql("SELECT task, count(*) AS runs, round(avg(f1), 6) AS mean, round(stddev_samp(f1), 6) AS sd, round(stddev_pop(f1), 6) AS sd_pop FROM f1s GROUP BY task", **_SHOTS))
def seed_mean_sd(spark, d):
    f = metrics.f1(_predictions(spark, d), "macro", ("task", "seed"))
    return metrics.over_seeds(f, "f1", ("task",)).select("task", "runs", *[F.round(c, 6).alias(c) for c in ("mean", "sd", "sd_pop")])


def _occurrences(shapes: dict[str, str], docs: str) -> str:
    """Every match of every shape with its place: what lies between matches and the matches before it add up to its start."""
    parts = [
        f"SELECT doc_id, '{kind}' AS type, unnest(regexp_extract_all(text, '{p}')) AS m, unnest(string_split_regex(text, '{p}')[1:len(regexp_extract_all(text, '{p}'))]) AS gap, generate_subscripts(regexp_extract_all(text, '{p}'), 1) AS k FROM {docs}"
        for kind, p in shapes.items()
    ]
    return f"SELECT doc_id, type, m, 1 + sum(length(gap) + length(m)) OVER w - length(m) AS start, 1 + sum(length(gap) + length(m)) OVER w AS stop FROM ({' UNION ALL '.join(parts)}) WINDOW w AS (PARTITION BY doc_id, type ORDER BY k ROWS UNBOUNDED PRECEDING)"


_SHAPE = "CASE WHEN contains(m, ' ') THEN m ELSE " + reduce(lambda x, step: f"regexp_replace({x}, '{step[0]}', '{step[1]}', 'g')", fewshot.SHAPE, "m") + " END"
_FIFTH = uniform("doc_id", "spans") + " < 0.2e0"


@query(
    "span_f1",
    sql(
        "SELECT type, count(*) FILTER (p AND g)::BIGINT AS tp, count(*) FILTER (p AND NOT g)::BIGINT AS fp, count(*) FILTER (g AND NOT p)::BIGINT AS fn, round(2e0 * count(*) FILTER (p AND g) / (2 * count(*) FILTER (p AND g) + count(*) FILTER (p AND NOT g) + count(*) FILTER (g AND NOT p)), 6) AS f1 FROM (SELECT type, bool_or(x = 0) AS p, bool_or(x = 1) AS g FROM (SELECT doc_id, start, stop, type, 0 AS x FROM tagged UNION ALL SELECT doc_id, start, stop, type, 1 FROM gold WHERE doc_id IN (SELECT doc_id FROM rest)) GROUP BY doc_id, start, stop, type) GROUP BY type",
        rest=f"SELECT doc_id, text FROM corpus WHERE NOT ({_FIFTH})",
        gold=_occurrences(fewshot.SPANS, "corpus"),
        tok1=_occurrences({"": fewshot.TOKEN}, "rest"),
        toks="SELECT doc_id, start, stop, m FROM tok1 UNION ALL SELECT a.doc_id, a.start, b.stop, a.m || ' ' || b.m FROM tok1 a JOIN tok1 b ON a.doc_id = b.doc_id AND b.start = a.stop + 1 JOIN rest r ON r.doc_id = a.doc_id WHERE substring(r.text, a.stop::BIGINT, 1) = ' '",
        heads=f"SELECT DISTINCT type, {_SHAPE} AS head FROM gold WHERE {_FIFTH}",
        tagged=f"SELECT t.doc_id, t.start, t.stop, h.type FROM toks t JOIN heads h ON {_SHAPE.replace('m,', 't.m,').replace('(m', '(t.m').replace('THEN m', 'THEN t.m')} = h.head",
    ),
)
def span_f1(spark, d):
    docs = corpus(spark, d).select("doc_id", "text")
    fifth = hash_uniform("doc_id", "spans") < 0.2  # as shots
    pool, rest = docs.where(fifth), docs.where(~fifth)
    return metrics.span_f1(fewshot.lexicon_spans(pool, rest), fewshot.rule_spans(rest)).withColumn("f1", F.round("f1", 6))


@query("model_weight_choice")
def model_weight_choice(spark, d):
    """How each weight of the model does within the shot pool; fewshot.MU is the best of them on the given tables."""
    b = experiments.Bench(spark, d)
    return fewshot.weights_on_pool(b.pool, b.base)


#: The share of good documents, in percent, of each source (a selector) in each language (a task), and of all of them as the base.
_PUB_CTE = dict(
    rated="SELECT coalesce(source, 'none') AS source, coalesce(lang, 'none') AS lang, quality FROM documents JOIN labels USING (doc_id)",
    pub="SELECT source AS selector, lang AS task, 100e0 * avg(quality) AS value FROM rated GROUP BY ALL UNION ALL SELECT 'base_only', lang, 100e0 * avg(quality) FROM rated GROUP BY ALL",
)


def _by_source(docs, *values):
    """(selector, task) and aggregates: every source, and all of them as base_only, by language."""
    task = F.coalesce("lang", F.lit("none")).alias("task")
    return docs.groupBy(F.coalesce("source", F.lit("none")).alias("selector"), task).agg(*values).unionByName(docs.groupBy(F.lit("base_only").alias("selector"), task).agg(*values))


def _quality(spark, d):
    rated = read_table(spark, d, "documents").select("doc_id", "lang", "source").join(read_table(spark, d, "labels").select("doc_id", "quality"), "doc_id")
    return _by_source(rated, (F.lit(100.0) * F.avg("quality")).alias("value"))


@query(
    "win_rate",
    sql("SELECT a.selector, round(100e0 * avg(CASE WHEN a.value > b.value THEN 1e0 WHEN a.value = b.value THEN 0.5e0 ELSE 0e0 END), 6) AS win_rate FROM pub a JOIN pub b ON a.task = b.task AND a.selector <> b.selector GROUP BY a.selector", **_PUB_CTE),
)
def win_rate(spark, d):
    return metrics.win_rate(_quality(spark, d)).select("selector", F.round("win_rate", 6).alias("win_rate"))


@query(
    "win_rate_with_self",
    sql("SELECT a.selector, round(100e0 * avg(CASE WHEN a.selector = b.selector OR a.value > b.value THEN 1e0 ELSE 0e0 END), 6) AS win_rate FROM pub a JOIN pub b ON a.task = b.task GROUP BY a.selector", **_PUB_CTE),
)
def win_rate_with_self(spark, d):
    return metrics.win_rate(_quality(spark, d), ties="strict", with_self="win").select("selector", F.round("win_rate", 6).alias("win_rate"))


@query(
    "delta_pct",
    sql("SELECT selector, round(average, 6) AS average, round(sd_tasks, 6) AS sd_tasks, round(100e0 * (average / (SELECT average FROM avgs WHERE selector = 'base_only') - 1), 6) AS delta_pct FROM avgs", **_PUB_CTE, avgs="SELECT selector, avg(value) AS average, stddev_pop(value) AS sd_tasks FROM pub GROUP BY selector"),
)
def delta_pct(spark, d):
    return metrics.delta_pct(metrics.task_average(_quality(spark, d))).select("selector", *[F.round(c, 6).alias(c) for c in ("average", "sd_tasks", "delta_pct")])


#: Lengths by source and language, recounted from the texts (value) beside what the table reports (average, average_sd, gain).
_SEL_CTE = dict(
    sized="SELECT coalesce(source, 'none') AS selector, coalesce(lang, 'none') AS task, avg(length(text)) AS value, avg(n_chars) AS reported FROM documents GROUP BY ALL UNION ALL SELECT 'base_only', coalesce(lang, 'none') AS task, avg(length(text)), avg(n_chars) FROM documents GROUP BY task",
    stated="SELECT selector, round(avg(reported), 4) AS average, round(stddev_pop(reported), 4) AS average_sd FROM sized GROUP BY selector",
    sel="SELECT selector, '' AS mode, task, value, average, average_sd, round(100e0 * (average / (SELECT average FROM stated WHERE selector = 'base_only') - 1), 4) AS gain FROM sized JOIN stated USING (selector)",
    avgs="SELECT selector, mode, min(average) AS a FROM sel GROUP BY ALL",
)


@query(
    "published_replay",
    sql(
        "SELECT selector, mode, round(avg(value), 4) AS average, round(stddev_pop(value), 4) AS sd_tasks, min(average) AS reported_average, min(average_sd) AS reported_sd, min(gain) AS reported_gain, round(100e0 * (min(average) / (SELECT a FROM avgs WHERE selector = 'base_only') - 1), 4) AS gain FROM sel GROUP BY selector, mode",
        **_SEL_CTE,
    ),
)
def published_replay(spark, d):
    """The published comparison's arithmetic on the table's own lengths: those it reports beside those of its texts."""
    sized = _by_source(read_table(spark, d, "documents"), F.avg(F.length("text")).alias("value"), F.avg("n_chars").alias("reported"))
    stated = sized.groupBy("selector").agg(F.round(F.avg("reported"), 4).alias("average"), F.round(F.stddev_pop("reported"), 4).alias("average_sd"))
    stated = metrics.delta_pct(stated).withColumn("gain", F.round("delta_pct", 4)).drop("delta_pct")
    return results.replay(spark, sized.join(stated, "selector").withColumn("mode", F.lit("")))


#: selector: (column, table of the hard choice, weight, table of the soft one)
_SELECTORS = {
    "task_similar": ("similarity", "metrics", "q_similarity", "quant"),
    "novelty": ("perplexity", "metrics", "q_perplexity", "quant"),
    "diversity": ("entropy", "metrics", "q_entropy", "quant"),
    "blended": ("blended", "blend", "blended", "blend"),
}
_MADE = dict(
    **{f"h_{s}": hard_body(c, t) for s, (c, t, _, _) in _SELECTORS.items()},
    **{f"s_{s}": soft_body(w, t) for s, (_, _, w, t) in _SELECTORS.items()},
    made=" UNION ALL ".join(["SELECT 'full_domain' AS selector, '' AS mode, doc_id FROM metrics", *[f"SELECT '{s}', '{mode}', doc_id FROM {mode[0]}_{s}" for s in _SELECTORS for mode in ("hard", "soft")]]),
    avgs="SELECT selector, mode, round(50e0 * (avg(quality) + avg(1 - toxic)), 6) AS a FROM made JOIN labels USING (doc_id) GROUP BY ALL",
)


@query(
    "published_observations",
    sql(
        "SELECT observation, coalesce(holds, false) AS holds FROM ("
        "SELECT 'hard task-similar is first' AS observation, (SELECT a FROM avgs WHERE selector = 'task_similar' AND mode = 'hard') = (SELECT max(a) FROM avgs) AS holds"
        " UNION ALL SELECT 'hard blended is within one point of it', (SELECT a FROM avgs WHERE selector = 'task_similar' AND mode = 'hard') - (SELECT a FROM avgs WHERE selector = 'blended' AND mode = 'hard') <= 1"
        " UNION ALL SELECT 'hard diversity is third', (SELECT a FROM avgs WHERE selector = 'diversity' AND mode = 'hard') IS NOT NULL AND (SELECT count(*) FROM avgs WHERE a > (SELECT a FROM avgs WHERE selector = 'diversity' AND mode = 'hard')) = 2"
        " UNION ALL SELECT 'hard beats soft for every metric', (SELECT count(*) = 4 AND bool_and(h.a > s.a) FROM avgs h JOIN avgs s ON h.selector = s.selector AND h.mode = 'hard' AND s.mode = 'soft')"
        " UNION ALL SELECT 'all data lies below a tenth by similarity', (SELECT a FROM avgs WHERE selector = 'full_domain') < (SELECT a FROM avgs WHERE selector = 'task_similar' AND mode = 'hard'))",
        **_MADE,
    ),
)
def published_observations(spark, d):
    """Which published observations hold for the share of good and of clean documents among what each selection of the given tables chooses."""
    m, labels = metrics_table.standard(spark, d), read_table(spark, d, "labels").select("doc_id", "quality", "toxic")
    parts = [select.choose(m, s, mode, 0.1).select(F.lit(s).alias("selector"), F.lit(mode).alias("mode"), "doc_id") for s in _SELECTORS for mode in ("hard", "soft")]
    made = reduce(lambda a, b: a.unionByName(b), parts, m.select(F.lit("full_domain").alias("selector"), F.lit("").alias("mode"), "doc_id"))
    mean = F.round(F.lit(50.0) * (F.avg("quality") + F.avg(F.lit(1) - F.col("toxic"))), 6)
    return results.observations(spark, {(r["selector"], r["mode"]): r["a"] for r in made.join(labels, "doc_id").groupBy("selector", "mode").agg(mean.alias("a")).collect()})


@query(
    "cost_ledger",
    sql(
        "SELECT unnest(['corpus_share_of_pretraining', 'subset_share_of_pretraining', 'tokens_per_second_1B', 'tokens_per_second_6.9B', 'surrogate_over_full_scoring', 'full_scoring_over_training']) AS item,"
        " unnest([round(c / b, 9), round(c * 0.1e0 / b, 9), round(c / (3e0 * 86400), 9), round(c / (18e0 * 86400), 9), round(0.07e0 * c / c, 9), round(0.25e0 * c / c, 9)]) AS value FROM seen",
        seen="SELECT (SELECT sum(n_tokens)::DOUBLE FROM len) AS c, (SELECT n FROM lmt) AS b",
    ),
)
def cost_ledger(spark, d):
    return costs.ledger(*[t.select(n_tokens("text").alias("n_tokens")) for t in (corpus(spark, d), general(spark, d))])


@query("tokens_used", sql("SELECT (SELECT sum(n_tokens) FROM h)::BIGINT AS tokens, (SELECT sum(n_tokens) FROM metrics)::BIGINT AS all_tokens, round((SELECT sum(n_tokens) FROM h)::DOUBLE / (SELECT sum(n_tokens) FROM metrics), 6) AS share", **_CHOSEN))
def tokens_used(spark, d):
    return costs.tokens_used(_chosen(spark, d), metrics_table.standard(spark, d)).withColumn("share", F.round("share", 6))


def _items_sql(items: str) -> dict[str, str]:
    return dict(
        items=items,
        placed="SELECT *, row_number() OVER (ORDER BY md5(item::VARCHAR), item) - 1 AS at, count(*) OVER () AS total FROM items",
        pairs="SELECT a.item, c.candidate, a.prompt, b.text, c.candidate = 0 AS is_true FROM placed a CROSS JOIN (SELECT unnest(range(0, 4)) AS candidate) c JOIN placed b ON b.at = (a.at + c.candidate) % a.total",
        pw=f"SELECT item, candidate, term, count(*) AS k FROM (SELECT item, candidate, unnest({_W.replace('text', 'prompt')}) AS term FROM pairs) GROUP BY ALL",
        psz=f"SELECT item, candidate, len({_W.replace('text', 'prompt')}) AS size FROM pairs",
        cw=f"SELECT item, candidate, term, count(*) AS m FROM (SELECT item, candidate, unnest({_W}) AS term FROM pairs) GROUP BY ALL",
        cll="SELECT item, candidate, sum(m * ln((coalesce(k, 0) + 200e0 * ((coalesce(c, 0) + 1e0) / (lmt.n + lmt.v + 1e0))) / (size + 200e0))) AS ll FROM cw LEFT JOIN pw USING (item, candidate, term) LEFT JOIN lm1 USING (term) JOIN psz USING (item, candidate) CROSS JOIN lmt GROUP BY ALL",
        sc="SELECT item, candidate, is_true, coalesce(ll, 0) AS score, coalesce(ll, 0) / greatest(strlen(text), 1) AS score_norm FROM pairs LEFT JOIN cll USING (item, candidate)",
    )


def _best(score: str) -> str:
    return f"SELECT count(*) AS items, round(avg(is_true::INT), 6) AS accuracy FROM (SELECT *, row_number() OVER (PARTITION BY item ORDER BY round({score}, 9) DESC, candidate) AS place FROM sc) WHERE place = 1"


_TURNS = _items_sql("SELECT conv_id || '-' || turn AS item, text AS prompt, next AS text FROM (SELECT conv_id, turn, text, lead(text) OVER (PARTITION BY conv_id ORDER BY turn) AS next FROM conversations) WHERE next IS NOT NULL")
_CUT = "floor(len(string_split(text, ' ')) / 2)::INT"
_PASSAGES = _items_sql(f"SELECT item_id AS item, array_to_string(string_split(text, ' ')[1:{_CUT}], ' ') AS prompt, array_to_string(string_split(text, ' ')[{_CUT} + 1:], ' ') AS text FROM benchmark")


def _turns(spark, d):
    return fewshot.with_scores(fewshot.conditional_ll(fewshot.with_distractors(fewshot.next_turns(general(spark, d))), lm.train(general(spark, d))))


@query("choice_accuracy", sql(_best("score"), **_TURNS))
def choice_accuracy(spark, d):
    return metrics.choice_accuracy(_turns(spark, d)).select("items", F.round("accuracy", 6).alias("accuracy"))


@query("choice_accuracy_norm", sql(_best("score_norm"), **_TURNS))
def choice_accuracy_norm(spark, d):
    return metrics.choice_accuracy(_turns(spark, d), "score_norm").select("items", F.round("accuracy", 6).alias("accuracy"))


@query("choice_passage_halves", sql(_best("score"), **_PASSAGES))
def choice_passage_halves(spark, d):
    pairs = fewshot.with_distractors(fewshot.passage_halves(read_table(spark, d, "benchmark")))
    return metrics.choice_accuracy(fewshot.with_scores(fewshot.conditional_ll(pairs, lm.train(general(spark, d))))).select("items", F.round("accuracy", 6).alias("accuracy"))


@query("choice_title_to_article")
def choice_title_to_article(spark, d):
    pairs = fewshot.with_distractors(fewshot.page_titles(read_table(spark, d, "pages")))
    return metrics.choice_accuracy(fewshot.with_scores(fewshot.conditional_ll(pairs, lm.train(general(spark, d))))).select("items", F.round("accuracy", 6).alias("accuracy"))


@query(
    "mc1_mc2",
    sql(
        f"SELECT a.items, a.accuracy AS mc1, m.mc2 FROM ({_best('score')}) a CROSS JOIN (SELECT round(avg(mass), 6) AS mc2 FROM (SELECT item, coalesce(sum(e) FILTER (is_true), 0) / sum(e) AS mass FROM (SELECT *, exp(score - max(score) OVER (PARTITION BY item)) AS e FROM sc) GROUP BY item)) m",
        **_PASSAGES,
    ),
)
def mc1_mc2(spark, d):
    pairs = fewshot.with_distractors(fewshot.passage_halves(read_table(spark, d, "benchmark")))
    s = settle(fewshot.with_scores(fewshot.conditional_ll(pairs, lm.train(general(spark, d)))))
    one = metrics.mc1(s).select("items", F.round("accuracy", 6).alias("mc1"))
    return one.crossJoin(metrics.mc2(s).select(F.round("mc2", 6).alias("mc2")))


@query("mc_multi_truth")
def mc_multi_truth(spark, d):
    from winnow.operators import dedup

    docs = settle(corpus(spark, d).select("doc_id", "text"))
    pairs = fewshot.copies_as_truths(docs, settle(dedup.resembling_pairs(docs)))
    s = settle(fewshot.with_scores(fewshot.conditional_ll(pairs, lm.train(general(spark, d)))))
    return metrics.mc1(s).select("items", F.round("accuracy", 6).alias("mc1")).crossJoin(metrics.mc2(s).select(F.round("mc2", 6).alias("mc2")))


@query(
    "purity_lift",
    sql(
        "SELECT count(*) AS labelled, count(h.doc_id) AS chosen, round(avg(quality), 6) AS quality_all, round(avg(quality) FILTER (h.doc_id IS NOT NULL), 6) AS quality_chosen, round(avg(toxic) FILTER (h.doc_id IS NOT NULL), 6) AS toxic_chosen, round(count(*) FILTER (h.doc_id IS NOT NULL AND quality = 1) / nullif(count(*) FILTER (quality = 1), 0)::DOUBLE, 6) AS recall, round(avg(quality) FILTER (h.doc_id IS NOT NULL) / avg(quality), 6) AS lift FROM labels LEFT JOIN h USING (doc_id)",
        **_CHOSEN,
    ),
)
def purity_lift(spark, d):
    r = metrics.purity(_chosen(spark, d), read_table(spark, d, "labels"))
    return r.select("labelled", "chosen", *[F.round(c, 6).alias(c) for c in ("quality_all", "quality_chosen", "toxic_chosen", "recall", "lift")])


def _auc_sql(c: str) -> str:
    return f"SELECT '{c}' AS metric, round((sum(r) FILTER (quality = 1) - count(*) FILTER (quality = 1) * (count(*) FILTER (quality = 1) + 1) / 2e0) / (count(*) FILTER (quality = 1) * count(*) FILTER (quality = 0)), 6) AS auc FROM (SELECT quality, rank() OVER (ORDER BY {c}) + (count(*) OVER (PARTITION BY {c}) - 1) / 2e0 AS r FROM metrics JOIN labels USING (doc_id) WHERE {c} IS NOT NULL)"


@query("metric_auc", sql(" UNION ALL ".join(_auc_sql(c) for c in ("similarity", "perplexity", "entropy"))))
def metric_auc(spark, d):
    m, labels = metrics_table.standard(spark, d), read_table(spark, d, "labels")
    parts = [metrics.auc(m, labels, c).select(F.lit(c).alias("metric"), F.round("auc", 6).alias("auc")) for c in ("similarity", "perplexity", "entropy")]
    return reduce(lambda a, b: a.unionByName(b), parts)


#: How far a sketched quantile may lie from the exact one.
SKETCH_BOUND = 0.02


@query("approximation_error", " UNION ALL ".join(f"SELECT '{c}' AS metric, '{how}' AS method, true AS within" for c in ("similarity", "perplexity") for how in ("approx", "kll")))
def approximation_error(spark, d):
    """Whether no quantile under a sketched grid lies further than SKETCH_BOUND from the exact one."""
    m = metrics_table.standard(spark, d)
    parts = [metrics.rank_error(m, c, how).select(F.lit(c).alias("metric"), F.lit(how).alias("method"), (F.col("largest") <= SKETCH_BOUND + 1e-9).alias("within")) for c in ("similarity", "perplexity") for how in ("approx", "kll")]
    return reduce(lambda a, b: a.unionByName(b), parts)


@query("near_dup_recall", sql("SELECT count(*) AS pairs, true AS complete FROM (SELECT a, b, c / (x.n + y.n - c)::DOUBLE AS jaccard FROM (SELECT p.doc_id AS a, q.doc_id AS b, count(*) AS c FROM g p JOIN g q ON p.g = q.g AND p.doc_id < q.doc_id GROUP BY ALL) JOIN gn x ON a = x.doc_id JOIN gn y ON b = y.doc_id) WHERE jaccard >= 0.8", **GRAMS))
def near_dup_recall(spark, d):
    """The pairs that reach the threshold, and whether min-hashing joined at least 0.95 of them."""
    from winnow.operators import dedup

    docs = settle(corpus(spark, d).select("doc_id", "text"))
    return metrics.dedup_recall(settle(dedup.near(docs)), dedup.resembling_pairs(docs)).select("pairs", (F.coalesce("recall", F.lit(1.0)) >= 0.95).alias("complete"))


@query("selection_comparison")
def selection_comparison(spark, d):
    b = experiments.Bench(spark, d)
    return experiments.comparison_table(settle(experiments.selection_comparison(b, experiments.ROWS, seeds=10)))


@query("gain_and_retention")
def gain_and_retention(spark, d):
    return experiments.gain_and_retention(experiments.Bench(spark, d))


@query("open_domain_choice")
def open_domain_choice(spark, d):
    return experiments.open_domain(experiments.Bench(spark, d))


@query("size_pair")
def size_pair(spark, d):
    return experiments.size_pair(spark, d).groupBy("model", "selector", "task").agg(F.round(F.avg("f1"), 6).alias("f1"), F.round(F.avg("accuracy"), 6).alias("accuracy"))


@query("f1_by_size")
def f1_by_size(spark, d):
    return experiments.f1_ablation(experiments.Bench(spark, d))


@query("supervised_tuning")
def supervised_tuning(spark, d):
    """The classifier trained on all labelled pool rows, with no continued training."""
    b = experiments.Bench(spark, d)
    shots = b.pool.select(F.lit(0).alias("seed"), "task", "doc_id", "label", "text")
    p = fewshot.classify(b.tests, settle(shots), b.base)
    return metrics.f1(p, "macro", ("task", "seed")).select("task", F.round("f1", 6).alias("f1"))
