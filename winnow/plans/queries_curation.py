"""Corpus, dedup and seed queries."""

from __future__ import annotations

from pyspark.sql import functions as F

from winnow.functions.textops import n_tokens, words
from winnow.operators import curate, dedup, tasks
from winnow.operators.curate import ENTITIES, HTML_STEPS
from winnow.plans.catalog import query
from winnow.plans.oracle import sql
from winnow.plans.settle import spread_like
from winnow.sources.tables import read_table


def _html_sql() -> str:
    out = "html"
    for pattern, new in HTML_STEPS:
        quoted = pattern.replace("'", "''")
        out = f"regexp_replace({out}, '{quoted}', '{new}', 'g')" if new != "\n" else f"regexp_replace({out}, '{quoted}', chr(10), 'g')"
    for name, char in ENTITIES:
        quoted = char.replace("'", "''")
        out = f"replace({out}, '{name}', '{quoted}')"
    out = f"regexp_replace({out}, '[ \\t]+', ' ', 'g')"
    out = f"regexp_replace({out}, ' ?\\n ?', chr(10), 'g')"
    return f"regexp_replace({out}, '^\\n+|\\n+$|(\\n)\\n+', '\\1', 'g')"


_COUNTS = r"""count(*) AS docs, sum(len(regexp_extract_all(lower(text), '[\p{L}\p{N}]+')))::BIGINT AS words,
 sum(len(regexp_extract_all(text, '\p{L}+|\p{N}+|[^\p{L}\p{N} \t\r\n]')))::BIGINT AS pieces, sum(strlen(text))::BIGINT AS bytes, sum(length(text))::BIGINT AS chars"""


@query("corpus_stats_by_source", f"SELECT source, {_COUNTS} FROM documents GROUP BY source")
def corpus_stats_by_source(spark, d):
    return curate.corpus_stats(read_table(spark, d, "documents"))


@query(
    "corpus_token_rollup",
    r"""SELECT lang, source, sum(len(regexp_extract_all(lower(text), '[\p{L}\p{N}]+')))::BIGINT AS words, count(*) AS docs, grouping_id(lang, source)::BIGINT AS level
    FROM documents GROUP BY ROLLUP (lang, source)""",
)
def corpus_token_rollup(spark, d):
    docs = read_table(spark, d, "documents").select("lang", "source", n_tokens("text").alias("n"))
    return docs.rollup("lang", "source").agg(F.sum("n").alias("words"), F.count(F.lit(1)).alias("docs"), F.grouping_id().alias("level"))


@query("page_text_extract", f"SELECT page_id, {_html_sql()} AS text FROM pages")
def page_text_extract(spark, d):
    return read_table(spark, d, "pages").select("page_id", curate.html_to_text("html").alias("text"))


_SEED_LEX = r"""lex AS (SELECT s.term, round(ln((s.s + 1e0) / (sn + 1e0)) - ln((coalesce(g.g, 0) + 1e0) / (gn + 1e0)), 9) AS log_odds
 FROM (SELECT term, count(*) AS s FROM (SELECT unnest(regexp_extract_all(lower(text), '[\p{L}\p{N}]+')) AS term FROM benchmark) GROUP BY term) s
 LEFT JOIN (SELECT term, count(*) AS g FROM (SELECT unnest(regexp_extract_all(lower(text), '[\p{L}\p{N}]+')) AS term FROM conversations) GROUP BY term) g USING (term)
 CROSS JOIN (SELECT sum(len(regexp_extract_all(lower(text), '[\p{L}\p{N}]+'))) AS sn FROM benchmark)
 CROSS JOIN (SELECT sum(len(regexp_extract_all(lower(text), '[\p{L}\p{N}]+'))) AS gn FROM conversations)
 ORDER BY log_odds DESC, term LIMIT 200)"""


@query("seed_lexicon", f"WITH {_SEED_LEX} SELECT term, log_odds FROM lex")
def seed_lexicon(spark, d):
    return curate.seed_lexicon(read_table(spark, d, "benchmark"), read_table(spark, d, "conversations"))


@query(
    "page_domain_filter",
    f"""WITH {_SEED_LEX}, t AS (SELECT page_id, url, {_html_sql()} AS text FROM pages WHERE regexp_matches(regexp_extract(url, '^[a-z]+://[^/]+(/[^?#]*)', 1), '/[a-z]{{2}}/')),
    w AS (SELECT page_id, unnest(regexp_extract_all(lower(text), '[\\p{{L}}\\p{{N}}]+')) AS term FROM t)
    SELECT page_id, round(avg((term IN (SELECT term FROM lex))::INT), 6) AS density FROM w GROUP BY page_id HAVING avg((term IN (SELECT term FROM lex))::INT) >= 0.01""",
)
def page_domain_filter(spark, d):
    lexicon = [r["term"] for r in seed_lexicon(spark, d).collect()]  # 200 terms at most
    return curate.domain_filter(read_table(spark, d, "pages"), lexicon, 0.01).select("page_id", F.round("density", 6).alias("density"))


@query(
    "source_screen",
    r"""SELECT source, words, words >= 20000 AND source <> 'src0' AS keep FROM (SELECT source, sum(len(regexp_extract_all(lower(text), '[\p{L}\p{N}]+')))::BIGINT AS words FROM documents GROUP BY source)""",
)
def source_screen(spark, d):
    stats = curate.corpus_stats(read_table(spark, d, "documents"))
    return curate.screen_sources(stats, 20_000, [f"src{i}" for i in range(1, 20)]).select("source", "words", "keep")


@query("exact_dedup", sql("SELECT doc_id, lang, source, n_chars FROM corpus"))
def exact_dedup(spark, d):
    return dedup.exact(read_table(spark, d, "documents")).drop("text")


@query("exact_dup_clusters", "SELECT doc_id, min(doc_id) OVER (PARTITION BY text) AS keeper, count(*) OVER (PARTITION BY text) AS copies FROM documents")
def exact_dup_clusters(spark, d):
    return dedup.exact_clusters(read_table(spark, d, "documents"))


@query(
    "repeated_lines",
    """WITH l AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS pos FROM documents),
    s AS (SELECT line FROM l WHERE length(line) >= 10 GROUP BY line HAVING count(DISTINCT doc_id) >= 3)
    SELECT doc_id, md5(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (line NOT IN (SELECT line FROM s)), '')) AS text_md5, count(*) FILTER (line IN (SELECT line FROM s)) AS dropped FROM l GROUP BY doc_id""",
)
def repeated_lines(spark, d):
    out = dedup.repeated_lines(read_table(spark, d, "documents"))
    return out.select("doc_id", F.md5(F.col("text").cast("binary")).alias("text_md5"), "dropped")


#: The 5-grams of each document and how many there are.
GRAMS = dict(
    w=r"SELECT doc_id, regexp_extract_all(lower(text), '[\p{L}\p{N}]+') AS w FROM corpus",
    g="SELECT DISTINCT doc_id, g FROM (SELECT doc_id, unnest(list_transform(range(1, greatest(len(w) - 4, 1) + 1), lambda i: array_to_string(w[i:i+4], ' '))) AS g FROM w) WHERE g <> ''",
    gn="SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id",
)


@query(
    "near_dup_pairs_exact_jaccard",
    sql(
        """SELECT a, b, round(jaccard, 6) AS jaccard FROM (SELECT a, b, c / (x.n + y.n - c)::DOUBLE AS jaccard FROM
        (SELECT p.doc_id AS a, q.doc_id AS b, count(*) AS c FROM g p JOIN g q ON p.g = q.g AND p.doc_id < q.doc_id GROUP BY ALL) JOIN gn x ON a = x.doc_id JOIN gn y ON b = y.doc_id) WHERE jaccard >= 0.8""",
        **GRAMS,
    ),
)
def near_dup_pairs_exact_jaccard(spark, d):
    docs = read_table(spark, d, "documents")
    return dedup.resembling_pairs(spread_like(dedup.exact(docs), docs, "doc_id"))


@query("near_dup_minhash")
def near_dup_minhash(spark, d):
    docs = read_table(spark, d, "documents")
    return dedup.near(spread_like(dedup.exact(docs), docs, "doc_id"))


@query(
    "contamination_hits",
    sql("SELECT item_id, count(*) AS docs, min(doc_id) AS first_doc FROM benchmark JOIN corpus ON contains(corpus.text, benchmark.text) GROUP BY item_id"),
)
def contamination_hits(spark, d):
    from winnow.operators.metrics import contamination

    hits = contamination(dedup.exact(read_table(spark, d, "documents")), read_table(spark, d, "benchmark"))
    return hits.groupBy("item_id").agg(F.count(F.lit(1)).alias("docs"), F.min("doc_id").alias("first_doc"))


@query("shot_pool", sql("SELECT task, doc_id, label, rank FROM pool WHERE rank <= 50"))
def shot_pool(spark, d):
    t = tasks.labelled(read_table(spark, d, "documents"), read_table(spark, d, "labels"))
    return tasks.shot_pool(t).select("task", "doc_id", "label", "rank")


@query("unlabelled_seed", sql("SELECT task, doc_id AS seed_id, md5(text) AS text_md5 FROM pool WHERE rank > 50"))
def unlabelled_seed(spark, d):
    t = tasks.labelled(read_table(spark, d, "documents"), read_table(spark, d, "labels"))
    return tasks.unlabelled_seed(t).select("task", "seed_id", F.md5(F.col("text").cast("binary")).alias("text_md5"))


@query(
    "seed_tokens",
    sql(r"SELECT task, count(*) AS docs, sum(len(regexp_extract_all(lower(text), '[\p{L}\p{N}]+')))::BIGINT AS words FROM pool WHERE rank > 50 GROUP BY ROLLUP (task)"),
)
def seed_tokens(spark, d):
    t = tasks.labelled(read_table(spark, d, "documents"), read_table(spark, d, "labels"))
    return tasks.seed_tokens(tasks.unlabelled_seed(t))


@query(
    "few_shot_prompts",
    sql(
        """SELECT t.task, t.doc_id, md5('Decide.' || chr(10) || chr(10) || shown || chr(10) || chr(10) || 'Text: ' || t.text || chr(10) || 'Answer:') AS prompt_md5
        FROM tests t JOIN (SELECT task, test_id, string_agg('Text: ' || text || chr(10) || 'Answer: ' || label, chr(10) || chr(10) ORDER BY place) AS shown FROM shots WHERE place <= 5 GROUP BY ALL) s ON s.task = t.task AND s.test_id = t.doc_id""",
        tests="SELECT * FROM pool WHERE rank > 50",
        shots="SELECT p.task, t.doc_id AS test_id, p.text, p.label, row_number() OVER (PARTITION BY p.task, t.doc_id ORDER BY ('0x' || substr(md5(p.doc_id || '-' || t.doc_id || ':1'), 1, 13))::BIGINT, p.doc_id) AS place FROM pool p JOIN tests t ON p.task = t.task AND p.rank <= 50",
    ),
)
def few_shot_prompts(spark, d):
    ranked = tasks.ranked_pool(tasks.labelled(read_table(spark, d, "documents"), read_table(spark, d, "labels")))
    tests = ranked.where("rank > 50")
    out = tasks.build_prompts(ranked.where("rank <= 50"), tests, "Decide.")
    return out.select("task", "doc_id", F.md5(F.col("prompt").cast("binary")).alias("prompt_md5"))


@query("corpus_union_stats", f"SELECT source, {_COUNTS} FROM (SELECT text, source FROM documents UNION ALL SELECT {_html_sql()} AS text, 'crawl' AS source FROM pages) GROUP BY source")
def corpus_union_stats(spark, d):
    return curate.corpus_stats(curate.build_corpus(spark, d))


@query("vocabulary_overlap", sql(r"SELECT count(*) AS terms, count(*) FILTER (term IN (SELECT term FROM lm1)) AS known FROM (SELECT DISTINCT term FROM tok)"))
def vocabulary_overlap(spark, d):
    terms = dedup.exact(read_table(spark, d, "documents")).select(F.explode(words("text")).alias("term")).distinct()
    known = read_table(spark, d, "conversations").select(F.explode(words("text")).alias("term")).distinct().withColumn("k", F.lit(1))
    return terms.join(known, "term", "left").agg(F.count(F.lit(1)).alias("terms"), F.count("k").alias("known"))
