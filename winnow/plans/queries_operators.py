"""Generic relational operators on the given tables, one query each."""

from __future__ import annotations

import uuid

from pyspark.sql import Window
from pyspark.sql import functions as F

from winnow.functions import vectors
from winnow.functions.textops import words
from winnow.operators import lm, metrics_table, select
from winnow.plans.catalog import query
from winnow.plans.oracle import hard_body, soft_body, sql, uniform
from winnow.plans.queries_scores import corpus, general
from winnow.plans.settle import checkpoint_dir, settle
from winnow.sources import tables
from winnow.sources.tables import read_table


def t(spark, d, name):
    return read_table(spark, d, name)


@query("op_scan_pruned", "SELECT l_orderkey, l_quantity, l_shipdate FROM lineitem WHERE l_shipdate >= TIMESTAMP '1995-01-01' AND l_shipdate < TIMESTAMP '1998-01-01'")
def op_scan_pruned(spark, d):
    return t(spark, d, "lineitem").where("l_shipdate >= timestamp_ntz'1995-01-01' AND l_shipdate < timestamp_ntz'1998-01-01'").select("l_orderkey", "l_quantity", "l_shipdate")


@query(
    "op_predicates",
    "SELECT c_custkey, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal BETWEEN 0 AND 5000 THEN 'mid' ELSE 'rich' END AS band, c_nationkey IS NOT DISTINCT FROM 3 AS third FROM customer WHERE c_mktsegment IN ('BUILDING', 'MACHINERY') AND c_name LIKE 'Customer%' AND c_acctbal IS NOT NULL",
)
def op_predicates(spark, d):
    c = t(spark, d, "customer").where(F.col("c_mktsegment").isin("BUILDING", "MACHINERY") & F.col("c_name").like("Customer%") & F.col("c_acctbal").isNotNull())
    band = F.when(F.col("c_acctbal") < 0, "debt").when(F.col("c_acctbal").between(0, 5000), "mid").otherwise("rich")
    return c.select("c_custkey", band.alias("band"), F.col("c_nationkey").eqNullSafe(3).alias("third"))


_OC = "SELECT o_orderkey, c_custkey, c_mktsegment FROM orders JOIN customer ON o_custkey = c_custkey"


def _orders_customer(hint):
    def run(spark, d):
        c = t(spark, d, "customer")
        c = F.broadcast(c) if hint == "broadcast" else c.hint(hint)  # the customer table's size is known here
        return t(spark, d, "orders").join(c, F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_custkey", "c_mktsegment")

    return run


for _name, _hint in (("broadcast", "broadcast"), ("merge", "merge"), ("shuffle_hash", "shuffle_hash")):
    query(f"op_join_{_name}", _OC)(_orders_customer(_hint))


@query("op_join_left_default", sql("SELECT term, coalesce(c, 0) AS c FROM (SELECT DISTINCT term FROM tok) LEFT JOIN lm1 USING (term)"))
def op_join_left_default(spark, d):
    terms = corpus(spark, d).select(F.explode(words("text")).alias("term")).distinct()
    return terms.join(lm.unigram_counts(general(spark, d)), "term", "left").select("term", F.coalesce("c", F.lit(0)).alias("c"))


@query("op_join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def op_join_semi(spark, d):
    return t(spark, d, "customer").join(t(spark, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@query("op_join_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def op_join_anti(spark, d):
    return t(spark, d, "customer").join(t(spark, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@query("op_join_full", sql("SELECT coalesce(h.doc_id, s.doc_id) AS doc_id, CASE WHEN h.doc_id IS NULL THEN 'soft' WHEN s.doc_id IS NULL THEN 'hard' ELSE 'both' END AS side FROM h FULL JOIN s ON h.doc_id = s.doc_id", h=hard_body("entropy"), s=soft_body("q_entropy", "quant")))
def op_join_full(spark, d):
    m = metrics_table.standard(spark, d)
    h = select.choose(m, "diversity", "hard", 0.1).select("doc_id", F.lit(1).alias("h"))
    s = select.choose(m, "diversity", "soft", 0.1).select("doc_id", F.lit(1).alias("s"))
    side = F.when(F.col("h").isNull(), "soft").when(F.col("s").isNull(), "hard").otherwise("both")
    return h.join(s, "doc_id", "full_outer").select("doc_id", side.alias("side"))


@query("op_join_cross", "SELECT conv_id, candidate FROM (SELECT conv_id FROM conversations WHERE turn = 0) CROSS JOIN (SELECT unnest(range(0, 4))::INT AS candidate)")
def op_join_cross(spark, d):
    four = spark.range(4).select(F.col("id").cast("int").alias("candidate"))
    return t(spark, d, "conversations").where("turn = 0").select("conv_id").crossJoin(F.broadcast(four))


@query("op_join_theta", "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_name < b.n_name")
def op_join_theta(spark, d):
    n = t(spark, d, "nation")
    a, b = n.alias("a"), n.alias("b")
    return a.join(b, (F.col("a.n_regionkey") == F.col("b.n_regionkey")) & (F.col("a.n_name") < F.col("b.n_name"))).select(F.col("a.n_nationkey").alias("a"), F.col("b.n_nationkey").alias("b"))


@query("op_join_range", "SELECT o_orderkey, lo FROM orders JOIN (SELECT unnest(range(0, 500000, 50000)) AS lo) ON o_totalprice >= lo AND o_totalprice < lo + 50000")
def op_join_range(spark, d):
    """Value in interval: intervals are keyed by bin, so the join has an equality and doesn't compare all pairs."""
    cuts = spark.range(0, 500_000, 50_000).select(F.col("id").alias("lo"), F.floor(F.col("id") / 50_000).alias("bin"))
    o = t(spark, d, "orders").select("o_orderkey", "o_totalprice", F.floor(F.col("o_totalprice") / 50_000).alias("bin"))
    return o.join(F.broadcast(cuts), "bin").where("o_totalprice >= lo AND o_totalprice < lo + 50000").select("o_orderkey", "lo")


@query("op_join_interval", "SELECT l_orderkey, l_linenumber FROM lineitem JOIN orders ON l_orderkey = o_orderkey AND l_shipdate >= o_orderdate AND l_shipdate <= o_orderdate + INTERVAL 30 DAY")
def op_join_interval(spark, d):
    soon = F.col("l_shipdate").between(F.col("o_orderdate"), F.col("o_orderdate") + F.expr("INTERVAL 30 DAY"))
    return t(spark, d, "lineitem").join(t(spark, d, "orders"), (F.col("l_orderkey") == F.col("o_orderkey")) & soon).select("l_orderkey", "l_linenumber")


@query(
    "op_join_asof",
    "SELECT p.event_id, max_by(v.event_id, (v.ts, v.event_id)) AS last_view FROM events p LEFT JOIN events v ON v.user_id = p.user_id AND v.event_type = 'view' AND (v.ts, v.event_id) <= (p.ts, p.event_id) WHERE p.event_type = 'purchase' GROUP BY p.event_id",
)
def op_join_asof(spark, d):
    """Latest view at or before each purchase of the user: one window with a forward fill instead of a range join."""
    e = t(spark, d, "events").where("event_type IN ('view', 'purchase')").select("event_id", "user_id", "ts", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    seen = e.withColumn("last_view", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(w))
    return seen.where("event_type = 'purchase'").select("event_id", "last_view")


@query(
    "op_join_star",
    "SELECT r_name, year(o_orderdate)::INT AS year, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL",
)
def op_join_star(spark, d):
    n = t(spark, d, "nation").join(t(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "r_name")
    j = t(spark, d, "lineitem").join(t(spark, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(t(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey"))
    return j.join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("r_name", F.year("o_orderdate").alias("year")).agg(F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"))


@query(
    "op_join_self_band",
    sql(
        "SELECT a.doc_id, count(DISTINCT a.g) AS shared, count(*) AS meetings, min(b.doc_id) AS first_partner FROM g8 a JOIN g8 b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY a.doc_id",
        w8=f"SELECT doc_id, regexp_extract_all(lower(text), '[\\p{{L}}\\p{{N}}]+') AS w FROM corpus",
        g8="SELECT DISTINCT doc_id, g FROM (SELECT doc_id, unnest(list_transform(range(1, len(w) - 6), lambda i: array_to_string(w[i:i+7], ' '))) AS g FROM w8 WHERE len(w) >= 8)",
    ),
)
def op_join_self_band(spark, d):
    """Documents joined with themselves on the 8-grams they share, one row per document: how many of its grams others hold, how often it meets others on them, and the smallest document met.

    The count is pushed below the join: a gram's holders are counted and their two smallest found before documents meet it, so
    a gram that a third of the documents hold gives one row per holder, not one per pair.
    """
    from winnow.operators.dedup import gram_sets

    g = settle(gram_sets(corpus(spark, d), 8, least=8).select("doc_id", F.explode("grams").alias("g")))
    held = g.groupBy("g").agg(F.count(F.lit(1)).alias("n"), F.min("doc_id").alias("least")).where("n > 1")
    met = settle(g.join(held, "g"))
    second = met.where("doc_id <> least").groupBy(F.col("g").alias("_g")).agg(F.min("doc_id").alias("next"))
    own = met.join(second, F.col("g") == F.col("_g"))
    return own.groupBy("doc_id").agg(F.count(F.lit(1)).alias("shared"), F.sum(F.col("n") - 1).alias("meetings"), F.min(F.when(F.col("doc_id") == F.col("least"), F.col("next")).otherwise(F.col("least"))).alias("first_partner"))


@query("op_agg_basic", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty, round(avg(l_extendedprice), 4) AS price, min(l_discount) AS lo, max(l_tax) AS hi FROM lineitem GROUP BY ALL")
def op_agg_basic(spark, d):
    return t(spark, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.avg("l_extendedprice"), 4).alias("price"), F.min("l_discount").alias("lo"), F.max("l_tax").alias("hi"))


@query("op_agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY event_type")
def op_agg_distinct(spark, d):
    return t(spark, d, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"))


@query("op_agg_filter", "SELECT user_id, count(*) FILTER (event_type = 'view') AS views, count(*) FILTER (value > 50) AS large, bool_and(value >= 0) AS all_pos, bool_or(event_type = 'purchase') AS bought FROM events GROUP BY user_id")
def op_agg_filter(spark, d):
    t(spark, d, "events").createOrReplaceTempView("_winnow_events")
    return spark.sql("SELECT user_id, count(*) FILTER (WHERE event_type = 'view') AS views, count(*) FILTER (WHERE value > 50) AS large, bool_and(value >= 0) AS all_pos, bool_or(event_type = 'purchase') AS bought FROM _winnow_events GROUP BY user_id")


_LQ = "(SELECT d.lang, d.source, l.quality FROM documents d JOIN labels l USING (doc_id))"


def _lq(spark, d):
    return t(spark, d, "documents").select("doc_id", "lang", "source").join(t(spark, d, "labels"), "doc_id").select("lang", "source", "quality")


@query("op_agg_grouping_sets", f"SELECT lang, quality, count(*) AS n, grouping_id(lang, quality)::BIGINT AS level FROM {_LQ} GROUP BY GROUPING SETS ((lang, quality), (lang), ())")
def op_agg_grouping_sets(spark, d):
    return _lq(spark, d).groupingSets([["lang", "quality"], ["lang"], []], "lang", "quality").agg(F.count(F.lit(1)).alias("n"), F.grouping_id("lang", "quality").alias("level"))


@query("op_agg_rollup", f"SELECT lang, source, count(*) AS n FROM {_LQ} GROUP BY ROLLUP (lang, source)")
def op_agg_rollup(spark, d):
    return _lq(spark, d).rollup("lang", "source").agg(F.count(F.lit(1)).alias("n"))


@query("op_agg_cube", f"SELECT lang, source, quality, count(*) AS n, grouping_id(lang, source, quality)::BIGINT AS level FROM {_LQ} GROUP BY CUBE (lang, source, quality)")
def op_agg_cube(spark, d):
    return _lq(spark, d).cube("lang", "source", "quality").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().alias("level"))


@query("op_agg_stats", "SELECT l_returnflag, round(stddev_samp(l_quantity), 6) AS sd, round(var_pop(l_quantity), 6) AS v, round(corr(l_quantity, l_extendedprice), 6) AS r, round(covar_samp(l_quantity, l_discount), 6) AS cv FROM lineitem GROUP BY l_returnflag")
def op_agg_stats(spark, d):
    return t(spark, d, "lineitem").groupBy("l_returnflag").agg(F.round(F.stddev_samp("l_quantity"), 6).alias("sd"), F.round(F.var_pop("l_quantity"), 6).alias("v"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r"), F.round(F.covar_samp("l_quantity", "l_discount"), 6).alias("cv"))


@query("op_agg_percentile", "SELECT lang, quantile_cont(n_chars, 0.25) AS q1, median(n_chars) AS q2, quantile_cont(n_chars, 0.75) AS q3 FROM documents GROUP BY lang")
def op_agg_percentile(spark, d):
    return t(spark, d, "documents").groupBy("lang").agg(F.percentile("n_chars", 0.25).alias("q1"), F.median("n_chars").alias("q2"), F.percentile("n_chars", 0.75).alias("q3"))


@query("op_agg_maxby", "SELECT source, max_by(doc_id, (n_chars, doc_id)) AS longest, min_by(doc_id, (n_chars, doc_id)) AS shortest FROM documents GROUP BY source")
def op_agg_maxby(spark, d):
    key = F.struct("n_chars", "doc_id")
    return t(spark, d, "documents").groupBy("source").agg(F.max_by("doc_id", key).alias("longest"), F.min_by("doc_id", key).alias("shortest"))


@query("op_agg_mode", "SELECT user_id, min(event_type) AS event_type FROM (SELECT user_id, event_type, rank() OVER (PARTITION BY user_id ORDER BY count(*) DESC) AS r FROM events GROUP BY user_id, event_type) WHERE r = 1 GROUP BY user_id")
def op_agg_mode(spark, d):
    return t(spark, d, "events").groupBy("user_id").agg(F.mode("event_type", True).alias("event_type"))


@query("op_agg_collect", "SELECT user_id, string_agg(DISTINCT event_type, ',' ORDER BY event_type) AS kinds FROM events GROUP BY user_id")
def op_agg_collect(spark, d):
    return t(spark, d, "events").groupBy("user_id").agg(F.array_join(F.array_sort(F.collect_set("event_type")), ",").alias("kinds"))


@query("op_agg_sketches")
def op_agg_sketches(spark, d):
    """Vocabulary size by HyperLogLog and theta sketch, length quartiles by KLL, heavy terms by top-k and count-min."""
    terms = corpus(spark, d).select(F.explode(words("text")).alias("term"))
    a = terms.agg(F.approx_count_distinct("term").alias("hll"), F.hll_sketch_estimate(F.hll_sketch_agg("term")).alias("hll_sketch"), F.theta_sketch_estimate(F.theta_sketch_agg("term")).alias("theta"), F.expr("approx_top_k(term, 5)").alias("top"), F.length(F.expr("count_min_sketch(term, 0.01d, 0.95d, 7)")).alias("cms_bytes"))
    k = corpus(spark, d).agg(F.kll_sketch_get_quantile_bigint(F.kll_sketch_agg_bigint("n_chars"), F.lit(0.5)).alias("median_chars"))
    return a.crossJoin(k)


@query("op_pivot", "SELECT source, count(*) FILTER (lang = 'en') AS en, count(*) FILTER (lang = 'fr') AS fr, count(*) FILTER (lang = 'de') AS de, count(*) FILTER (lang = 'es') AS es FROM documents GROUP BY source")
def op_pivot(spark, d):
    return t(spark, d, "documents").groupBy("source").pivot("lang", ["en", "fr", "de", "es"]).count().na.fill(0)


@query("op_unpivot", "SELECT doc_id, 'quality' AS task, quality AS label FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels")
def op_unpivot(spark, d):
    return t(spark, d, "labels").unpivot(["doc_id"], ["quality", "toxic"], "task", "label")


_S = "(PARTITION BY source ORDER BY n_chars DESC, doc_id)"


@query("op_win_rank", f"SELECT doc_id, row_number() OVER {_S}::INT AS rn, rank() OVER (PARTITION BY source ORDER BY n_chars)::INT AS rk, dense_rank() OVER (PARTITION BY source ORDER BY n_chars)::INT AS dr FROM documents")
def op_win_rank(spark, d):
    w = Window.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id")
    v = Window.partitionBy("source").orderBy("n_chars")
    return t(spark, d, "documents").select("doc_id", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"))


@query("op_win_ntile", f"SELECT doc_id, ntile(10) OVER {_S}::INT AS tile FROM documents")
def op_win_ntile(spark, d):
    return t(spark, d, "documents").select("doc_id", F.ntile(10).over(Window.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id")).alias("tile"))


@query("op_win_cume", "SELECT doc_id, round(cume_dist() OVER w, 6) AS cd, round(percent_rank() OVER w, 6) AS pr FROM documents WINDOW w AS (PARTITION BY source ORDER BY n_chars)")
def op_win_cume(spark, d):
    w = Window.partitionBy("source").orderBy("n_chars")
    return t(spark, d, "documents").select("doc_id", F.round(F.cume_dist().over(w), 6).alias("cd"), F.round(F.percent_rank().over(w), 6).alias("pr"))


@query("op_win_lag", "SELECT conv_id, turn, lag(role) OVER (PARTITION BY conv_id ORDER BY turn) AS before, nth_value(role, 2) OVER (PARTITION BY conv_id ORDER BY turn) AS second FROM conversations")
def op_win_lag(spark, d):
    w = Window.partitionBy("conv_id").orderBy("turn")
    return t(spark, d, "conversations").select("conv_id", "turn", F.lag("role").over(w).alias("before"), F.nth_value("role", 2).over(w).alias("second"))


@query("op_win_lead", "SELECT conv_id, turn, md5(lead(text) OVER (PARTITION BY conv_id ORDER BY turn)) AS next FROM conversations")
def op_win_lead(spark, d):
    w = Window.partitionBy("conv_id").orderBy("turn")
    return t(spark, d, "conversations").select("conv_id", "turn", F.md5(F.lead("text").over(w).cast("binary")).alias("next"))


@query("op_win_running", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING), 4) AS total FROM events")
def op_win_running(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return t(spark, d, "events").select("event_id", F.round(F.sum("value").over(w), 4).alias("total"))


@query("op_win_sliding", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND 3 FOLLOWING), 4) AS mean7 FROM events")
def op_win_sliding(spark, d):
    return t(spark, d, "events").select("event_id", F.round(F.avg("value").over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-3, 3)), 4).alias("mean7"))


@query("op_win_range", "SELECT doc_id, count(*) OVER (PARTITION BY lang ORDER BY n_chars RANGE BETWEEN 100 PRECEDING AND 100 FOLLOWING) AS near FROM documents")
def op_win_range(spark, d):
    return t(spark, d, "documents").select("doc_id", F.count(F.lit(1)).over(Window.partitionBy("lang").orderBy("n_chars").rangeBetween(-100, 100)).alias("near"))


@query("op_win_last_ignore_nulls", "SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS last_buy FROM events")
def op_win_last_ignore_nulls(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return t(spark, d, "events").select("event_id", F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w).alias("last_buy"))


@query("op_topk_global", "SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 10")
def op_topk_global(spark, d):
    return t(spark, d, "documents").select("doc_id", "n_chars").orderBy(F.desc("n_chars"), "doc_id").limit(10)


@query("op_topk_group", "SELECT lang, doc_id FROM (SELECT lang, doc_id, row_number() OVER (PARTITION BY lang ORDER BY n_chars DESC, doc_id) AS r FROM documents) WHERE r <= 3")
def op_topk_group(spark, d):
    w = Window.partitionBy("lang").orderBy(F.desc("n_chars"), "doc_id")
    return t(spark, d, "documents").select("lang", "doc_id", F.row_number().over(w).alias("r")).where("r <= 3").select("lang", "doc_id")


@query("op_offset", "SELECT doc_id FROM documents ORDER BY n_chars DESC, doc_id LIMIT 10 OFFSET 10")
def op_offset(spark, d):
    return t(spark, d, "documents").orderBy(F.desc("n_chars"), "doc_id").select("doc_id").offset(10).limit(10)


_LONG, _EN = "SELECT source, lang FROM documents WHERE n_chars > 2000", "SELECT source, lang FROM documents WHERE lang = 'en'"


def _sets(spark, d):
    docs = t(spark, d, "documents")
    return docs.where("n_chars > 2000").select("source", "lang"), docs.where("lang = 'en'").select("source", "lang")


for _name, _op, _kind in (("op_union", "unionByName", "UNION ALL"), ("op_intersect", "intersect", "INTERSECT"), ("op_intersect_all", "intersectAll", "INTERSECT ALL"), ("op_except", "subtract", "EXCEPT"), ("op_except_all", "exceptAll", "EXCEPT ALL")):

    def _run(spark, d, op=_op):
        a, b = _sets(spark, d)
        return getattr(a, op)(b)

    query(_name, f"{_LONG} {_kind} {_EN}")(_run)


@query("op_distinct", "SELECT DISTINCT source, lang FROM documents")
def op_distinct(spark, d):
    return t(spark, d, "documents").select("source", "lang").distinct()


@query(
    "op_string_fns",
    """SELECT doc_id, upper(source) AS a, md5(text) AS b, sha256(text) AS c, instr(text, 'e')::INT AS e, replace(substr(text, 1, 30), 'a', '_') AS f, contains(text, 'the') AS g, starts_with(text, 'T') AS h,
    reverse(substr(text, 1, 5)) AS i, repeat(lang, 2) AS j, concat_ws('-', lang, source) AS k, levenshtein(lang, source)::INT AS l, trim(substr(text, 1, 3)) AS m, translate(source, 'src', 'SRC') AS n, regexp_extract(source, '([0-9]+)', 1) AS o FROM documents""",
)
def op_string_fns(spark, d):
    x = F.col("text")
    return t(spark, d, "documents").select(
        "doc_id", F.upper("source").alias("a"), F.md5(x.cast("binary")).alias("b"), F.sha2(x.cast("binary"), 256).alias("c"), F.instr(x, "e").alias("e"), F.replace(F.substring(x, 1, 30), F.lit("a"), F.lit("_")).alias("f"),
        F.contains(x, F.lit("the")).alias("g"), x.startswith("T").alias("h"), F.reverse(F.substring(x, 1, 5)).alias("i"), F.repeat("lang", 2).alias("j"), F.concat_ws("-", "lang", "source").alias("k"),
        F.levenshtein("lang", "source").alias("l"), F.trim(F.substring(x, 1, 3)).alias("m"), F.translate("source", "src", "SRC").alias("n"), F.regexp_extract("source", "([0-9]+)", 1).alias("o"),
    )


@query(
    "op_math_fns",
    "SELECT l_orderkey, l_linenumber, round(ln(l_quantity), 6) AS a, round(sqrt(l_extendedprice), 6) AS b, floor(l_extendedprice)::BIGINT AS c, ceil(l_extendedprice)::BIGINT AS e, greatest(l_discount, l_tax) AS f, abs(l_discount - 0.05e0) AS g, l_orderkey % 7 AS h, sign(l_tax)::DOUBLE AS i, round(pow(l_discount, 2e0), 9) AS j, round(exp(l_tax), 6) AS k, round(log2(l_quantity), 6) AS l FROM lineitem",
)
def op_math_fns(spark, d):
    q, p, x, y = (F.col(c) for c in ("l_quantity", "l_extendedprice", "l_discount", "l_tax"))
    return t(spark, d, "lineitem").select(
        "l_orderkey", "l_linenumber", F.round(F.log(q), 6).alias("a"), F.round(F.sqrt(p), 6).alias("b"), F.floor(p).alias("c"), F.ceil(p).alias("e"), F.greatest(x, y).alias("f"), F.abs(x - 0.05).alias("g"), F.pmod("l_orderkey", F.lit(7)).alias("h"),
        F.signum(y).alias("i"), F.round(F.pow(x, F.lit(2.0)), 9).alias("j"), F.round(F.exp(y), 6).alias("k"), F.round(F.log2(q), 6).alias("l"),
    )


@query(
    "op_array_fns",
    """SELECT vec_id, round(list_max(e), 6) AS hi, round(list_min(e), 6) AS lo, len(list_filter(e, lambda x: x > 0)) ::INT AS pos, round(list_sum(list_transform(e, lambda x: x * x)), 6) AS sq, round(e[1], 6) AS first, len(e[2:5])::INT AS four, list_contains(e, 0e0) AS zero FROM (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings)""",
)
def op_array_fns(spark, d):
    e = F.col("embedding").cast("array<double>")
    return t(spark, d, "embeddings").select(
        "vec_id", F.round(F.array_max(e), 6).alias("hi"), F.round(F.array_min(e), 6).alias("lo"), F.size(F.filter(e, lambda x: x > 0)).alias("pos"), F.round(F.aggregate(F.transform(e, lambda x: x * x), F.lit(0.0), lambda s, x: s + x), 6).alias("sq"),
        F.round(F.element_at(e, 1), 6).alias("first"), F.size(F.slice(e, 2, 4)).alias("four"), F.array_contains(e, F.lit(0.0)).alias("zero"),
    )


@query("op_map_fns", sql("SELECT doc_id, count(*)::INT AS kinds, max(n)::BIGINT AS top, coalesce(sum(n) FILTER (tok_type = 'DET'), 0)::BIGINT AS dets FROM typed GROUP BY doc_id"))
def op_map_fns(spark, d):
    from winnow.operators.diversity import type_counts

    m = type_counts(corpus(spark, d)).groupBy("doc_id").agg(F.map_from_entries(F.collect_list(F.struct("tok_type", "n"))).alias("m"))
    return m.select("doc_id", F.size(F.map_keys("m")).alias("kinds"), F.array_max(F.map_values("m")).alias("top"), F.coalesce(F.try_element_at("m", F.lit("DET")), F.lit(0)).cast("long").alias("dets"))


@query("op_json_fns", "SELECT event_id, json_extract_string(props, '$.' || (json_keys(props))[1]) AS first_value, len(json_keys(props))::INT AS keys FROM events WHERE props IS NOT NULL")
def op_json_fns(spark, d):
    e = t(spark, d, "events").where("props IS NOT NULL").select("event_id", "props", F.json_object_keys("props").alias("k"))
    v = F.parse_json("props")
    as_map = F.from_json("props", "map<string,string>")
    return e.select("event_id", F.when(F.is_variant_null(v), None).otherwise(F.try_element_at(as_map, F.col("k")[0])).alias("first_value"), F.size("k").alias("keys"))


@query("op_date_fns", "SELECT o_orderkey, date_trunc('month', o_orderdate)::TIMESTAMP AS m, year(o_orderdate)::INT AS y, date_diff('day', TIMESTAMP '1992-01-01', o_orderdate)::INT AS days, (o_orderdate + INTERVAL 1 MONTH)::DATE AS later, dayofweek(o_orderdate)::INT + 1 AS dow FROM orders")
def op_date_fns(spark, d):
    o = F.col("o_orderdate")
    return t(spark, d, "orders").select("o_orderkey", F.date_trunc("month", o).cast("timestamp_ntz").alias("m"), F.year(o).alias("y"), F.datediff(o, F.lit("1992-01-01").cast("date")).alias("days"), F.add_months(o, 1).alias("later"), F.dayofweek(o).alias("dow"))


@query(
    "op_vector_fns",
    "SELECT a.vec_id, round(list_dot_product(a.e, b.e), 6) AS dot, round(sqrt(list_dot_product(a.e, a.e)), 6) AS norm, round(list_cosine_similarity(a.e, b.e), 6) AS cosine, round(list_distance(a.e, b.e), 6) AS l2 FROM (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings) a CROSS JOIN (SELECT embedding::DOUBLE[] AS e FROM embeddings WHERE vec_id = 0) b",
)
def op_vector_fns(spark, d):
    e = t(spark, d, "embeddings").select("vec_id", "embedding")
    one = F.broadcast(e.where("vec_id = 0").select(F.col("embedding").alias("o")))  # one row
    return e.crossJoin(one).select("vec_id", F.round(vectors.dot("embedding", "o"), 6).alias("dot"), F.round(vectors.norm("embedding"), 6).alias("norm"), F.round(vectors.cosine("embedding", "o"), 6).alias("cosine"), F.round(vectors.l2("embedding", "o"), 6).alias("l2"))


@query("op_window_tumbling", "SELECT time_bucket(INTERVAL 1 DAY, ts) AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
def op_window_tumbling(spark, d):
    return t(spark, d, "events").groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


@query("op_window_sliding", "SELECT start, count(*) AS n FROM (SELECT time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 6 HOUR * k AS start FROM events CROSS JOIN (SELECT unnest(range(0, 4)) AS k)) GROUP BY start")
def op_window_sliding(spark, d):
    return t(spark, d, "events").groupBy(F.window("ts", "1 day", "6 hours").alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "n")


@query(
    "op_window_session",
    "SELECT user_id, min(ts) AS start, count(*) AS n FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s FROM (SELECT *, (ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) > INTERVAL 30 MINUTE OR lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) IS NULL)::INT AS new FROM events)) GROUP BY user_id, s",
)
def op_window_session(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    new = F.lag("ts").over(w).isNull() | (F.col("ts") - F.lag("ts").over(w) > F.expr("INTERVAL '30' MINUTE"))
    e = t(spark, d, "events").withColumn("new", new.cast("int")).withColumn("s", F.sum("new").over(w.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    return e.groupBy("user_id", "s").agg(F.min("ts").alias("start"), F.count(F.lit(1)).alias("n")).drop("s")


@query("op_udf_grouped_mean", "SELECT label, i::INT AS i, round(avg(embedding[i + 1]::DOUBLE), 5) AS mean FROM embeddings, range(0, 64) t(i) GROUP BY ALL")
def op_udf_grouped_mean(spark, d):
    from winnow.functions.udfs import mean_vector

    m = t(spark, d, "embeddings").groupBy("label").agg(mean_vector("embedding").alias("m"))
    return m.select("label", F.posexplode("m").alias("i", "mean")).select("label", "i", F.round("mean", 5).alias("mean"))


@query("io_lines", "SELECT doc_id, md5(text) AS text_md5, lang, source, n_chars FROM documents")
def io_lines(spark, d):
    """Documents written as JSON lines and read back by the strict reader with its declared schema."""
    folder = f"{checkpoint_dir(spark)}/lines-{uuid.uuid4().hex}"
    t(spark, d, "documents").write.json(folder)
    return tables.read_lines(spark, folder, tables.SCHEMAS["documents"]).select("doc_id", F.md5(F.col("text").cast("binary")).alias("text_md5"), "lang", "source", "n_chars")


@query("op_udf_arrow", "SELECT doc_id, length(text)::BIGINT AS n FROM documents")
def op_udf_arrow(spark, d):
    from winnow.functions.udfs import code_points

    return t(spark, d, "documents").select("doc_id", code_points("text").alias("n"))


@query("op_udtf_chunks", sql("SELECT doc_id, ((pos - 1) // 64)::INT AS chunk_no, count(*)::INT AS n_tokens FROM postok GROUP BY ALL"))
def op_udtf_chunks(spark, d):
    from winnow.functions.udfs import chunks

    return chunks(corpus(spark, d), 64).select("doc_id", "chunk_no", "n_tokens")


@query("op_grouped_map", "SELECT lang, count(*) AS n, round(avg(n_chars), 6) AS mean FROM documents GROUP BY lang")
def op_grouped_map(spark, d):
    """Pre-aggregated by partition, so a group reaches Python as a few rows however large it is."""
    import pandas as pd

    part = t(spark, d, "documents").groupBy("lang", F.spark_partition_id().alias("p")).agg(F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("s"))

    def merged(pdf):
        return pd.DataFrame({"lang": pdf["lang"][:1], "n": [pdf["n"].sum()], "mean": [round(pdf["s"].sum() / pdf["n"].sum(), 6)]})

    return part.groupBy("lang").applyInPandas(merged, "lang string, n long, mean double")


@query("sql_functions", sql("SELECT doc_id, round(entropy, 6) AS entropy FROM ent"))
def sql_functions(spark, d):
    """The SQL entry: registered functions over a view."""
    from winnow.functions.udfs import register

    register(spark)
    corpus(spark, d).createOrReplaceTempView("_winnow_corpus")
    return spark.sql("SELECT doc_id, round(round(type_entropy(text), 9), 6) AS entropy FROM _winnow_corpus")


def _roundtrip(kind):
    def run(spark, d):
        docs = t(spark, d, "documents")
        path = f"{checkpoint_dir(spark)}/roundtrip-{kind}"
        tables.write_as(docs, path, kind)
        back = tables.read_as(spark, path, kind, tables.SCHEMAS["documents"])
        return back.select("doc_id", F.md5(F.col("text").cast("binary")).alias("text_md5"), "lang", "source", "n_chars")

    return run


for _kind in tables.FORMATS:
    query(f"io_roundtrip_{_kind}", "SELECT doc_id, md5(text) AS text_md5, lang, source, n_chars FROM documents")(_roundtrip(_kind))


@query(
    "io_shards",
    sql(
        f"SELECT least(floor({uniform('doc_id', 7)} * n), n - 1)::INT AS shard, count(*) AS docs, sum(n_tokens)::BIGINT AS tokens FROM sized CROSS JOIN (SELECT greatest(1, ceil(sum(n_tokens) / 50000e0)) AS n FROM sized) GROUP BY shard",
        sized="SELECT doc_id, coalesce(n_tokens, 0) AS n_tokens FROM (SELECT doc_id FROM corpus) LEFT JOIN len USING (doc_id)",
    ),
)
def io_shards(spark, d):
    from winnow.functions.textops import n_tokens

    docs = corpus(spark, d).withColumn("n_tokens", n_tokens("text"))
    return tables.write_shards(docs, f"{checkpoint_dir(spark)}/shards", 50_000)


@query("recipe_run", sql("SELECT doc_id, n_tokens FROM c", c=hard_body("similarity")))
def recipe_run(spark, d):
    from winnow.plans.spec import SelectionSpec, run

    seed = t(spark, d, "benchmark").select(F.lit("benchmark").alias("task"), F.col("item_id").alias("seed_id"), "text")
    return run(spark, SelectionSpec(), t(spark, d, "documents"), seed, general(spark, d))
