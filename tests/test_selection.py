import math
import random

import pytest
from pyspark.sql import functions as F

from winnow.functions.textops import hash_uniform
from winnow.operators import baselines, lm, metrics_table, quantiles, select, similarity
from winnow.operators.ranking import ranked, running_total
from winnow.plans import spec
from winnow.plans.settle import settle
from winnow.sources import tables
from winnow.sources.tables import read_table

DOCS = [(1, "bank loan bank rate"), (2, "rate rises"), (3, "tree tree leaf"), (4, "loan")]
BASE = [("bank", 2), ("rate", 1), ("tree", 4), ("leaf", 1)]


@pytest.fixture(scope="module")
def table(spark, sf):
    return settle(metrics_table.standard(spark, sf))


def base_model(spark):
    return lm.Model(spark.createDataFrame(BASE, "term string, c long"), None, 8, 4)


def tiny(spark):
    docs = spark.createDataFrame(DOCS, "doc_id long, text string")
    seed = spark.createDataFrame([(0, "bank loan")], "seed_id long, text string")
    return settle(metrics_table.score_all(docs, similarity.centroid(seed), base_model(spark)))


def test_hand_checked_scores(spark):
    m = {r.doc_id: r for r in quantiles.normalise(tiny(spark), "similarity").collect()}
    assert [m[i].n_tokens for i in (1, 2, 3, 4)] == [4, 2, 3, 1]
    assert [round(m[i].perplexity, 6) for i in (1, 2, 3, 4)] == [6.311393, 9.192388, 3.528743, 13.0]
    assert [round(m[i].similarity, 6) for i in (1, 2, 3, 4)] == [0.866025, 0.0, 0.0, 0.707107]
    assert [m[i].q_similarity for i in (1, 2, 3, 4)] == [1.0, 0.5, 0.5, 0.75]


def test_hand_checked_choices(spark):
    m = tiny(spark)
    ids = lambda df: {r.doc_id for r in df.collect()}
    assert ids(select.choose(m, "task_similar", "hard", 0.5)) == {1, 4}
    soft = select.choose(m, "task_similar", "soft", 0.5)
    assert [round(r.rank_key, 6) for r in soft.orderBy("rank_key").collect()] == [0.150622, 0.20452]
    assert ids(soft) == {2, 4}
    assert round(spark.range(1).select(hash_uniform("id", 7)).first()[0], 13) == 0.5269208679749


@pytest.mark.parametrize("texts,want", [("a b", 0.0), ("12 a", math.log(2)), ("12 a . of", math.log(4))])
def test_entropy_of_known_shares(spark, texts, want):
    from winnow.operators.diversity import with_entropy

    df = spark.createDataFrame([(1, texts.replace("a", "xyzzyx").replace("b", "qwfpgj"))], "doc_id long, text string")
    for native in (False, True):
        assert abs(with_entropy(df, native=native).first()["entropy"] - want) < 1e-12


def test_arrow_and_native_entropy_agree(spark, sf):
    from winnow.operators.diversity import with_entropy

    docs = read_table(spark, sf, "documents")
    a, b = (with_entropy(docs, native=n).select("doc_id", F.col("entropy").alias(f"e{n}")) for n in (True, False))
    assert a.join(b, "doc_id").where("abs(eTrue - eFalse) > 1e-9").count() == 0


def plain_cut(rows, limit, overshoot):
    """(cum, n) of the ranking's prefix, from rows (score, key, n)."""
    total, out = 0, []
    for s, k, n in sorted(rows, key=lambda r: (-round(r[0], 9), r[1] is not None, r[1] if r[1] is not None else 0, r[2] or 0)):
        if (total + (n or 0) > limit) if overshoot == "exclude" else (total >= limit):
            break
        total += n or 0
        out.append((k, n, total))
    return out


@pytest.mark.parametrize("overshoot", ["exclude", "include"])
def test_the_cut_of_odd_rows_against_brute_force(spark, overshoot):
    """Repeated ids and rows, null ids, ties, null scores and tokens, clashing columns, cut at many budgets."""
    rng = random.Random(3)
    rows = [(rng.choice([0.5, 0.25, 1.0, rng.random()]), rng.choice([None, 1, 2, rng.randrange(50)]), rng.choice([None, 0, 1, 7])) for _ in range(300)]
    df = spark.createDataFrame([(s, k, n, "x", 1) for s, k, n in rows] + [(None, 3, 4, "x", 1), (float("nan"), 3, 4, "x", 1)], "s double, doc_id long, n_tokens long, _rt_at string, cum_tokens int").repartition(7)
    for limit in (0, 1, 13, 250, 10_000):
        got = select.hard(df, "s", limit, overshoot=overshoot)
        assert got.columns == ["s", "doc_id", "n_tokens", "_rt_at", "cum_tokens"]
        have = sorted(((r.doc_id, r.n_tokens, r.cum_tokens) for r in got.collect()), key=str)
        assert have == sorted(plain_cut(rows, limit, overshoot), key=str)


def test_the_cut_of_equal_scores_strings_and_nothing(spark):
    df = spark.range(100).select(F.concat(F.lit("d"), F.lpad(F.col("id").cast("string"), 3, "0")).alias("doc_id"), F.lit(1.0).alias("s"), F.lit(3).cast("long").alias("n_tokens"))
    for limit in (0, 2, 50, 149, 300, 1000):
        assert sorted(r.doc_id for r in select.hard(df, "s", limit).collect()) == [f"d{i:03d}" for i in range(min(100, limit // 3))]
    assert select.hard(df.limit(0), "s", 10).collect() == []
    same = spark.range(50).select(F.lit(1).alias("doc_id"), F.lit(1.0).alias("s"), F.lit(2).cast("long").alias("n_tokens"))
    assert sorted(r.cum_tokens for r in select.hard(same, "s", 21).collect()) == list(range(2, 21, 2))


def test_budget_is_kept_and_the_next_breaks_it(spark, table):
    limit = select.budget(table, 0.1)
    chosen = select.choose(table, "diversity", "hard", 0.1)
    ids = [r.doc_id for r in chosen.collect()]
    used = chosen.agg(F.sum("n_tokens")).first()[0]
    rest = table.where(~F.col("doc_id").isin(ids) & F.col("entropy").isNotNull()).orderBy(F.desc("entropy"), "doc_id").first()
    assert used <= limit < used + rest.n_tokens
    assert chosen.agg(F.min("entropy")).first()[0] >= rest.entropy


def test_hard_choices_nest(spark, table):
    sets = [{r.doc_id for r in select.choose(table, "novelty", "hard", f).collect()} for f in (0.01, 0.05, 0.1, 1.0)]
    assert all(a <= b for a, b in zip(sets, sets[1:], strict=False))


def test_weights_of_one_metric_make_blended_that_metric(spark, table):
    a = select.choose(table, "blended", "hard", 0.1, weights=(1, 0, 0))
    q = quantiles.normalise(table, "similarity")
    b = select.hard(q.where("perplexity IS NOT NULL AND entropy IS NOT NULL"), "q_similarity", select.budget(table, 0.1))
    assert sorted(r.doc_id for r in a.collect()) == sorted(r.doc_id for r in b.collect())


def test_soft_reaches_everywhere_and_rises_with_weight(spark, table):
    q = settle(quantiles.normalise(table, "entropy"))
    counts = {}
    for seed in range(25):
        for r in select.soft(q, "q_entropy", select.budget(table, 0.1), seed).select("q_entropy").collect():
            counts[min(int(r.q_entropy * 2), 1)] = counts.get(min(int(r.q_entropy * 2), 1), 0) + 1
    assert counts[1] > counts[0] > 0


def test_bernoulli_keeps_the_expected_number(spark, table):
    q = settle(quantiles.normalise(table, "similarity"))
    want, var = q.agg(F.sum("q_similarity"), F.sum(F.col("q_similarity") * (1 - F.col("q_similarity")))).first()
    assert abs(select.soft(q, "q_similarity", None, method="bernoulli").count() - want) < 4 * math.sqrt(var)
    scaled = select.soft(q, "q_similarity", select.budget(table, 0.3), method="bernoulli_scaled")
    assert 0 < scaled.agg(F.sum("n_tokens")).first()[0] < 0.6 * table.agg(F.sum("n_tokens")).first()[0]


@pytest.mark.parametrize("method", quantiles.METHODS)
def test_quantiles_are_monotone_and_share_ties(spark, table, method):
    rows = quantiles.normalise(table, "perplexity", method).orderBy("perplexity").collect()
    for a, b in zip(rows, rows[1:], strict=False):
        assert a.q_perplexity <= b.q_perplexity <= 1
        if a.perplexity == b.perplexity:
            assert a.q_perplexity == b.q_perplexity


def test_quantiles_against_their_definition(spark, table):
    values = [r.entropy for r in table.collect()]
    some = [v for v in values if v is not None]
    for method, q in (
        ("exact", lambda v: math.ceil(100.0 * (sum(x <= v for x in some) / len(some))) / 100.0),
        ("percent_rank", lambda v: math.floor(100.0 * (sum(x < v for x in some) / (len(some) - 1.0))) / 100.0),
    ):
        for r in quantiles.normalise(table, "entropy", method).collect():
            assert r.q_entropy == (None if r.entropy is None else q(r.entropy))
    none = table.where("false")
    assert quantiles.normalise(none, "entropy").collect() == []


def test_ranks_and_running_totals_over_partitions(spark):
    df = spark.range(1000).select("id", F.pmod("id", F.lit(3)).alias("g"), F.when(F.pmod("id", F.lit(7)) > 0, F.pmod("id", F.lit(5))).alias("x")).repartition(9)
    got = running_total(ranked(df, ["g"], ["x", "id"], "r"), ["g"], ["x", "id"], "id", "total").collect()
    for g in range(3):
        own = sorted((r for r in got if r.g == g), key=lambda r: (r.x is not None, r.x or 0, r.id))
        total = 0
        for k, r in enumerate(own):
            total += r.id
            assert (r.r, r.total) == (k, total)


def test_layout_does_not_matter(spark, sf):
    docs = read_table(spark, sf, "documents").dropDuplicates(["text"])
    seed = read_table(spark, sf, "benchmark").withColumnRenamed("item_id", "seed_id")
    model = lm.train(read_table(spark, sf, "conversations"))
    a, b = (settle(metrics_table.score_all(x, similarity.centroid(seed), model)) for x in (docs, docs.repartition(13)))
    pick = lambda m: sorted(r.doc_id for r in select.choose(m, "blended", "soft", 0.1).collect())
    assert pick(a) == pick(b)


def test_requirements_are_enforced(spark):
    with pytest.raises(ValueError):
        baselines.check_inputs("task_similar", None)
    with pytest.raises(ValueError):
        baselines.check_inputs("novelty", spark.range(1))
    with pytest.raises(ValueError):
        similarity.score(spark.createDataFrame(DOCS, "doc_id long, text string"), spark.createDataFrame([], "term string, w double"))
    with pytest.raises(ValueError):
        select.budget(tiny(spark), 1.5)


def test_texts_without_words(spark):
    docs = spark.createDataFrame([(1, ""), (2, "  \n"), (3, "!?"), (4, None), (5, "word")], "doc_id long, text string")
    seed = spark.createDataFrame([(0, "bank loan")], "seed_id long, text string")
    m = {r.doc_id: r for r in metrics_table.score_all(docs, similarity.centroid(seed), base_model(spark)).collect()}
    assert all(m[i].n_tokens == 0 and m[i].perplexity is None and m[i].similarity == 0 for i in (1, 2, 3, 4))
    assert m[1].entropy is None and m[3].entropy == 0
    chosen = select.choose(spark.createDataFrame([tuple(r) for r in m.values()], "doc_id long, n_tokens long, similarity double, perplexity double, entropy double"), "novelty", "hard", 1.0)
    assert [r.doc_id for r in chosen.collect()] == [5]


def test_recipe_writes_shards_and_manifest(spark, sf, tmp_path):
    docs = read_table(spark, sf, "documents")
    seed = read_table(spark, sf, "benchmark").withColumnRenamed("item_id", "seed_id")
    chosen = spec.run(spark, spec.SelectionSpec(selector="blended", noise_guard=True, fraction=0.3), docs, seed, read_table(spark, sf, "conversations"), str(tmp_path), 4000)
    back = spark.read.json(f"{tmp_path}/shards")
    assert sorted(r.doc_id for r in back.select("doc_id").collect()) == sorted(r.doc_id for r in chosen.collect())
    assert "blended" in spark.read.text(f"{tmp_path}/manifest").first()["value"]
    assert spec.choose_route(10, 10)["model"] == "broadcast" and spec.choose_route(10**9, 10)["model"] != "broadcast"


def test_lines_filings_and_the_metric_store(spark, sf, tmp_path):
    docs = read_table(spark, sf, "documents")
    docs.write.json(str(tmp_path / "lines"))
    back = tables.read_lines(spark, str(tmp_path / "lines"), tables.SCHEMAS["documents"])
    assert sorted(map(str, back.collect())) == sorted(map(str, docs.collect()))
    (tmp_path / "bad").mkdir()
    (tmp_path / "bad" / "x.json").write_text('{"doc_id": 1, "text": "a"\n')
    with pytest.raises(Exception, match="(?i)malformed|FAILED_READ_FILE"):
        tables.read_lines(spark, str(tmp_path / "bad"), tables.SCHEMAS["documents"]).collect()
    (tmp_path / "filings").mkdir()
    for k, text in enumerate(("one\ntwo\n", "", "x")):
        (tmp_path / "filings" / f"{k}.txt").write_text(text)
    found = {r.path.rsplit("/", 1)[1]: r.text for r in tables.read_filings(spark, str(tmp_path / "filings")).collect()}
    assert found["0.txt"] == "one\ntwo\n" and found["2.txt"] == "x"
    m = metrics_table.standard(spark, sf)
    spark.sql(f"CREATE DATABASE IF NOT EXISTS winnow_test LOCATION '{tmp_path}/store'")
    tables.save_metrics(m, "winnow_test.metrics", "first", 4)
    try:
        kept = spark.table("winnow_test.metrics")
        assert kept.where("snapshot = 'first'").count() == m.count() and set(m.columns) < set(kept.columns)
    finally:
        spark.sql("DROP DATABASE winnow_test CASCADE")


def test_large_models_and_seeds_score_as_small_ones(spark, sf, monkeypatch):
    """The joins that serve tables too large for a broadcast give the same scores."""
    docs = read_table(spark, sf, "documents")
    seed = read_table(spark, sf, "benchmark").withColumnRenamed("item_id", "seed_id")
    general = read_table(spark, sf, "conversations")
    ids = lambda df, *c: sorted((tuple(None if v is None else round(v, 6) for v in (r[x] for x in ("doc_id", *c))) for r in df.collect()), key=str)
    small = [lm.train(general, o) for o in (1, 2)]
    want = [ids(lm.perplexity(docs, m), "perplexity") for m in small], ids(similarity.score_each(docs, seed, "max"), "similarity"), ids(metrics_table.score_all(docs, similarity.centroid(seed), small[0]), "similarity", "perplexity")
    monkeypatch.setattr(lm, "TERMS_BROADCAST", 10)
    monkeypatch.setattr(lm, "fits", lambda df: False)
    monkeypatch.setattr(similarity, "SEED_ENTRIES", 10)
    large = [lm.train(general, o) for o in (1, 2)]
    assert not large[0].small
    got = [ids(lm.perplexity(docs, m), "perplexity") for m in large], ids(similarity.score_each(docs, seed, "max"), "similarity"), ids(metrics_table.score_all(docs, similarity.centroid(seed), large[0]), "similarity", "perplexity")
    assert got == want


def test_odd_tables_under_scores_models_and_baselines(spark):
    """Null, empty and repeated rows, null ids, clashing columns and empty tables have the stated results."""
    schema = "doc_id long, text string, w string, c string, term string, _w string, k string"
    rows = [(1, "bank loan"), (2, None), (3, ""), (4, "!?"), (None, "loan"), (5, "tree " * 20_000), (6, "bank loan"), (6, "bank loan")]
    docs = spark.createDataFrame([(*r, "x", "x", "x", "x", "x") for r in rows], schema)
    seed = spark.createDataFrame([(0, "bank loan"), (1, None), (2, "..")], "seed_id long, text string")
    model = base_model(spark)
    idf = similarity.inverse_frequency(docs)
    for how in ({}, {"pool": "max"}, {"pool": "mean"}, {"idf": idf}):
        got = {r.doc_id: r.similarity for r in similarity.similarity(docs, seed, **how).collect()}
        assert got[1] > 0.99 and got[2] == got[3] == got[4] == got[5] == 0 and 0 < got[None] < 1
        assert similarity.similarity(docs.limit(0), seed, **how).count() == 0
    for m in (model, lm.train(docs, 2)):
        got = {r.doc_id: r.n_tokens for r in lm.perplexity(docs, m).collect()}
        assert got == {1: 2, None: 1, 5: 20_000, 6: 4} and lm.perplexity(docs.limit(0), m).count() == 0
    empty = lm.train(docs.limit(0))
    assert empty.vocabulary == 0 and abs(lm.perplexity(docs.where("doc_id = 1"), empty).first()["perplexity"] - 1) < 1e-12
    sized = docs.withColumn("n_tokens", F.lit(2).cast("long"))
    assert sorted(r.doc_id or 0 for r in baselines.uniform_budget(sized, 1.0).collect()) == [0, 1, 2, 3, 4, 5, 6, 6]
    assert baselines.uniform_budget(sized, 0.5).agg(F.sum("n_tokens")).first()[0] == 8
    assert {r.doc_id for r in baselines.importance_resample(docs.drop("k").withColumn("n_tokens", F.lit(1).cast("long")).where("doc_id < 6"), seed, 1.0).collect()} == {1, 5}
