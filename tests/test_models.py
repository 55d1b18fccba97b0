import hashlib
import math
import random

from pyspark.sql import functions as F

from winnow.operators import dedup, fewshot, lm, metrics, metrics_table, results, select, tasks
from winnow.operators.components import connected_components
from winnow.operators.skew import salted_join
from winnow.plans import catalog
from winnow.sources.tables import load_model, read_table, save_model


def texts(spark, *t):
    return spark.createDataFrame(list(enumerate(t)), "doc_id long, text string")


def test_probabilities_sum_to_one(spark):
    m = lm.train(texts(spark, "a b a", "c"))
    p = m.unigrams.select(F.sum(m.p1(F.col("c"))).alias("s")).first()["s"]
    unknown = (0 + m.alpha) / (m.total + m.alpha * (m.vocabulary + 1))
    assert abs(p + unknown - 1) < 1e-12


def test_perplexity_facts(spark):
    m = lm.train(texts(spark, "a b c d"))  # uniform
    r = {x.doc_id: x.perplexity for x in lm.perplexity(texts(spark, "a b", "a b a b", "zzz"), m).collect()}
    assert abs(r[0] - 9 / 2) < 1e-9 and abs(r[0] - r[1]) < 1e-9 and abs(r[2] - 9) < 1e-9


def test_texts_of_the_same_words_tie_in_perplexity_and_rank_by_id(spark):
    rng = random.Random(5)
    m = lm.train(texts(spark, *[" ".join(f"w{i}" for _ in range(i * i)) for i in range(1, 60)]))
    bag = [f"w{rng.randrange(1, 80)}" for _ in range(40)] + [f"new{i}" for i in range(400)]
    docs = texts(spark, *[" ".join(rng.sample(bag, len(bag))) for _ in range(40)])
    centre = spark.createDataFrame([("w1", 1.0)], "term string, w double")
    scored = metrics_table.score_all(docs, centre, m).collect()
    assert len({r.perplexity for r in scored}) == 1 and scored[0].perplexity > 10_000
    assert len({r.ll for r in lm.log_likelihood(docs, m).collect()}) == 1
    chosen = select.choose(spark.createDataFrame(scored), "novelty", "hard", 0.5).collect()
    assert [r.doc_id for r in sorted(chosen, key=lambda r: r.cum_tokens)] == list(range(20))


def test_bigram_interpolation_by_hand(spark):
    m = lm.train(texts(spark, "a b a c"), 2)
    got = lm.perplexity(texts(spark, "a b"), m).first()["perplexity"]
    p1 = lambda c: (c + 1) / (4 + 4)
    want = math.exp(-(math.log(p1(2)) + math.log(0.5 * 1 / 2 + 0.5 * p1(1))) / 2)
    assert abs(got - want) < 1e-9


def test_continued_counts_add_up(spark):
    base = lm.train(texts(spark, "a b a"))
    more = lm.continue_training(base, texts(spark, "b c"), 2)
    assert {r.term: r.c for r in more.unigrams.collect()} == {"a": 2, "b": 3, "c": 2} and (more.total, more.vocabulary) == (7, 3)
    assert lm.continue_training(base, texts(spark, "x"), 0) is base


def test_packed_model_equals_the_table_without_collisions(spark):
    m = lm.train(texts(spark, "a b c a", "d e"))
    packed = lm.pack(m, 16)
    a = {r.doc_id: r.perplexity for r in lm.perplexity(texts(spark, "a b", "e q", "c"), m).collect()}
    b = {r.doc_id: r.perplexity for r in lm.perplexity_packed(texts(spark, "a b", "e q", "c"), packed).collect()}
    assert a.keys() == b.keys() and all(abs(a[k] - b[k]) < 1e-4 for k in a)


def test_model_store(spark, tmp_path):
    m = lm.train(texts(spark, "a b"))
    save_model(spark, str(tmp_path), m.unigrams, {"total": m.total})
    counts, meta = load_model(spark, str(tmp_path))
    assert counts.count() == 2 and meta == {"total": 2}


def test_near_duplicates_against_all_pairs(spark, sf):
    docs = read_table(spark, "/root/testdata/sf0.01", "documents")
    unique = dedup.exact(docs).select("doc_id", "text")
    sets = {r.doc_id: frozenset(r.grams) for r in dedup.grams_of(unique).collect()}
    ids = sorted(sets)
    true = [(a, b) for i, a in enumerate(ids) for b in ids[i + 1 :] if sets[a] & sets[b] and len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])]
    keeper = {r.doc_id: r.keeper for r in dedup.near(unique).collect()}
    assert true and sum(keeper.get(a) is not None and keeper.get(a) == keeper.get(b) for a, b in true) / len(true) >= 0.99
    linked = {x for p in true for x in p}
    assert set(keeper) <= linked
    assert dedup.exact(dedup.exact(docs)).count() == dedup.exact(docs).count()


def test_crowded_bands_keep_their_groups(spark):
    base = [f"w{i}" for i in range(60)]
    rows = [(i, " ".join([*base, f"tail{i}"])) for i in range(50)]
    keeper = dedup.near(texts(spark, *[t for _, t in rows]), block=4).collect()
    assert len(keeper) == 50 and {r.keeper for r in keeper} == {0}


def test_crowded_bands_keep_pairs_far_from_the_hub(spark):
    """Near copies in pairs only, on one long template; neither the smallest id nor the neighbour is a near copy."""
    base = [f"w{i}" for i in range(444)]
    n = 40
    rows = [" ".join([*base, *[f"p{i % n}x{j}" for j in range(12)], *[f"d{i}x{j}" for j in range(48)]]) for i in range(2 * n)]
    docs = texts(spark, *rows)
    sets = {r.doc_id: frozenset(r.grams) for r in dedup.grams_of(docs).collect()}
    true = {(a, b) for a in sets for b in sets if a < b and len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])}
    assert true == {(i, n + i) for i in range(n)}
    assert {r.doc_id: r.keeper for r in dedup.near(docs, block=4).collect()} == {x: a for a, b in true for x in (a, b)}


def test_a_crowded_template_loses_no_pair(spark):
    """Three hundred pairs of near copies on one template that alone isn't enough, ids shuffled."""
    base = [f"w{i}" for i in range(444)]
    n = 300
    ids = random.Random(2).sample(range(10_000), 2 * n)
    rows = [(ids[i], " ".join([*base, *[f"p{i % n}x{j}" for j in range(12)], *[f"d{i}x{j}" for j in range(48)]])) for i in range(2 * n)]
    found = {r.doc_id: r.keeper for r in dedup.near(spark.createDataFrame(rows, "doc_id long, text string").repartition(8)).collect()}
    hits = sum(found.get(ids[i]) is not None and found.get(ids[i]) == found.get(ids[i + n]) for i in range(n))
    assert hits / n >= 0.99


def test_exact_dedup_of_odd_rows(spark):
    rows = [(3, "a", "x"), (3, "a", "x"), (3, "b", "x"), (5, "a", "y"), (None, "a", "z"), (None, "n", "z"), (None, "n", "z"), (7, None, "q"), (8, None, "q"), (9, "c", "u"), (9, "c", "v")]
    df = spark.createDataFrame(rows, "doc_id long, text string, _ex_d string").repartition(4)
    got = sorted(((r.doc_id, r.text, r._ex_d) for r in dedup.exact(df).collect()), key=str)
    assert [x for x in got if x[0] != 9] == sorted([(3, "a", "x"), (3, "b", "x"), (None, "n", "z"), (7, None, "q")], key=str)
    assert [x[:2] for x in got if x[0] == 9] == [(9, "c")] and dedup.exact(df).columns == df.columns
    again = sorted(((r.doc_id, r.text, r._ex_d) for r in dedup.exact(df.repartition(3)).collect()), key=str)
    assert again == got and dedup.exact(df.limit(0)).count() == 0


def test_repeated_lines_of_odd_rows(spark):
    line = "a line that many documents hold"
    rows = [(1, f"{line}\nown one"), (2, f"x\n{line}\n{line}"), (3, line), (None, f"{line}\nlast"), (4, None), (4, None), (5, ""), (6, "a\tshort one\n"), (1, "another text of the same id")]
    got = sorted(((r.doc_id, r.text, r.dropped) for r in dedup.repeated_lines(spark.createDataFrame(rows, "doc_id long, text string")).collect()), key=str)
    want = [(1, "own one", 1), (2, "x", 2), (3, "", 1), (None, "last", 1), (4, "", 0), (4, "", 0), (5, "", 0), (6, "a\tshort one\n", 0), (1, "another text of the same id", 0)]
    assert got == sorted(want, key=str)
    assert dedup.repeated_lines(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_resembling_pairs_of_crowds_against_all_pairs(spark):
    """Sixty near copies on one boilerplate, equal sets and short texts; no gram may be lost for being common."""
    base = [f"w{i}" for i in range(60)]
    rows = [" ".join([*base, f"tail{i}"]) for i in range(60)]
    rows += [" ".join([*base[:30], *[f"u{i}v{j}" for j in range(30)]]) for i in range(5)]
    rows += ["one two three four", "One two, three four!", "a b c d e f", "a b c d e f a b c d e f"]
    docs = texts(spark, *rows)
    sets = {r.doc_id: frozenset(r.grams) for r in dedup.grams_of(docs).collect()}
    j = {(a, b): len(sets[a] & sets[b]) / len(sets[a] | sets[b]) for a in sets for b in sets if a < b}
    want = {(*p, round(v, 6)) for p, v in j.items() if v >= 0.8}
    got = [tuple(r) for r in dedup.resembling_pairs(docs).select("a", "b", "jaccard").collect()]
    assert len(got) == len(set(got)) and set(got) == want and len(want) > 60 * 59 / 2


def test_every_test_item_gets_its_prompt(spark):
    """Against brute force on a table with far more than ninety labelled rows."""
    d = "/root/testdata/sf0.01"
    ranked = tasks.ranked_pool(tasks.labelled(read_table(spark, d, "documents"), read_table(spark, d, "labels"))).collect()
    digest = lambda s: hashlib.md5(s.encode()).hexdigest()
    want = set()
    for t in (r for r in ranked if r["rank"] > 50):
        pool = sorted((r for r in ranked if r["task"] == t["task"] and r["rank"] <= 50), key=lambda r: (int(digest(f"{r['doc_id']}-{t['doc_id']}:1")[:13], 16), r["doc_id"]))
        shown = "\n\n".join(f"Text: {r['text']}\nAnswer: {r['label']}" for r in pool[:5])
        want.add((t["task"], t["doc_id"], digest(f"Decide.\n\n{shown}\n\nText: {t['text']}\nAnswer:")))
    got = [tuple(r) for r in catalog.queries()["few_shot_prompts"](spark, d).select("task", "doc_id", "prompt_md5").collect()]
    assert len(got) == len(want) > 80 and set(got) == want


def test_f1_by_hand(spark):
    pred = spark.createDataFrame([("t", "1", "1"), ("t", "1", "0"), ("t", "0", "0"), ("t", "0", "2")], "task string, label string, predicted string")
    one = lambda a: metrics.f1(pred, a, ("task",)).first()["f1"]
    assert abs(one("macro") - (2 / 3 + 1 / 2 + 0) / 3) < 1e-12
    assert abs(one("micro") - 0.5) < 1e-12 and abs(one("binary") - 2 / 3) < 1e-12
    assert abs(one("weighted") - (2 * 2 / 3 + 2 * 1 / 2) / 4) < 1e-12


def test_win_rates_average_fifty(spark):
    r = metrics.win_rate(results.selection(spark).withColumn("selector", F.concat_ws("/", "selector", "mode")))
    assert abs(r.agg(F.avg("win_rate")).first()[0] - 50) < 1e-9


def test_reported_arithmetic(spark):
    for r in results.replay(spark).collect():
        assert abs(r.average - r.reported_average) <= 0.011 and abs(r.sd_tasks - r.reported_sd) <= 0.06 and abs(r.gain - r.reported_gain) <= 0.1
    assert all(r.holds for r in results.observations(spark).collect())
    full = {r.model: (r.a, r.f) for r in results.full_corpus(spark).where("measure LIKE '%f1'").groupBy("model").agg(F.first("average").alias("a"), F.avg("value").alias("f")).collect()}
    off = {m for m, (a, f) in full.items() if abs(a - f) > 0.011}
    assert off == {"continued_6.9b"}  # printed as 54.83, the mean is 55.01
    for r in results.retention(spark).where("measure LIKE '%acc' OR measure = 'o3_mc1'").groupBy("selector", "mode").agg(F.avg("value").alias("v"), F.first("average").alias("a")).collect():
        assert abs(r.v - r.a) <= 0.011


def test_multiple_choice_measures(spark):
    s = spark.createDataFrame([(1, 0, True, 0.0), (1, 1, False, math.log(3)), (2, 0, True, 1.0), (2, 1, True, 1.0), (2, 2, False, 0.0)], "item long, candidate int, is_true boolean, score double")
    assert metrics.mc1(s).first()["accuracy"] == 0.5
    e = math.e
    assert abs(metrics.mc2(s).first()["mc2"] - (0.25 + 2 * e / (2 * e + 1)) / 2) < 1e-12


def test_contamination_finds_planted_passages(spark):
    docs = texts(spark, "before. The passage that was planted here, word by word! after", "nothing", "xThe passage that was planted here, word by word!x", "the Passage that was planted here, word by word!")
    items = spark.createDataFrame([(7, "The passage that was planted here, word by word!"), (8, "no")], "item_id long, text string")
    assert sorted((r.doc_id, r.item_id) for r in metrics.contamination(docs, items).collect()) == [(0, 7), (2, 7)]


def test_distractors_are_others(spark):
    items = spark.createDataFrame([(i, f"p{i}", f"t{i}") for i in range(9)], "item long, prompt string, text string")
    rows = fewshot.with_distractors(items).collect()
    assert len(rows) == 36 and all((r.text == f"t{r.item}") == r.is_true for r in rows)


def test_salted_join_equals_the_join_and_deals_a_heavy_key(spark):
    left = spark.range(5000).select(F.when(F.col("id") < 4000, F.lit(7)).otherwise(F.col("id") % 50).cast("long").alias("k"), F.col("id").alias("x"))
    right = spark.range(60).select(F.col("id").alias("k"), (F.col("id") * 2).alias("y"), F.lit("c").alias("_salt"))
    got = salted_join(left, right, ["k"], 5000)
    assert got.columns == ["k", "x", "y", "_salt"]
    assert sorted(tuple(r) for r in got.collect()) == sorted(tuple(r) for r in left.join(right, "k").collect())
    assert salted_join(left.limit(0), right, ["k"], 0).count() == 0


def test_components_of_a_hub_and_a_chain(spark):
    hub = [(0, i) for i in range(1, 900)] + [(5000 + i, 5001 + i) for i in range(60)] + [(3, 3), (None, 4), (899, 0)]
    got = {r.node: r.root for r in connected_components(spark.createDataFrame(hub, "a long, b long")).collect()}
    assert got == {i: 0 for i in range(1, 900)} | {5001 + i: 5000 for i in range(60)}


def test_few_edges_are_joined_up_in_one_task(spark, monkeypatch):
    from winnow.operators import components

    rng = random.Random(4)
    edges = [(rng.randrange(-300, 300), rng.randrange(-300, 300)) for _ in range(250)] + [(i, i + 1) for i in range(1000, 1200)] + [(5000, -9), (7, 7)]
    rows = spark.createDataFrame([*edges, (None, 3)], "a long, b long")
    by_rounds = {(r.node, r.root) for r in connected_components(rows, one_task=0).collect()}

    def no_round(*_):
        raise AssertionError("a round was planned")

    monkeypatch.setattr(components, "_large_star", no_round)
    assert {(r.node, r.root) for r in connected_components(rows).collect()} == by_rounds
    names = spark.createDataFrame([("é", "b"), ("b", "zz"), ("x", "y"), ("x", "x")], "a string, b string")
    assert {(r.node, r.root) for r in connected_components(names).collect()} == {("é", "b"), ("zz", "b"), ("y", "x")}
    assert connected_components(rows.where("a > 9999")).count() == 0
