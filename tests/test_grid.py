from pyspark.sql import functions as F

from winnow.plans import experiments
from winnow.plans.settle import settle


def test_models_side_by_side_give_what_each_gives_alone(spark, sf, monkeypatch):
    b = experiments.Bench(spark, sf)
    alone = [settle(b.few_shot(b.continued(s, "hard", f), 2).agg(F.round(F.avg("f1"), 6).alias("f1"))).first()["f1"] for s, f in (("novelty", 0.1), ("uniform_budget", 1.0))]

    def one_by_one(*_, **__):
        raise AssertionError("a model was tested alone")

    monkeypatch.setattr(b, "few_shot", one_by_one)
    got = {(r["selector"], r["fraction"]): r["f1"] for r in experiments.f1_ablation(b, (0.1, 1.0), 2).collect()}
    assert len(got) == 8 and [got["novelty", 0.1], got["uniform_budget", 1.0]] == alone
    assert got["diversity", 0.1] != got["novelty", 0.1]


def test_the_comparison_gives_what_each_row_gives_alone(spark, sf, monkeypatch):
    b = experiments.Bench(spark, sf)
    rows = (("base_only", ""), ("task_only", ""), ("blended", "soft"))
    key = lambda r: (r["task"], r["seed"], round(r["f1"], 9), r["accuracy"] and round(r["accuracy"], 9))
    alone = sorted(("task_only", "", *key(r)) for r in b.few_shot(b.continued("task_only"), 2).collect())

    def one_by_one(*_, **__):
        raise AssertionError("a row was trained or tested alone")

    monkeypatch.setattr(b, "few_shot", one_by_one)
    monkeypatch.setattr(b, "continued", one_by_one)
    got = experiments.selection_comparison(b, rows, 2).collect()
    assert {(r["selector"], r["mode"]) for r in got} == set(rows)
    assert sorted((r["selector"], r["mode"], *key(r)) for r in got if r["selector"] == "task_only") == alone


def test_spans_are_handed_on_in_small_batches():
    from winnow.operators import fewshot

    docs = fewshot.pa.table({"doc_id": [1, 2, 3], "text": ["a  b " * 40_000, None, "x@y.zz q\n10.0.0.1"]}).to_batches()
    run = {}

    class Docs:
        def select(self, *_):
            return self

        def mapInArrow(self, f, _):
            run["f"] = f

    fewshot.token_spans(Docs())
    rows = [r for b in run["f"](iter(docs)) for r in b.to_pylist()]
    assert len(rows) == 80_000 + 39_999 + 3 + 1 and {"doc_id": 3, "start": 1, "stop": 9, "m": "x@y.zz q"} in rows
    assert max(b.num_rows for b in run["f"](iter(docs))) <= fewshot.ROWS_AT_A_TIME
    fewshot.rule_spans(Docs())
    assert [(r["doc_id"], r["start"], r["type"]) for b in run["f"](iter(docs)) for r in b.to_pylist()] == [(3, 1, "EMAIL"), (3, 10, "IP")]


def test_choices_side_by_side_give_what_each_model_gives_alone(spark, sf, monkeypatch):
    from functools import reduce

    from winnow.operators import fewshot, metrics

    b = experiments.Bench(spark, sf)
    rows = (("importance_resample", ""), ("representative_subset", ""), ("blended", "soft"))
    items = {k: settle(v) for k, v in fewshot.general_items(spark, sf, b.corpus).items()}
    alone = []
    for s, m in rows:
        model = b.continued(s, m or "hard")
        for task, pairs in items.items():
            scored = settle(fewshot.with_scores(fewshot.conditional_ll(pairs, model)))
            a = metrics.choice_accuracy(scored).first()
            alone.append((s, m, task, a["items"], a["accuracy"], metrics.choice_accuracy(scored, "score_norm").first()["accuracy"], metrics.mc2(scored).first()["mc2"]))

    def one_by_one(*_, **__):
        raise AssertionError("a row was chosen or trained alone")

    monkeypatch.setattr(b, "selection", one_by_one)
    monkeypatch.setattr(b, "continued", one_by_one)
    shown = lambda r: (*r[:4], *[None if x is None else round(x, 6) for x in r[4:]])
    assert sorted(map(shown, map(tuple, experiments.open_domain(b, rows).collect()))) == sorted(map(shown, alone))


def test_the_size_pair_gives_what_the_bigram_model_gives_alone(spark, sf, monkeypatch):
    b = experiments.Bench(spark, sf, 2)
    key = lambda r: (r["task"], r["seed"], round(r["f1"], 9), r["accuracy"] and round(r["accuracy"], 9))
    alone = sorted(map(key, b.few_shot(b.continued("full_domain"), 1, pool="fresh").collect()))

    def counted(*_, **__):
        raise AssertionError("the corpus's pairs were counted")

    monkeypatch.setattr(experiments.lm, "bigram_counts", counted)
    got = experiments.size_pair(spark, sf, 1).collect()
    for size in ("small", "large"):
        assert sorted(key(r) for r in got if (r["model"], r["selector"]) == (size, "full_domain")) == alone
