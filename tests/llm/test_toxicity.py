import random

import numpy as np

from winnow.llm import toxicity


def test_held_out_accuracy(spark):
    folder = "/root/testdata/sf0.1"
    labels = {r.doc_id: r.toxic for r in spark.read.parquet(f"{folder}/labels.parquet").collect()}
    rows = toxicity.op7_toxicity(spark, folder).collect()
    assert len(rows) == 10_000 and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.5) and r.held_out == toxicity.held_out(r.doc_id) for r in rows)
    out = [(r.score, labels[r.doc_id]) for r in rows if r.held_out and r.doc_id in labels]
    pos, neg = [s for s, y in out if y], [s for s, y in out if not y]
    auc = sum((p > n) + 0.5 * (p == n) for p in pos for n in neg) / (len(pos) * len(neg))
    assert auc > 0.95 and sum(p >= 0.5 for p in pos) / len(pos) > 0.85 and sum(n >= 0.5 for n in neg) / len(neg) < 0.03


def biased(n=600, seed=4):
    """Insults decide the label, but the sample's toxic texts mention one group far more often."""
    rng = random.Random(seed)
    fill = [f"word{i}" for i in range(60)]
    out = []
    for _ in range(n):
        toxic = rng.random() < 0.4
        w = set(rng.sample(fill, 12))
        if toxic:
            w |= {rng.choice(["idiot", "scum", "moron"])} if rng.random() < 0.8 else set()
        if rng.random() < (0.7 if toxic else 0.05):
            w |= {"muslims"}
        out.append((w, int(toxic)))
    return out, sorted({x for w, _ in out for x in w} | set(toxicity._KIND))


def test_swaps_reduce_false_alarms_on_neutral_mentions():
    """With the shipped penalty and rounds: neutral mentions of the group that toxic texts name are no longer rejected."""
    examples, vocabulary = biased()
    free = toxicity.fit(examples, vocabulary, swap_penalty=0.0)
    held = toxicity.fit(examples, vocabulary)
    mention = {"muslims", "word1", "word2", "word3"}
    other = {"christians", "word1", "word2", "word3"}
    assert abs(held.score(mention) - held.score(other)) < 0.25 * abs(free.score(mention) - free.score(other))
    assert held.score(mention) < 0.5 < free.score(mention)
    assert held.score(mention | {"scum"}) > held.score(mention) + 0.3
    clean = [w for w, y in biased(seed=5)[0] if not y and "muslims" not in w]
    rate = lambda m, extra: sum(m.score(w | extra) >= 0.5 for w in clean) / len(clean)
    # the mention adds next to nothing to the alarms that the random words alone raise, where it decided most without the penalty
    assert rate(held, {"muslims"}) <= rate(held, set()) + 0.03 and rate(free, {"muslims"}) > rate(free, set()) + 0.3


def test_the_fit_reaches_the_optimum_of_a_plain_dense_solver():
    rng = random.Random(8)
    words = [f"w{i}" for i in range(8)] + ["women", "men", "scum"]
    examples = []
    for _ in range(80):
        s = {w for w in words if rng.random() < 0.3}
        examples.append((s, int(("scum" in s) or ("women" in s and rng.random() < 0.5) or rng.random() < 0.1)))
    vocabulary = sorted({*words, "girls", "boys"})
    model = toxicity.fit(examples, vocabulary, rounds=5000)
    x = np.array([[float(any(f == v for w in s for f in toxicity.features(w))) for v in vocabulary] for s, _ in examples])
    y = np.array([t for _, t in examples], float)
    pairs = []
    for s, _ in examples:
        for w in sorted(s & toxicity._KIND.keys()):
            for t in toxicity._KIND[w]:
                if t != w:
                    after = (s - {w}) | {t}
                    d = [float(any(f == v for u in s for f in toxicity.features(u))) - float(any(f == v for u in after for f in toxicity.features(u))) for v in vocabulary]
                    if any(d):
                        pairs.append(d)
    d = np.array(pairs)
    c = np.where(y == 1, 0.5 / y.sum(), 0.5 / (len(y) - y.sum()))
    scale = 1 / np.sqrt(np.maximum(1e-6, c @ x) + 1e-3)
    xs, ds, seen = x * scale, d * scale, x.any(axis=0)

    def objective(w, b):
        z = b + xs @ w
        return float(c @ (np.logaddexp(0, z) - y * z)) + float(((ds @ w) ** 2).mean()) * toxicity.SWAP_PENALTY + toxicity.L1 * np.abs(w).sum()

    w, b, step = np.zeros(len(vocabulary)), 0.0, 0.2
    for _ in range(60_000):
        g = c * (1 / (1 + np.exp(-(b + xs @ w))) - y)
        grad = xs.T @ g + 2 * toxicity.SWAP_PENALTY / len(ds) * ds.T @ (ds @ w)
        w, b = w - step * grad, b - step * g.sum()
        w = np.sign(w) * np.maximum(np.abs(w) - step * toxicity.L1, 0) * seen
    mine = np.array([model.weights.get(v, 0.0) for v in vocabulary]) / scale
    assert abs(objective(mine, model.bias) - objective(w, b)) < 1e-5
    assert np.abs(mine - w).max() < 0.02


def test_swaps_stay_within_a_kind():
    found = {"women", "word", "gay"}
    pairs = toxicity.swapped(found)
    assert len(pairs) == 3 + 5 and all("word" in t and len(t) == 3 and t != found for _, t in pairs)
    assert {w for w, _ in pairs} == {"women", "gay"} and toxicity.swapped({"word"}) == []
    assert toxicity.mentions("Women vote. Nothing here! Las mujeres votan\nWomen vote?") == [["las", "mujeres", "votan"], ["vote", "women"]] and toxicity.mentions(None) == []


def test_differences_are_those_of_the_sentences():
    at = {f: i for i, f in enumerate(sorted({f for w in ("women", "men", "girls", "boys", "womenfolk") for f in toxicity.features(w)}))}
    for s in ({"women", "x"}, {"women", "men"}, {"women", "womenfolk"}):
        total = 0
        for diff, n in toxicity.differences([s], at).items():
            total += n
            assert all(sign in (1, -1) for _, sign in diff)
        assert total == len(toxicity.swapped(s))
        want = []
        for _, t in toxicity.swapped(s):
            a, b = ({at[f] for w in x for f in toxicity.features(w) if f in at} for x in (s, t))
            want.append(tuple(sorted([(i, 1) for i in a - b] + [(i, -1) for i in b - a])))
        assert sorted(want) == sorted(toxicity.differences([s], at).elements())


def test_labels_of_one_kind_or_none():
    assert toxicity.fit([], ["a"]).score({"a"}) < 1e-9
    assert toxicity.fit([({"a"}, 1)], ["a"]).score(set()) > 0.99
    assert toxicity.fit([({"a"}, 0)], ["a"]).score({"a"}) < 1e-9


def test_odd_rows(spark):
    docs = spark.createDataFrame([(1, None, "s"), (2, "", "s"), (None, "idiot", "s"), (3, "idiot", "s"), (3, "idiot", "s")], "doc_id long, text string, score string")
    labels = spark.createDataFrame([(3, 1), (2, 0), (None, 1), (1, None)], "doc_id long, toxic int")
    rows = toxicity.score(docs, toxicity.train(docs, labels)).collect()
    assert len(rows) == 5 and all(0 <= r.score <= 1 for r in rows)
    assert toxicity.clean(docs, labels).columns == docs.columns
    assert toxicity.clean(docs.limit(0), labels).count() == 0
    assert toxicity.clean(docs, labels.limit(0)).count() == 5
