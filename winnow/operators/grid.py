"""Many continued models side by side: their counts from one pass over the corpus, their few-shot results from one over the tests.

Defined cases are those of ``fewshot`` and ``lm``. A text's likelihood under a model is the same for every class, so it is left out of
the classes' scores here; the larger class wins where scores agree to six decimals. Ids of tests are taken to be distinct.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from winnow.functions.textops import words
from winnow.operators import fewshot, lm
from winnow.plans.settle import bounded, settle, stored

#: Models of one grid; each is a bit of a long.
MOST = 62


@dataclass(frozen=True)
class Models:
    """Unigram counts (term, c0, c1, ...) of models that continue one base, and each one's total and vocabulary."""

    counts: DataFrame
    totals: tuple[int, ...]
    vocabularies: tuple[int, ...]
    alpha: float

    def __len__(self) -> int:
        return len(self.totals)

    def p1(self, i: int) -> Column:
        return (F.coalesce(F.col(f"c{i}"), F.lit(0)) + F.lit(self.alpha)) / F.lit(self.totals[i] + self.alpha * (self.vocabularies[i] + 1))


def members(chosen: list[DataFrame]) -> DataFrame:
    """(doc_id, models): the bits of the selections that hold a document."""
    if len(chosen) > MOST:
        raise ValueError(f"at most {MOST} models at a time")
    rows = reduce(lambda a, b: a.unionAll(b), [c.select("doc_id", F.lit(1 << i).cast("long").alias("m")) for i, c in enumerate(chosen)])
    return settle(rows.groupBy("doc_id").agg(F.bit_or("m").alias("models")))


def continued(base: lm.Model, texts: DataFrame, n: int) -> Models:
    """The unigram models after one epoch each of the ``texts`` (models, text) whose bits name them."""
    own = texts.select("models", F.explode(words("text")).alias("term")).groupBy("models", "term").agg(F.count(F.lit(1)).alias("c"))
    both = own.unionByName(base.unigrams.select(F.lit((1 << n) - 1).cast("long").alias("models"), "term", "c"))
    of = lambda i: F.sum(F.when(F.col("models").bitwiseAND(F.lit(1 << i)) != 0, F.col("c")).otherwise(F.lit(0))).alias(f"c{i}")
    counts = stored(both.groupBy("term").agg(*[of(i) for i in range(n)]))
    sums = counts.agg(*[F.coalesce(F.sum(f"c{i}"), F.lit(0)).alias(f"t{i}") for i in range(n)], *[F.count_if(F.col(f"c{i}") > 0).alias(f"v{i}") for i in range(n)]).first()
    return Models(counts, tuple(int(sums[f"t{i}"]) for i in range(n)), tuple(int(sums[f"v{i}"]) for i in range(n)), base.alpha)


def confusions(tests: DataFrame, shots: DataFrame, models: Models, mu: float = fewshot.MU, classes: tuple[str, ...] = ("0", "1")) -> DataFrame:
    """(model, task, seed, label, predicted, n) for test documents (doc_id, text, golds: array of task and label).

    The classes' scores are those of ``fewshot.classify`` less the text's likelihood. What the few shots hold goes to every task
    as arrays, and a document's scores are taken within its row, so nothing the size of the tests is shuffled.
    """
    classes, n_models = tuple(sorted(classes)), len(models)
    seen = settle(fewshot.bag(shots, "seed", "task", "label"))
    held = {(r["seed"], r["task"], r["label"]): r["n"] for r in shots.groupBy("seed", "task", "label").agg(F.count(F.lit(1)).alias("n")).collect()}
    pairs = sorted({k[:2] for k in held})
    at = {(s, t, c): len(classes) * p + k for p, (s, t) in enumerate(pairs) for k, c in enumerate(classes)}
    found = sorted((r["term"], at[key], r["n"]) for r in seen.toLocalIterator() if (key := (r["seed"], r["task"], r["label"])) in at)
    known = {r["term"]: r[1:] for r in models.counts.join(F.broadcast(seen.select("term").distinct()), "term", "left_semi").toLocalIterator()}
    none = (0,) * n_models
    combo, k = np.array([x[1] for x in found], np.int64), np.array([x[2] for x in found], np.float64)
    c = np.array([known.get(x[0], none) for x in found], np.float64).reshape(-1, n_models).T
    p = (c + models.alpha) / (np.array(models.totals) + models.alpha * (np.array(models.vocabularies) + 1))[:, None]
    gain = np.log((k + mu * p) / (mu * p))
    rows_of: dict[str, tuple[int, int]] = {}
    for i, (term, _, _) in enumerate(found):
        rows_of[term] = (rows_of.get(term, (i, i))[0], i + 1)
    number = np.array([held.get((s, t, c), 0) for s, t in pairs for c in classes], np.float64)
    total = number.reshape(-1, len(classes)).sum(1).repeat(len(classes))
    fixed = np.log((number + 1) / (total + len(classes)))
    slope = np.log(mu / (np.bincount(combo, k, len(at)) + mu))
    of_task = {t: np.array([p for p, x in enumerate(pairs) if x[1] == t]) for t in {t for _, t in pairs}}
    shared = tests.sparkSession.sparkContext.broadcast((rows_of, combo, gain, fixed, slope, of_task, pairs, classes))

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows_of, combo, gain, fixed, slope, of_task, pairs, classes = shared.value
        n_models, n_classes, sums = len(gain), len(classes), {}
        for b in batches:
            for start in range(0, b.num_rows, 64):  # bounds the word lists held at a time
                part = b.slice(start, 64)
                for w, golds in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                    hits = [(*rows_of[t], n) for t, n in Counter(w).items() if t in rows_of]
                    score = np.tile(fixed + len(w) * slope, (n_models, 1))
                    if hits:
                        which = np.concatenate([np.arange(i, j) for i, j, _ in hits])
                        times = np.concatenate([np.full(j - i, float(n)) for i, j, n in hits])
                        to = combo[which]
                        for m in range(n_models):
                            score[m] += np.bincount(to, gain[m, which] * times, len(fixed))
                    score = np.round(score, 6).reshape(n_models, -1, n_classes)
                    best = n_classes - 1 - score[:, :, ::-1].argmax(2)
                    for g in golds:
                        if g["task"] in of_task:
                            into = sums.setdefault((g["task"], g["label"]), np.zeros((n_models, len(of_task[g["task"]]), n_classes), np.int64))
                            np.put_along_axis(into, (chosen := best[:, of_task[g["task"]], None]), np.take_along_axis(into, chosen, 2) + 1, 2)
        rows = [(m, task, pairs[of_task[task][p]][0], label, classes[c], int(into[m, p, c])) for (task, label), into in sums.items() for m, p, c in np.argwhere(into)]
        if rows:
            kinds = [pa.int32(), pa.string(), pa.int32(), pa.string(), pa.string(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows, strict=True), kinds, strict=True)], names=["model", "task", "seed", "label", "predicted", "n"])

    kinds = "model int, task string, seed int, label string, predicted string, n long"
    out = tests.select(words("text").alias("w"), "golds").mapInArrow(counted, kinds)
    return out.groupBy("model", "task", "seed", "label", "predicted").agg(F.sum("n").alias("n"))


def class_f1(confused: DataFrame) -> DataFrame:
    """(model, task, seed, f1, accuracy) from ``confusions``: the plain mean of F1 over the classes that are true or predicted."""
    by = ["model", "task", "seed"]
    hit = F.col("label") == F.col("predicted")
    sides = F.explode(F.array(F.struct(F.col("label").alias("c"), F.lit(True).alias("gold")), F.struct(F.col("predicted").alias("c"), F.lit(False).alias("gold")))).alias("x")
    each = confused.select(*by, "n", hit.alias("hit"), sides).groupBy(*by, "x.c").agg(F.sum(F.when(F.col("hit"), F.col("n")).otherwise(F.lit(0))).alias("both"), F.sum("n").alias("all"))
    # both counts every hit twice, once a side, and so does all
    f = each.groupBy(*by).agg(F.avg(F.coalesce(F.try_divide(F.col("both").cast("double"), F.col("all")), F.lit(0.0))).alias("f1"))
    right = confused.groupBy(*by).agg((F.sum(F.when(hit, F.col("n")).otherwise(F.lit(0))) / F.sum("n")).alias("accuracy"))
    return f.join(right, by)


def entity_f1(shots: DataFrame, gold: DataFrame, tokens: DataFrame, models: Models) -> DataFrame:
    """(model, seed, f1): ``fewshot.entity_f1`` under each model. Candidates are counted by their string before the models meet them."""
    each = range(len(models))
    own = settle(shots.select("seed", "doc_id").join(gold.select("doc_id", "type", "m"), "doc_id").select("seed", "type", "m", fewshot.shape().alias("head")).distinct())
    true = settle(gold.join(tokens.select("doc_id").distinct(), "doc_id", "left_semi").select("doc_id", "start", "stop", "type").distinct())
    held = tokens.withColumn("head", fewshot.shape()).join(bounded(own.select("head").distinct()), "head", "left_semi")
    marks = true.groupBy("doc_id", "start", "stop").agg(F.array_sort(F.collect_set("type")).alias("types"))
    strings = settle(held.join(marks, ["doc_id", "start", "stop"], "left").groupBy("m", "head", "types").agg(F.count(F.lit(1)).alias("n")))
    term = strings.select("m").unionAll(own.select("m")).distinct().select("m", F.explode(words("m")).alias("term"))
    known = settle(term.join(bounded(models.counts), "term", "left").groupBy("m").agg(*[F.avg(-F.log(models.p1(i))).alias(f"s{i}") for i in each]))
    least = own.join(known, "m", "left").groupBy("seed", "type").agg(*[F.min(F.coalesce(f"s{i}", F.lit(0.0))).alias(f"l{i}") for i in each])
    learned = settle(own.select("seed", "type", "head").distinct().join(least, ["seed", "type"]))
    met = strings.join(known, "m").join(bounded(learned), "head")
    tagged = lambda i: F.round(f"s{i}", 9) >= F.round(f"l{i}", 9)
    hit = F.coalesce(F.array_contains("types", F.col("type")), F.lit(False))
    sums = met.groupBy("seed").agg(*[F.sum(F.when(tagged(i), F.col("n"))).alias(f"p{i}") for i in each], *[F.sum(F.when(tagged(i) & hit, F.col("n"))).alias(f"t{i}") for i in each])
    g = true.count()
    sizes = shots.select("seed").distinct().join(sums, "seed", "left").na.fill(0)
    f = F.explode(F.array(*[F.struct(F.lit(i).alias("model"), F.coalesce(F.try_divide(2.0 * F.col(f"t{i}"), F.col(f"p{i}") + F.lit(g)), F.lit(0.0)).alias("f1")) for i in each])).alias("x")
    return sizes.select("seed", f).select("x.model", "seed", "x.f1")


#: Likelihoods are summed as whole numbers of this size, so that their sums don't depend on the order of the words.
UNIT = 2.0**-40


def choices(pairs: dict[str, DataFrame], models: Models, mu: float = fewshot.CACHE) -> DataFrame:
    """(model, task, items, accuracy, accuracy_norm, mass) of multiple-choice tasks (item, candidate, prompt, text, is_true, at, owner) under each model.

    Scores are those of ``fewshot.conditional_ll``. A text's likelihood without its prompt is taken once, where it is its own item's
    true one, and met by rank from the items it distracts; only words that prompt and text share are counted for each pair. A copy's text
    (owner null) is counted in its own pair. Words meet the models by a join, so neither has to fit anywhere. Null texts have no words; a
    task without items has 0 items and null figures.
    """
    names, each = list(pairs), range(len(models))
    kinds = [pa.int32(), pa.int64(), pa.int32(), pa.int64(), pa.bool_(), pa.string(), pa.int64(), pa.int64(), pa.int64()]
    cols = ["task", "at", "candidate", "owner", "is_true", "term", "n", "k", "size"]

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
        for b in batches:
            for start in range(0, b.num_rows, 64):  # bounds the word lists held at a time
                for task, at, candidate, owner, true, octets, prompt, text in zip(*(c.to_pylist() for c in b.slice(start, 64).columns), strict=True):
                    held, own = Counter(prompt), Counter(text)
                    yield task, at, candidate, owner, true, None, len(text), octets, len(prompt)
                    if candidate == 0 or owner is None:
                        alone = candidate if owner is None else -1
                        yield from ((task, at, alone, None, None, t, n, 0, 0) for t, n in own.items())
                    yield from ((task, at, candidate, None, None, t, n, held[t], 0) for t, n in own.items() if t in held)

    def unfolded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from fewshot._handed_on(rows(batches), kinds, cols)

    octets = F.coalesce(F.octet_length("text"), F.lit(0)).cast("long")
    flat = reduce(lambda a, b: a.unionAll(b), [p.select(F.lit(i).alias("task"), F.col("at").cast("long"), F.col("candidate").cast("int"), F.col("owner").cast("long"), "is_true", octets.alias("octets"), words("prompt").alias("prompt"), words("text").alias("text")) for i, p in enumerate(pairs.values())])
    flat = stored(flat.mapInArrow(unfolded, "task int, at long, candidate int, owner long, is_true boolean, term string, n long, k long, size long"))
    met = flat.where("term IS NOT NULL").select("task", "at", "candidate", "term", "n", "k").join(models.counts, "term", "left")
    # of a word that the prompt holds, what the prompt adds to ln p
    gain = lambda i: F.when(F.col("k") > 0, F.log((F.col("k") + F.lit(mu) * models.p1(i)) / (F.lit(mu) * models.p1(i)))).otherwise(F.log(models.p1(i)))
    sums = settle(met.groupBy("task", "at", "candidate").agg(*[F.sum(F.col("n") * F.round(gain(i) / F.lit(UNIT)).cast("long")).alias(f"s{i}") for i in each]))
    alone = sums.where("candidate = -1").select("task", F.col("at").alias("owner"), F.array(*[f"s{i}" for i in each]).alias("alone"))
    shared = sums.where("candidate >= 0").select("task", "at", "candidate", F.array(*[f"s{i}" for i in each]).alias("shared"))
    of = flat.where("term IS NULL").drop("term").join(alone, ["task", "owner"], "left").join(shared, ["task", "at", "candidate"], "left")
    none = F.array_repeat(F.lit(0).cast("long"), len(models))
    added = F.zip_with(F.coalesce("alone", none), F.coalesce("shared", none), lambda a, b: (a + b) * F.lit(UNIT))
    fixed = F.col("n") * F.log(F.lit(mu) / (F.col("size") + F.lit(mu)))
    cand = F.struct((-F.col("candidate")).alias("c"), "is_true", F.greatest("k", F.lit(1)).alias("octets"), F.transform(added, lambda x: x + fixed).alias("s"))
    items = of.groupBy("task", "at").agg(F.collect_list(cand).alias("cands"))
    one = items.select("task", "cands", F.explode(F.sequence(F.lit(0), F.lit(len(models) - 1))).alias("model"))
    one = one.select("task", "model", F.transform("cands", lambda x: F.struct(F.get(x["s"], F.col("model")).alias("s"), x["c"].alias("c"), x["is_true"].alias("is_true"), x["octets"].alias("octets"))).alias("x"))
    first = lambda score: F.array_max(F.transform("x", lambda x: F.struct(F.round(score(x), 9).alias("s"), x["c"].alias("c"), x["is_true"].alias("hit"))))["hit"].cast("int")
    top = F.array_max(F.transform("x", lambda x: x["s"]))
    one = one.select("task", "model", "x", first(lambda x: x["s"]).alias("hit"), first(lambda x: x["s"] / x["octets"]).alias("hit_norm"), top.alias("top"))
    summed = lambda some: F.aggregate("x", F.lit(0.0), lambda a, x: a + F.when(some(x), F.exp(x["s"] - F.col("top"))).otherwise(F.lit(0.0)))
    mass = summed(lambda x: x["is_true"]) / summed(lambda x: F.lit(True))
    found = one.groupBy("model", "task").agg(F.count(F.lit(1)).alias("items"), F.avg("hit").alias("accuracy"), F.avg("hit_norm").alias("accuracy_norm"), F.avg(mass).alias("mass"))
    all_of = pairs[names[0]].sparkSession.createDataFrame([(m, i, t) for m in each for i, t in enumerate(names)], "model int, task int, name string")
    out = all_of.join(F.broadcast(found), ["model", "task"], "left")  # one row for each model and task
    return out.select("model", F.col("name").alias("task"), F.coalesce("items", F.lit(0).cast("long")).alias("items"), "accuracy", "accuracy_norm", "mass")
