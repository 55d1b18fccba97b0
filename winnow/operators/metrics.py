"""Accuracy measures, purity, contamination and approximation error."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from winnow.functions.textops import words
from winnow.plans.settle import bounded

GROUPS = ("selector", "task", "seed")


def accuracy(pred: DataFrame, by: tuple[str, ...] = GROUPS) -> DataFrame:
    """(by, accuracy) from rows with label and predicted."""
    return pred.groupBy(*by).agg(F.avg((F.col("predicted") == F.col("label")).cast("int")).alias("accuracy"))


def class_counts(pred: DataFrame, by: tuple[str, ...] = GROUPS) -> DataFrame:
    """(by, class, tp, fp, fn, support)."""
    both = pred.select(*by, F.explode(F.array(F.struct(F.col("label").alias("c"), F.lit(1).alias("g")), F.struct(F.col("predicted").alias("c"), F.lit(0).alias("g")))).alias("x"), (F.col("label") == F.col("predicted")).alias("hit"))
    one = lambda cond: F.sum(F.when(cond, 1).otherwise(0))
    return both.groupBy(*by, F.col("x.c").alias("class")).agg(
        one((F.col("x.g") == 1) & F.col("hit")).alias("tp"), one((F.col("x.g") == 0) & ~F.col("hit")).alias("fp"), one((F.col("x.g") == 1) & ~F.col("hit")).alias("fn"), one(F.col("x.g") == 1).alias("support")
    )


def f1(pred: DataFrame, average: str = "macro", by: tuple[str, ...] = GROUPS, positive: str = "1") -> DataFrame:
    """(by, f1): macro is the plain mean over classes, weighted goes by support, micro sums the counts, binary takes one class.

    A class with nothing predicted and nothing true has F1 0.
    """
    c = class_counts(pred, by).withColumn("f", F.coalesce(F.try_divide(2.0 * F.col("tp"), 2 * F.col("tp") + F.col("fp") + F.col("fn")), F.lit(0.0)))
    if average == "macro":
        value = F.avg("f")
    elif average == "weighted":
        value = F.sum(F.col("f") * F.col("support")) / F.sum("support")
    elif average == "micro":
        value = F.coalesce(F.try_divide(2.0 * F.sum("tp"), 2 * F.sum("tp") + F.sum("fp") + F.sum("fn")), F.lit(0.0))
    elif average == "binary":
        value = F.coalesce(F.max(F.when(F.col("class") == positive, F.col("f"))), F.lit(0.0))
    else:
        raise ValueError("average is macro, weighted, micro or binary")
    return c.groupBy(*by).agg(value.alias("f1"))


def span_f1(pred: DataFrame, gold: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """(by, type, tp, fp, fn, f1) of exact span matches; rows are by, doc_id, start, stop, type."""
    keys = [*by, "doc_id", "start", "stop", "type"]
    p, g = pred.select(*keys).distinct().withColumn("p", F.lit(1)), gold.select(*keys).distinct().withColumn("g", F.lit(1))
    j = p.join(g, keys, "full_outer")
    out = j.groupBy(*by, "type").agg(F.count_if(F.col("p").isNotNull() & F.col("g").isNotNull()).alias("tp"), F.count_if(F.col("g").isNull()).alias("fp"), F.count_if(F.col("p").isNull()).alias("fn"))
    return out.withColumn("f1", F.coalesce(F.try_divide(2.0 * F.col("tp"), 2 * F.col("tp") + F.col("fp") + F.col("fn")), F.lit(0.0)))


def task_average(results: DataFrame, value: str = "value", by: tuple[str, ...] = ("selector",)) -> DataFrame:
    """Mean over tasks of the tasks' means over seeds, with the population deviation across tasks."""
    per_task = results.groupBy(*by, "task").agg(F.avg(value).alias("v"))
    return per_task.groupBy(*by).agg(F.avg("v").alias("average"), F.stddev_pop("v").alias("sd_tasks"))


def over_seeds(results: DataFrame, value: str = "value", by: tuple[str, ...] = ("selector", "task")) -> DataFrame:
    return results.groupBy(*by).agg(F.count(value).alias("runs"), F.avg(value).alias("mean"), F.stddev_samp(value).alias("sd"), F.stddev_pop(value).alias("sd_pop"))


def win_rate(results: DataFrame, value: str = "value", ties: str = "half", with_self: str = "exclude") -> DataFrame:
    """(selector, win_rate): share of (opponent, task) pairs won, in percent; ties count half, or not at all (strict).

    with_self='win' counts a selector's meeting with itself as won.
    """
    a = results.select(F.col("selector").alias("me"), "task", F.col(value).alias("x"))
    b = results.select(F.col("selector").alias("you"), F.col("task").alias("t"), F.col(value).alias("y"))
    met = a.join(b, (F.col("task") == F.col("t")) & (F.col("me") != F.col("you") if with_self == "exclude" else F.lit(True)))
    point = F.when(F.col("me") == F.col("you"), 1.0).when(F.col("x") > F.col("y"), 1.0).when((F.col("x") == F.col("y")) & F.lit(ties == "half"), 0.5).otherwise(0.0)
    return met.groupBy(F.col("me").alias("selector")).agg((F.lit(100.0) * F.avg(point)).alias("win_rate"))


def delta_pct(averages: DataFrame, base: str = "base_only", value: str = "average") -> DataFrame:
    """``averages`` plus delta_pct against the base selector's row."""
    b = averages.where(F.col("selector") == base).select(F.col(value).alias("_b")).limit(1)
    return averages.crossJoin(F.broadcast(b)).withColumn("delta_pct", F.lit(100.0) * (F.col(value) / F.col("_b") - 1)).drop("_b")


def choice_accuracy(scored: DataFrame, score: str = "score", by: tuple[str, ...] = ()) -> DataFrame:
    """Share of items whose best-scored candidate is right; rows are item, candidate, is_true, score. The first candidate wins ties."""
    best = scored.groupBy(*by, "item").agg(F.max_by("is_true", F.struct(F.round(score, 9), -F.col("candidate"))).alias("hit"))
    return best.groupBy(*by).agg(F.count(F.lit(1)).alias("items"), F.avg(F.col("hit").cast("int")).alias("accuracy"))


def mc1(scored: DataFrame, score: str = "score") -> DataFrame:
    return choice_accuracy(scored, score)


def mc2(scored: DataFrame, score: str = "score") -> DataFrame:
    """Mean over items of the probability mass on true candidates, by softmax within the item."""
    w = Window.partitionBy("item")
    e = scored.withColumn("_e", F.exp(F.col(score) - F.max(score).over(w)))
    per = e.groupBy("item").agg((F.sum(F.when(F.col("is_true"), F.col("_e")).otherwise(0.0)) / F.sum("_e")).alias("mass"))
    return per.agg(F.count(F.lit(1)).alias("items"), F.avg("mass").alias("mc2"))


def purity(selected: DataFrame, labels: DataFrame) -> DataFrame:
    """Among labelled documents: quality and toxic shares of the choice and of all, lift, precision and recall."""
    j = labels.join(selected.select("doc_id").distinct().withColumn("_in", F.lit(1)), "doc_id", "left")
    chosen = F.col("_in").isNotNull()
    r = j.agg(
        F.count(F.lit(1)).alias("labelled"),
        F.count_if(chosen).alias("chosen"),
        F.avg("quality").alias("quality_all"),
        F.avg(F.when(chosen, F.col("quality"))).alias("quality_chosen"),
        F.avg(F.when(chosen, F.col("toxic"))).alias("toxic_chosen"),
        F.try_divide(F.count_if(chosen & (F.col("quality") == 1)), F.count_if(F.col("quality") == 1)).alias("recall"),
    )
    return r.withColumn("lift", F.try_divide(F.col("quality_chosen"), F.col("quality_all")))


def auc(scores: DataFrame, labels: DataFrame, score: str, label: str = "quality") -> DataFrame:
    """Area under the curve by rank sums, ties shared; null scores are left out."""
    from winnow.operators.quantiles import levels

    j = scores.where(F.col(score).isNotNull()).join(labels.select("doc_id", label), "doc_id")
    one = lambda x: F.when(F.col(label) == x, 1).otherwise(0)
    at = levels(j, score, p=one(1), n=one(0))
    r = at.agg(F.sum(F.col("p") * (F.col("_lt") + 1 + F.col("_le")) / 2).alias("r"), F.sum("p").alias("p"), F.sum("n").alias("n"))
    return r.select(F.try_divide(F.col("r") - F.col("p") * (F.col("p") + 1) / 2, F.col("p") * F.col("n")).alias("auc"))


def contamination(docs: DataFrame, benchmark: DataFrame, k: int = 8) -> DataFrame:
    """(doc_id, item_id) of documents that hold a whole passage.

    A passage is found by hashes of its first k words: documents' k-grams are joined with the passages' first
    grams, and what meets is verified on the text. Passages of fewer than k words are found by all their words.
    """
    import pyspark.sql.functions as f

    items = benchmark.select("item_id", f.col("text").alias("passage"), words("text").alias("w")).where(f.size("w") > 0)
    # passages begin inside the word stream, but a document's word may extend beyond the passage's edge
    first = items.select("item_id", "passage", f.least(f.lit(k), f.greatest(f.size("w") - 2, f.lit(1))).alias("len"), "w")
    first = first.select("item_id", "passage", "len", f.xxhash64(f.array_join(f.slice("w", f.when(f.size("w") > 2, 2).otherwise(1), f.col("len")), " ")).alias("g"))
    lengths = [r["len"] for r in first.select("len").distinct().collect()]  # k numbers at most
    w = words("text")
    grams = None

    def windows(n: int):
        return f.transform(f.sequence(f.lit(1), f.greatest(f.size("w") - n + 1, f.lit(1))), lambda i: f.xxhash64(f.array_join(f.slice("w", i, f.lit(n)), " ")))

    for n in lengths:
        some = windows(n)
        part = docs.select("doc_id", w.alias("w")).where(f.size("w") > 0).select("doc_id", f.explode(f.array_distinct(some)).alias("g"))
        grams = part if grams is None else grams.unionAll(part)
    if grams is None:
        return docs.select("doc_id", f.lit(None).cast("long").alias("item_id")).where(f.lit(False))
    met = grams.join(bounded(first.select("item_id", "g")), "g").select("doc_id", "item_id").distinct()
    j = met.join(docs.select("doc_id", "text"), "doc_id").join(bounded(items.select("item_id", "passage")), "item_id")
    return j.where(f.contains("text", "passage")).select("doc_id", "item_id")


def rank_error(df: DataFrame, col: str, method: str = "approx") -> DataFrame:
    """One row: the largest and mean shift of a quantile under an approximate grid."""
    from winnow.operators.quantiles import normalise

    both = normalise(normalise(df, col, "exact", "_exact"), col, method, "_near")
    return both.agg(F.max(F.abs(F.col("_exact") - F.col("_near"))).alias("largest"), F.avg(F.abs(F.col("_exact") - F.col("_near"))).alias("mean"))


def dedup_recall(found: DataFrame, true_pairs: DataFrame) -> DataFrame:
    """Share of true pairs (a, b) whose ends have the same keeper."""
    k = found.select("doc_id", "keeper")
    a, b = (k.select(F.col("doc_id").alias(x), F.col("keeper").alias(f"k{x}")) for x in "ab")
    j = true_pairs.join(a, "a", "left").join(b, "b", "left")
    return j.agg(F.count(F.lit(1)).alias("pairs"), F.avg(F.coalesce(F.col("ka") == F.col("kb"), F.lit(False)).cast("int")).alias("recall"))


def new_term_rate(docs: DataFrame, known: DataFrame) -> DataFrame:
    """One row: distinct terms of ``docs`` and the share that (term, ...) doesn't know."""
    t = docs.select(F.explode(words("text")).alias("term")).distinct()
    j = t.join(known.select("term").distinct().withColumn("_k", F.lit(1)), "term", "left")
    return j.agg(F.count(F.lit(1)).alias("terms"), F.avg(F.col("_k").isNull().cast("int")).alias("new_rate"))
