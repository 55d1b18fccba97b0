"""Few-shot classification, entity spans and multiple choice under a (continued) language model."""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import reduce
from itertools import islice

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from winnow.functions.textops import words
from winnow.operators import lm
from winnow.plans.settle import bounded, settle

#: Weight of the model against the shots' counts. Shots of a class differ in length, and a light model would let the class with
#: the fewest shot words win every long text; this value keeps the base model's F1 off that corner.
MU = 200_000.0
#: Weight of the model against a prompt's counts in multiple choice.
CACHE = 200.0


def bag(texts: DataFrame, *keys: str, text: str = "text") -> DataFrame:
    return texts.select(*keys, F.explode(words(text)).alias("term")).groupBy(*keys, "term").agg(F.count(F.lit(1)).alias("n"))


def draw_shots(pool: DataFrame, seeds: int = 10, shots: int = 5) -> DataFrame:
    """(seed, task, doc_id, label, text): for each run, ``shots`` examples of each task by hash of id and run."""
    runs = pool.withColumn("seed", F.explode(F.sequence(F.lit(0), F.lit(seeds - 1))))
    key = F.md5(F.concat_ws(":", "doc_id", "task", "seed").cast("binary"))
    w = Window.partitionBy("task", "seed").orderBy(key, "doc_id")
    return runs.withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= shots).select("seed", "task", "doc_id", "label", "text")


def classify(tests: DataFrame, shots: DataFrame, model: lm.Model, mu: float = MU, classes: tuple[str, ...] = ("0", "1")) -> DataFrame:
    """(task, seed, doc_id, label, predicted, margin) for test rows (task, doc_id, label, text).

    A class's score is ln prior + sum over words of ln((n(w, class) + mu * p(w)) / (n(class) + mu)). All words
    first count as unseen in the shots, which needs one likelihood per text; words that the shots hold are then
    corrected, by a join with the shots' few terms. Priors are add-one shares of the shots.
    """
    n_classes = len(classes)
    seen = settle(bag(shots, "seed", "task", "label").withColumnRenamed("n", "k"))
    mass = seen.groupBy("seed", "task", "label").agg(F.sum("k").alias("mass"))
    held = shots.groupBy("seed", "task", "label").agg(F.count(F.lit(1)).alias("held"))
    runs = shots.select("seed", "task").distinct()
    label = F.explode(F.array(*[F.lit(c) for c in classes])).alias("label")
    priors = runs.select("seed", "task", label).join(held, ["seed", "task", "label"], "left").join(mass, ["seed", "task", "label"], "left").na.fill(0)
    total = F.sum("held").over(Window.partitionBy("seed", "task"))
    priors = priors.select("seed", "task", F.col("label").alias("class"), "mass", F.log((F.col("held") + 1.0) / (total + n_classes)).alias("prior"))
    texts = tests.select("doc_id", "text").dropDuplicates(["doc_id"])
    like = settle(lm.log_likelihood(texts, model))
    terms = seen.select(F.col("seed"), F.col("task"), F.col("label").alias("class"), "term", "k").join(model.sized(), "term", "left")
    gain = F.log((F.col("k") + F.lit(mu) * model.p1(F.col("c"))) / (F.lit(mu) * model.p1(F.col("c"))))
    terms = settle(terms.select("seed", "task", "class", "term", gain.alias("gain")))
    found = bag(texts, "doc_id").join(bounded(terms), "term")  # shots per run are few, so are their terms
    corrected = found.groupBy("doc_id", "seed", "task", "class").agg(F.sum(F.col("n") * F.col("gain")).alias("extra"))
    grid = tests.select("task", "doc_id", F.col("label").alias("gold")).join(F.broadcast(priors), "task").join(like, "doc_id", "left")
    scored = grid.join(corrected, ["doc_id", "seed", "task", "class"], "left")
    n = F.coalesce("n_tokens", F.lit(0))
    score = F.col("prior") + F.coalesce("ll", F.lit(0.0)) + n * F.log(F.lit(mu) / (F.col("mass") + F.lit(mu))) + F.coalesce("extra", F.lit(0.0))
    best = scored.withColumn("score", F.round(score, 6)).groupBy("task", "seed", "doc_id").agg(
        F.first("gold").alias("label"), F.max_by("class", F.struct("score", "class")).alias("predicted"), (F.max("score") - F.min("score")).alias("margin")
    )
    return best


def conditional_ll(pairs: DataFrame, model: lm.Model, mu: float = CACHE) -> DataFrame:
    """``pairs`` (item, candidate, prompt, text, ...) plus n_tokens and ll of the text given the prompt.

    p(w | prompt) = (n_prompt(w) + mu * p(w)) / (n_prompt + mu): a cache of the prompt over the model.
    """
    key = ["item", "candidate"]
    prompt = pairs.select(*key, F.size(words("prompt")).alias("size"))
    seen = bag(pairs, *key, text="prompt").withColumnRenamed("n", "k")
    own = bag(pairs, *key).join(seen, [*key, "term"], "left").join(model.sized(), "term", "left").join(prompt, key)
    p = (F.coalesce("k", F.lit(0)) + F.lit(mu) * model.p1(F.col("c"))) / (F.col("size") + F.lit(mu))
    ll = own.groupBy(*key).agg(F.sum("n").alias("n_tokens"), F.sum(F.col("n") * F.log(p)).alias("ll"))
    return pairs.join(ll, key, "left").na.fill({"n_tokens": 0, "ll": 0.0})


def with_scores(scored: DataFrame) -> DataFrame:
    """Rows with score (likelihood) and score_norm (per byte)."""
    return scored.withColumn("score", F.col("ll")).withColumn("score_norm", F.col("ll") / F.greatest(F.octet_length("text"), F.lit(1)))


def with_distractors(items: DataFrame, others: int = 3, placed_too: bool = False) -> DataFrame:
    """(item, candidate, prompt, text, is_true): the items' true texts and those of the items next in hash order.

    The order is taken by range-partitioned ranks, and a neighbour is found by joining on the rank. ``placed_too`` adds the
    rank of the item (at) and of the one whose text it is (owner).
    """
    from winnow.operators.ranking import ranked

    placed = settle(ranked(items.withColumn("_h", F.md5(F.col("item").cast("string").cast("binary"))), [], ["_h", "item"], "_at").drop("_h"))
    n = placed.count()
    each = placed.select("item", "prompt", F.explode(F.sequence(F.lit(0), F.lit(min(others, max(n - 1, 0))))).alias("candidate"), "_at")
    want = each.withColumn("_want", F.pmod(F.col("_at") + F.col("candidate"), F.lit(max(n, 1))))
    texts = placed.select(F.col("_at").alias("_want"), "text")
    more = [F.col("_at").alias("at"), F.col("_want").alias("owner")] if placed_too else []
    return want.join(texts, "_want").select("item", "candidate", "prompt", "text", (F.col("candidate") == 0).alias("is_true"), *more)


def halves(text: str = "text"):
    """A text's first and second half, in words by blanks."""
    w = F.split(F.col(text), " ")
    cut = F.floor(F.size(w) / F.lit(2)).cast("int")
    return F.array_join(F.slice(w, F.lit(1), cut), " "), F.array_join(F.slice(w, cut + 1, F.size(w)), " ")


def page_titles(pages: DataFrame) -> DataFrame:
    """A page's title as prompt, its text as the true candidate."""
    from winnow.operators.curate import html_to_text

    return pages.select(F.col("page_id").alias("item"), F.regexp_extract("html", r"(?s)<title>(.*?)</title>", 1).alias("prompt"), html_to_text("html").alias("text"))


def passage_halves(benchmark: DataFrame) -> DataFrame:
    a, b = halves()
    return benchmark.select(F.col("item_id").alias("item"), a.alias("prompt"), b.alias("text"))


def next_turns(conversations: DataFrame) -> DataFrame:
    """Every turn but a conversation's last as prompt, the next one as the true candidate."""
    w = Window.partitionBy("conv_id").orderBy("turn")
    out = conversations.withColumn("next", F.lead("text").over(w)).where(F.col("next").isNotNull())
    return out.select(F.concat_ws("-", "conv_id", "turn").alias("item"), F.col("text").alias("prompt"), F.col("next").alias("text"))


def copies_as_truths(docs: DataFrame, pairs: DataFrame, placed_too: bool = False) -> DataFrame:
    """(item, candidate, prompt, text, is_true): a document's first half, the second halves of itself and a near copy, and two others.

    ``placed_too`` adds the ranks of ``with_distractors``; a copy's text has no owner.
    """
    a, b = halves()
    cut = docs.select("doc_id", a.alias("first"), b.alias("second"))
    one = pairs.groupBy(F.col("a").alias("item")).agg(F.min("b").alias("copy"))
    items = one.join(cut.withColumnRenamed("doc_id", "item"), "item").select("item", "copy", F.col("first").alias("prompt"), F.col("second").alias("text"))
    if placed_too:
        items = settle(items)
    base = with_distractors(items.select("item", "prompt", "text"), 2, placed_too)
    twin = items.select("item", "copy", "prompt").join(cut.select(F.col("doc_id").alias("copy"), F.col("second").alias("text")), "copy")
    twin = twin.select("item", F.lit(9).alias("candidate"), "prompt", "text", F.lit(True).alias("is_true"))
    if placed_too:
        base = settle(base)
        twin = twin.join(base.where("candidate = 0").select("item", "at"), "item").withColumn("owner", F.lit(None).cast("long"))
    return base.unionByName(twin)


#: The rule's entity shapes, the gold of the span task.
SPANS = {"EMAIL": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9.-]+[.][A-Za-z]{2,}", "IP": r"[0-9]{1,3}[.][0-9]{1,3}[.][0-9]{1,3}[.][0-9]{1,3}", "HEX": r"[0-9a-f]{32,}", "LICENCE": r"(Apache License|MIT License|GPL|CC BY[A-Z-]*)"}


_SPAN = "doc_id long, start long, stop long, type string, m string"
TOKEN = r"[^ \t\r\n]+"


#: Rows that a task's Python holds before it hands them on: a batch of documents unfolds to thousands of times as many.
ROWS_AT_A_TIME = 1 << 15


def _handed_on(rows: Iterator[tuple], kinds: list[pa.DataType], names: list[str]) -> Iterator[pa.RecordBatch]:
    while part := list(islice(rows, ROWS_AT_A_TIME)):
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*part, strict=True), kinds, strict=True)], names=names)


def _texts(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
    for b in batches:
        for at in range(0, b.num_rows, 256):
            yield from zip(*(c.to_pylist() for c in b.slice(at, 256).columns), strict=True)


def _found(docs: DataFrame, shapes: dict[str, str], text: str) -> DataFrame:
    """(doc_id, start, stop, type, m): every occurrence of every shape, in code points from 1, ``stop`` exclusive."""

    def matched(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ready = [(kind, re.compile(p)) for kind, p in shapes.items()]
        rows = ((i, m.start() + 1, m.end() + 1, kind, m[0]) for i, x in _texts(batches) for kind, p in ready for m in p.finditer(x or ""))
        yield from _handed_on(rows, [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string()], [f.split()[0] for f in _SPAN.split(", ")])

    return docs.select("doc_id", text).mapInArrow(matched, _SPAN)


def rule_spans(docs: DataFrame, text: str = "text") -> DataFrame:
    """(doc_id, start, stop, type, m) of the rule's spans, one row per occurrence. Null texts have none."""
    return _found(docs, SPANS, text)


def token_spans(docs: DataFrame, text: str = "text") -> DataFrame:
    """(doc_id, start, stop, m) of a text's tokens between white space, and of neighbours with one blank between them."""

    def spans(texts: Iterator[tuple]) -> Iterator[tuple]:
        token = re.compile(TOKEN)
        for i, x in texts:
            before = None
            for m in token.finditer(x or ""):
                s, e = m.span()
                yield i, s + 1, e + 1, m[0]
                if before and s == before[1] + 1 and x[before[1]] == " ":
                    yield i, before[0] + 1, e + 1, x[before[0] : e]
                before = s, e

    def candidates(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from _handed_on(spans(_texts(batches)), [pa.int64(), pa.int64(), pa.int64(), pa.string()], ["doc_id", "start", "stop", "m"])

    return docs.select("doc_id", text).mapInArrow(candidates, "doc_id long, start long, stop long, m string")


#: How a string of one word becomes its shape. Runs of letters, of digits, then of both in turn.
SHAPE = ((r"[A-Za-z]+", "a"), (r"[0-9]+", "0"), (r"(a0)+a|(0a)+0|(a0)+|(0a)+", "x"))


def shape(m: str = "m") -> Column:
    """What a span is recognised by: its shape, or, where it holds a blank, itself."""
    out = F.col(m)
    for pattern, new in SHAPE:
        out = F.regexp_replace(out, pattern, new)
    return F.when(F.contains(F.col(m), F.lit(" ")), F.col(m)).otherwise(out)


def lexicon_spans(shots: DataFrame, tests: DataFrame) -> DataFrame:
    """(doc_id, start, stop, type): a candidate is tagged wherever it occurs if a shot span has its shape or, of two words, its text."""
    known = bounded(settle(rule_spans(shots).select("type", shape().alias("shape")).distinct()))  # else every candidate would be shuffled
    return token_spans(tests).withColumn("shape", shape()).join(known, "shape").select("doc_id", "start", "stop", "type")


def surprise(strings: DataFrame, model: lm.Model) -> DataFrame:
    """(m, surprise): mean -ln p of a string's words under the model; strings without words are left out."""
    w = strings.select("m").distinct().select("m", F.explode(words("m")).alias("term"))
    return w.join(model.sized(), "term", "left").groupBy("m").agg(F.avg(-F.log(model.p1(F.col("c")))).alias("surprise"))


def entity_f1(shots: DataFrame, gold: DataFrame, tokens: DataFrame, model: lm.Model) -> DataFrame:
    """(seed, f1) of the span task under a model, over exact spans of all types.

    From each run's shots come the spans' shapes and, by type, how little a span's words surprised the model;
    a candidate is tagged if it has a span's shape and surprises the model at least as much. ``gold`` holds the rule's spans of
    all documents, ``tokens`` those of the test documents.
    """
    known = settle(surprise(gold.select("m").unionAll(tokens.select("m")), model))
    own = shots.select("seed", "doc_id").join(gold, "doc_id").join(known, "m", "left").select("seed", "type", shape().alias("head"), F.coalesce("surprise", F.lit(0.0)).alias("s"))
    learned = settle(own.select("seed", "type", "head").distinct().join(own.groupBy("seed", "type").agg(F.min("s").alias("least")), ["seed", "type"]))
    held = tokens.join(known, "m").withColumn("head", shape())
    tagged = held.join(learned, "head").where(F.round("surprise", 9) >= F.round("least", 9)).select("seed", "doc_id", "start", "stop", "type").distinct()
    true = gold.join(tokens.select("doc_id").distinct(), "doc_id", "left_semi").select("doc_id", "start", "stop", "type").distinct()
    hits = tagged.join(true, ["doc_id", "start", "stop", "type"], "left_semi").groupBy("seed").agg(F.count(F.lit(1)).alias("tp"))
    sizes = shots.select("seed").distinct().join(tagged.groupBy("seed").agg(F.count(F.lit(1)).alias("p")), "seed", "left").join(hits, "seed", "left")
    g = true.count()
    return sizes.na.fill(0).select("seed", F.coalesce(F.try_divide(2.0 * F.col("tp"), F.col("p") + F.lit(g)), F.lit(0.0)).alias("f1"))


def weights_on_pool(pool: DataFrame, model: lm.Model, candidates: tuple[float, ...] = (200.0, 2_000.0, 20_000.0, 200_000.0, 2_000_000.0), seeds: int = 5, shots: int = 5) -> DataFrame:
    """(mu, f1): how each weight of the model against the shots does within the shot pool, test rows aside.

    One half of the pool, by hash, gives the shots and the other half is classified.
    """
    from winnow.functions.textops import hash_uniform
    from winnow.operators import metrics

    first = hash_uniform("doc_id", "halves") < 0.5
    drawn, rest = settle(draw_shots(pool.where(first), seeds, shots)), settle(pool.where(~first).select("task", "doc_id", "label", "text"))
    parts = [metrics.f1(classify(rest, drawn, model, mu), "macro", ("task", "seed")).agg(F.lit(float(mu)).alias("mu"), F.round(F.avg("f1"), 6).alias("f1")) for mu in candidates]
    return reduce(lambda a, b: a.unionByName(b), parts)


def general_items(spark: SparkSession, folder: str, docs: DataFrame) -> dict[str, DataFrame]:
    """The four general multiple-choice tasks on the given tables, as scored-to-be pairs with ranks. ``docs`` are the documents, one of each text."""
    from winnow.operators import dedup
    from winnow.sources.tables import read_table

    return {
        "title_to_article": with_distractors(page_titles(read_table(spark, folder, "pages")), placed_too=True),
        "passage_halves": with_distractors(passage_halves(read_table(spark, folder, "benchmark")), placed_too=True),
        "copies_as_truths": copies_as_truths(docs, dedup.resembling_pairs(docs), placed_too=True),
        "next_turn": with_distractors(next_turns(read_table(spark, folder, "conversations")), placed_too=True),
    }
