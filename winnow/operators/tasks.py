"""Labelled tasks: the shot pool, the unlabelled seed and few-shot prompts.

Defined cases: documents without label, and labels without document, take no part; a null label is
left out; a null text gives no prompt; equal hashes go by id; empty tables give empty results.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from winnow.functions.textops import hash_uniform, n_tokens

POOL = 50
SHOTS = 5


def labelled(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """(task, doc_id, text, label): quality and toxic of the labelled documents, as strings."""
    joined = docs.select("doc_id", "text").join(labels, "doc_id")
    return joined.unpivot(["doc_id", "text"], ["quality", "toxic"], "task", "label").where("label IS NOT NULL").select("task", "doc_id", "text", F.col("label").cast("string").alias("label"))


def language_tasks(docs: DataFrame, langs: tuple[str, ...] = ("en", "fr", "de", "es")) -> DataFrame:
    """One-against-rest questions about the language."""
    q = F.explode(F.array(*[F.struct(F.lit(f"lang_{x}").alias("task"), (F.col("lang") == x).cast("int").cast("string").alias("label")) for x in langs]))
    return docs.select("doc_id", "text", q.alias("q")).select("q.task", "doc_id", "text", "q.label")


def ranked_pool(tasks: DataFrame, seed: int = 7) -> DataFrame:
    """``tasks`` plus rank from 1 within the task, by seeded hash."""
    w = Window.partitionBy("task").orderBy(hash_uniform("doc_id", seed), "doc_id")
    return tasks.withColumn("rank", F.row_number().over(w))


def shot_pool(tasks: DataFrame, size: int = POOL, seed: int = 7) -> DataFrame:
    """The ``size`` examples of each task that may serve as shots."""
    return ranked_pool(tasks, seed).where(F.col("rank") <= size)


def unlabelled_seed(tasks: DataFrame, size: int = POOL, seed: int = 7) -> DataFrame:
    """(task, seed_id, text): all other examples; the label column is not there any more."""
    return ranked_pool(tasks, seed).where(F.col("rank") > size).select("task", F.col("doc_id").alias("seed_id"), "text")


def seed_tokens(seed: DataFrame) -> DataFrame:
    """Documents and words by task and, with a null task, in all."""
    return seed.rollup("task").agg(F.count(F.lit(1)).alias("docs"), F.sum(n_tokens("text")).alias("words"))


def shots_for(pool: DataFrame, tests: DataFrame, shots: int = SHOTS, seed: int = 1) -> DataFrame:
    """(task, test_id, doc_id, label, text, place): each test item's shots, drawn from the pool by hash of both ids and the seed.

    The pool has a fixed size per task, so a test item meets a bounded number of candidates.
    """
    t = tests.select(F.col("task").alias("_task"), F.col("doc_id").alias("test_id"))
    pairs = F.broadcast(pool.select("task", "doc_id")).join(t, (F.col("task") == F.col("_task")) & (F.col("doc_id") != F.col("test_id")))
    w = Window.partitionBy("task", "test_id").orderBy(hash_uniform(F.concat_ws("-", "doc_id", "test_id"), seed), "doc_id")
    chosen = pairs.withColumn("place", F.row_number().over(w)).where(F.col("place") <= shots).select("task", "test_id", "doc_id", "place")
    return chosen.join(F.broadcast(pool), ["task", "doc_id"]).select("task", "test_id", "doc_id", "label", "text", "place")


def build_prompts(pool: DataFrame, tests: DataFrame, instruction: str, shots: int = SHOTS, seed: int = 1) -> DataFrame:
    """(task, doc_id, prompt) for an external model."""
    chosen = shots_for(pool, tests, shots, seed)
    block = F.concat(F.lit("Text: "), F.col("text"), F.lit("\nAnswer: "), F.col("label"))
    shown = chosen.groupBy("task", "test_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("place", block.alias("b")))), lambda x: x["b"]), "\n\n").alias("shown"))
    joined = tests.select("task", "doc_id", F.col("text").alias("_x")).join(shown.withColumnRenamed("test_id", "doc_id"), ["task", "doc_id"])
    return joined.select("task", "doc_id", F.concat(F.lit(instruction + "\n\n"), "shown", F.lit("\n\nText: "), "_x", F.lit("\nAnswer:")).alias("prompt"))
