"""Declared schemas, table readers, sinks and stores."""

from __future__ import annotations

import json
from pathlib import PurePosixPath

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

SCHEMAS = {
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "labels": "doc_id long, quality int, toxic int",
    "benchmark": "item_id long, text string",
    "conversations": "conv_id long, turn long, role string, text string",
    "pages": "page_id long, url string, html string",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "events": "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string",
}
FORMATS = ("parquet", "json", "csv", "orc")


def read_table(spark: SparkSession, folder: str, name: str) -> DataFrame:
    """A table with its declared schema if it has one, so nothing is inferred and columns prune in the scan."""
    return spark.read.parquet(f"{folder}/{name}.parquet") if name not in SCHEMAS else spark.read.schema(SCHEMAS[name]).parquet(f"{folder}/{name}.parquet")


def read_lines(spark: SparkSession, path: str, schema: str) -> DataFrame:
    """JSON lines with a declared schema; malformed lines fail the read."""
    return spark.read.schema(schema).option("mode", "FAILFAST").json(path)


def read_filings(spark: SparkSession, path: str) -> DataFrame:
    """(path, text) of whole text files."""
    return spark.read.text(path, wholetext=True).select(F.input_file_name().alias("path"), F.col("value").alias("text"))


def write_as(df: DataFrame, path: str, kind: str) -> None:
    if kind not in FORMATS:
        raise ValueError(f"format must be one of {FORMATS}")
    writer = df.write.mode("overwrite")
    writer = writer.option("header", True).option("quoteAll", True).option("escape", '"') if kind == "csv" else writer
    writer.format(kind).save(path)


def read_as(spark: SparkSession, path: str, kind: str, schema: str) -> DataFrame:
    reader = spark.read.schema(schema)
    reader = reader.option("header", True).option("multiLine", True).option("escape", '"') if kind == "csv" else reader
    return reader.format(kind).load(path)


def write_shards(selected: DataFrame, path: str, tokens_per_shard: int, seed: int = 7, tokens: str = "n_tokens") -> DataFrame:
    """Writes ``selected`` as JSON lines in shards of about equal tokens, in an order shuffled by a seeded hash.

    Rows are dealt to shards by the hash, of which there are total tokens / tokens_per_shard, so shards are equal
    up to the law of large numbers and no global order is needed. Returns the manifest (shard, docs, tokens).
    """
    from winnow.functions.textops import hash_uniform

    total = selected.agg(F.coalesce(F.sum(tokens), F.lit(0)).alias("t")).first()["t"]
    n = max(1, -(-int(total) // tokens_per_shard))
    dealt = selected.withColumn("_u", hash_uniform("doc_id", seed)).withColumn("shard", F.floor(F.col("_u") * n).cast("int"))
    ordered = dealt.repartitionByRange("shard", "_u").sortWithinPartitions("shard", "_u").drop("_u")
    ordered.write.mode("overwrite").partitionBy("shard").json(path)
    return dealt.groupBy("shard").agg(F.count(F.lit(1)).alias("docs"), F.sum(tokens).cast("long").alias("tokens"))


#: The reported continued-training settings, as hand-off facts.
TRAINING = {"epochs": 1, "precision": "bf16", "learning_rate": 3e-05, "large_model": {"learning_rate": 1.2e-05, "batch": 512}}


def write_manifest(spark: SparkSession, path: str, recipe: dict, shards: DataFrame) -> dict:
    """A one-row JSON file: the recipe, the training settings and totals. The shard list, which grows with the corpus, is written beside it as JSON lines."""
    total = shards.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum("tokens"), F.lit(0)).alias("t"), F.coalesce(F.sum("docs"), F.lit(0)).alias("d")).first()
    body = {"recipe": recipe, "training": TRAINING, "tokens": int(total["t"]), "docs": int(total["d"]), "shards": int(total["n"])}
    spark.createDataFrame([(json.dumps(body, sort_keys=True),)], "value string").coalesce(1).write.mode("overwrite").text(path)
    shards.write.mode("overwrite").json(f"{path}-shards")
    return body


def save_metrics(metrics: DataFrame, name: str, snapshot: str, buckets: int = 16) -> None:
    """The metric table as a bucketed table, one partition per snapshot, so later joins on doc_id need no shuffle."""
    metrics.withColumn("snapshot", F.lit(snapshot)).write.mode("overwrite").partitionBy("snapshot").bucketBy(buckets, "doc_id").sortBy("doc_id").saveAsTable(name)


def save_model(spark: SparkSession, path: str, counts: DataFrame, meta: dict) -> None:
    """Counts as Parquet with a JSON manifest."""
    base = PurePosixPath(path) if "://" not in path else None
    counts.write.mode("overwrite").parquet(f"{base or path}/counts")
    spark.createDataFrame([(json.dumps(meta, sort_keys=True),)], "value string").coalesce(1).write.mode("overwrite").text(f"{base or path}/manifest")


def load_model(spark: SparkSession, path: str) -> tuple[DataFrame, dict]:
    return spark.read.parquet(f"{path}/counts"), json.loads(spark.read.text(f"{path}/manifest").first()["value"])


def shard_tokens_spread(manifest: DataFrame) -> DataFrame:
    """Each shard's tokens against the mean of all."""
    return manifest.withColumn("ratio", F.col("tokens") / F.avg("tokens").over(Window.partitionBy()))
