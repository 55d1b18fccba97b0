"""Spread of token types within a document."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from winnow.functions.textops import once, pieces
from winnow.functions.typing_rules import ENTITIES, POS, entity_tags, pos_tags
from winnow.functions.udfs import word_class_entropy

ENTITY_TOKEN = r"[^ \t\r\n]+"


def tags(text: str, tagset: str = "pos") -> Column:
    if tagset == "pos":
        return pos_tags(pieces(text))
    if tagset == "entity":
        tokens = F.coalesce(F.regexp_extract_all(F.col(text), F.lit(ENTITY_TOKEN), F.lit(0)), F.array().cast("array<string>"))
        return F.filter(entity_tags(tokens), lambda t: t != "OTHER")
    raise ValueError("tagset must be pos or entity")


def entropy_of(tag_array: Column, types: tuple[str, ...]) -> Column:
    """-sum p ln p over the types of one row's tags, without a shuffle; null where the row has no tags."""
    counts = F.transform(F.array(*[F.lit(t) for t in types]), lambda t: F.size(F.filter(tag_array, lambda x: x == t)).cast("double"))
    n = F.size(tag_array).cast("double")
    h = F.aggregate(counts, F.lit(0.0), lambda s, c: s - F.when(c > 0, c / n * F.log(c / n)).otherwise(F.lit(0.0)))
    return F.when(n > 0, F.greatest(h, F.lit(0.0)))


def entropy_column(text: str, tagset: str = "pos") -> Column:
    """Entropy in nats of a text column: word classes by the Arrow function, entities by expression; null without tags."""
    return word_class_entropy(text) if tagset == "pos" else entropy_of(tags(text, tagset), ENTITIES[:-1])


def with_entropy(docs: DataFrame, tagset: str = "pos", text: str = "text", base: float | None = None, normalise: bool = False, native: bool = False) -> DataFrame:
    """``docs`` plus entropy, computed once per row. ``native`` takes the expression for word classes too, its twin in tests."""
    types = POS if tagset == "pos" else ENTITIES[:-1]
    if native or tagset == "entity":
        out = once(once(docs, _tags=tags(text, tagset)), entropy=entropy_of(F.col("_tags"), types)).drop("_tags")
    else:
        out = docs.withColumn("entropy", word_class_entropy(text))
    h = F.col("entropy")
    if normalise:
        h = h / F.log(F.lit(float(len(types))))  # the unit cancels out
    elif base:
        h = h / F.log(F.lit(float(base)))
    return out.withColumn("entropy", F.coalesce(h, F.lit(0.0)) if tagset == "entity" else h)


def type_counts(docs: DataFrame, tagset: str = "pos", text: str = "text") -> DataFrame:
    """(doc_id, tok_type, n), the long form."""
    return docs.select("doc_id", F.explode(tags(text, tagset)).alias("tok_type")).groupBy("doc_id", "tok_type").agg(F.count(F.lit(1)).alias("n"))
