"""Python functions for what expressions can't say, and the SQL names of the engine's functions."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from winnow.functions.textops import PIECE, WORD
from winnow.functions.typing_rules import CLOSED, ENDINGS, POS, SENTENCE_END


def code_points(text: str):
    """Length by an Arrow-batched function; its native twin is ``length``."""

    @F.pandas_udf("long")
    def length(x: pd.Series) -> pd.Series:
        return x.str.len()

    return length(text)


def chunks(docs: DataFrame, size: int, overlap: int = 0) -> DataFrame:
    """(doc_id, chunk_no, text, n_tokens): windows of ``size`` words, by a table function joined laterally."""
    import regex

    word = regex.compile(WORD)

    @F.udtf(returnType="chunk_no int, text string, n_tokens int")
    class Windows:
        def eval(self, text: str):
            w = word.findall((text or "").lower())
            step = max(1, size - overlap)
            for no, at in enumerate(range(0, len(w), step)):
                yield no, " ".join(w[at : at + size]), len(w[at : at + size])

    spark = docs.sparkSession
    spark.udtf.register("_winnow_windows", Windows)
    docs.select("doc_id", "text").createOrReplaceTempView("_winnow_chunk_docs")
    return spark.sql("SELECT d.doc_id, c.chunk_no, c.text, c.n_tokens FROM _winnow_chunk_docs d, LATERAL _winnow_windows(d.text) c")


def register(spark: SparkSession) -> None:
    """SQL names: word_count(text), hash_uniform(key, seed), tag_entropy(types) as SQL functions, which run as expressions, and type_entropy(text)."""
    spark.sql(r"CREATE OR REPLACE TEMPORARY FUNCTION word_count(t STRING) RETURNS INT RETURN size(regexp_extract_all(lower(t), '[\\p{L}\\p{N}]+', 0))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION hash_uniform(k STRING, s STRING) RETURNS DOUBLE RETURN CAST(conv(substring(md5(CAST(concat(k, ':', s) AS BINARY)), 1, 13), 16, 10) AS BIGINT) / 4503599627370496D")
    listed = ", ".join(f"'{t}'" for t in POS)
    spark.sql(
        f"""CREATE OR REPLACE TEMPORARY FUNCTION tag_entropy(tags ARRAY<STRING>) RETURNS DOUBLE RETURN
        CASE WHEN size(tags) > 0 THEN greatest(aggregate(transform(array({listed}), k -> CAST(size(filter(tags, x -> x = k)) AS DOUBLE)), 0D, (s, c) -> s - CASE WHEN c > 0 THEN c / size(tags) * ln(c / size(tags)) ELSE 0D END), 0D) END"""
    )

    spark.udf.register("type_entropy", F.pandas_udf(entropies, "double"))


class Tagger:
    """The word-class rules in plain Python, with a memo of pieces seen lately: the twin of the column expression."""

    MEMO = 500_000

    def __init__(self):
        import regex

        self.piece = regex.compile(PIECE)
        self.number, self.word = regex.compile(r"^\p{N}"), regex.compile(r"^[\p{L}\p{N}]")
        self.closed = {w: t for t, ws in reversed(CLOSED.items()) for w in ws}
        self.endings = [(tuple(e), t) for t, e in ENDINGS.items()]
        self.caps, self.cap = regex.compile(r"^\p{Lu}{2,}$"), regex.compile(r"^\p{Lu}")
        self.ends = frozenset(SENTENCE_END)
        self.after_end: dict[str, int] = {}
        self.inside: dict[str, int] = {}
        self.index = {t: i for i, t in enumerate(POS)}

    def tag(self, piece: str, first: bool) -> str:
        low = piece.lower()
        if self.number.match(piece):
            return "NUM"
        if not self.word.match(piece):
            return "PUNCT"
        if low in self.closed:
            return self.closed[low]
        for ending, t in self.endings:
            if low.endswith(ending):
                return t
        if self.caps.match(piece):
            return "ALLCAPS"
        if self.cap.match(piece) and not first:
            return "PROPN"
        return "SHORT" if len(piece) <= 3 else "OTHER"

    def counts(self, text: str) -> list[int]:
        """Pieces by type, in the order of the types."""
        n = [0] * len(POS)
        ends, first = self.ends, True
        for x in self.piece.findall(text):
            known = self.after_end if first else self.inside
            k = known.get(x)
            if k is None:
                if len(known) > self.MEMO:
                    known.clear()
                k = known[x] = self.index[self.tag(x, first)]
            n[k] += 1
            first = x in ends
        return n

    def entropy(self, text: str) -> float | None:
        n = [c for c in self.counts(text) if c]
        total = sum(n)
        return max(0.0, -math.fsum(c / total * math.log(c / total) for c in n)) if total else None


def entropies(texts: pd.Series) -> pd.Series:
    tagger = Tagger()
    return texts.map(lambda x: None if x is None else tagger.entropy(x)).astype(float)


def word_class_entropy(text: Column | str) -> Column:
    """Entropy of word classes in nats by an Arrow-batched function, some twenty times as fast as nested expressions."""
    return F.pandas_udf(_over_batches, "double")(text)


def _over_batches(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
    tagger = Tagger()  # one memo per task
    for texts in batches:
        yield texts.map(lambda x: None if x is None else tagger.entropy(x)).astype(float)


def mean_vector(vector: Column | str) -> Column:
    """The mean of a group's vectors, as a grouped aggregate: the Arrow twin of ``vectors.mean``. Null vectors are left out; a group of none has null.

    A group's vectors reach one task; for groups of any size use the native form, which is partially aggregated.
    """

    @F.pandas_udf("array<double>")
    def mean(v: pd.Series) -> list[float]:
        some = [x for x in v if x is not None]
        return np.mean(np.stack(some).astype(float), axis=0).tolist() if some else None

    return mean(vector)
