"""Tokens, lengths and reproducible random numbers as column expressions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

WORD = r"[\p{L}\p{N}]+"
PIECE = r"\p{L}+|\p{N}+|[^\p{L}\p{N} \t\r\n]"
TOKEN_UNITS = ("word", "piece", "bytes4")


def words(text: Column | str) -> Column:
    """Lower-cased runs of letters and digits; null and empty texts have none."""
    col = F.col(text) if isinstance(text, str) else text
    return F.coalesce(F.regexp_extract_all(F.lower(col), F.lit(WORD), F.lit(0)), F.array().cast("array<string>"))


def pieces(text: Column | str) -> Column:
    """Letter runs, digit runs and single symbols, in their case."""
    col = F.col(text) if isinstance(text, str) else text
    return F.coalesce(F.regexp_extract_all(col, F.lit(PIECE), F.lit(0)), F.array().cast("array<string>"))


def n_tokens(text: Column | str, unit: str = "word") -> Column:
    """Length of a text in the unit that budgets are counted in."""
    col = F.col(text) if isinstance(text, str) else text
    if unit == "word":
        n = F.regexp_count(F.lower(col), F.lit(WORD))
    elif unit == "piece":
        n = F.regexp_count(col, F.lit(PIECE))
    elif unit == "bytes4":
        n = F.ceil(F.octet_length(col) / F.lit(4))
    else:
        raise ValueError(f"token unit must be one of {TOKEN_UNITS}")
    return F.coalesce(n.cast("long"), F.lit(0).cast("long"))


def hash_uniform(key: Column | str, seed: int | str) -> Column:
    """A number in [0, 1) from the first 52 bits of md5(key:seed): equal on every layout, retry and engine. Null keys draw as empty ones."""
    col = F.col(key) if isinstance(key, str) else key
    digits = F.substring(F.md5(F.concat(F.coalesce(col.cast("string"), F.lit("")), F.lit(f":{seed}")).cast("binary")), 1, 13)
    return F.conv(digits, 16, 10).cast("long") / F.lit(float(1 << 52))


def spare(df: DataFrame | list[str], stem: str) -> str:
    """``stem``, or the first lengthening of it that is no column of ``df`` (or of a list of names): a name for a helper column that clashes with nothing."""
    taken = {c.lower() for c in (df if isinstance(df, list) else df.columns)}
    while stem.lower() in taken:
        stem += "_"
    return stem


def sum_of_squared_counts(tokens: Column) -> Column:
    """Sum over distinct tokens of count squared, within the row: the n-th repeat of a token adds 2n + 1."""
    start = F.struct(F.lit("").alias("last"), F.lit(0).cast("long").alias("run"), F.lit(0).cast("long").alias("acc"))

    def step(s: Column, w: Column) -> Column:
        again = (s["last"] == w) & (s["run"] > 0)
        run = F.when(again, s["run"] + 1).otherwise(F.lit(1).cast("long"))
        return F.struct(w.alias("last"), run.alias("run"), (s["acc"] + 2 * run - 1).alias("acc"))

    return F.aggregate(F.array_sort(tokens), start, step, lambda s: s["acc"])


def once(df: DataFrame, **columns: Column) -> DataFrame:
    """``df`` plus columns that are computed once per row however often later steps name them.

    The optimizer would otherwise copy a costly expression into every filter and projection above it; it
    doesn't move expressions through a generator.
    """
    return df.select("*", F.inline(F.array(F.struct(*[c.alias(n) for n, c in columns.items()]))))
