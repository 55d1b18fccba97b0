import hashlib
import random

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from winnow.llm import line_dedup

BLANK = " \t\n\x0b\x0c\r"


def plain(rows, min_chars=10):
    """Definition, row by row: (id, text) -> {id: (n_lines, n_dropped, text)}."""
    def key(line):
        return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in line.strip(BLANK))

    held = {}
    for i, text in rows:
        for line in (text or "").split("\n"):
            held.setdefault(key(line), set()).add(i)
    out = {}
    for i, text in rows:
        lines = (text or "").split("\n")
        kept = [x for x in lines if len(key(x)) < min_chars or len(held[key(x)]) < 2 or min(held[key(x)]) == i]
        out[i] = (len(lines), len(lines) - len(kept), hashlib.sha256("\n".join(kept).encode()).hexdigest())
    return out


def got(spark, rows, **how):
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    return {r.doc_id: (r.n_lines, r.n_dropped, r.kept_sha256) for r in line_dedup.digest(docs, line_dedup.keep_bitmaps(docs, **how)).collect()}


def test_small_cases(spark):
    rows = [
        (5, "a shared line here\nown\n  A SHARED line HERE\t"),
        (2, "x\n\ta shared line here\ny"),
        (9, "A shared Line here"),
        (7, None), (8, ""), (1, "ten chars!\nten chars!"), (3, "Ten Chars!\nten char"), (4, "é" * 10), (6, "É" * 10 + "\n" + "é" * 10),
    ]
    assert got(spark, rows) == plain(rows)


def test_hot_line_over_many_partitions(spark):
    rng = random.Random(3)
    pool = [f"line number {i} of the pool" for i in range(40)]
    rows = [(i, "\n".join(["the line that all documents hold", *rng.sample(pool, rng.randint(0, 4)), f"only in {i} and nowhere"])) for i in range(600)]
    rng.shuffle(rows)
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    try:
        assert got(spark, rows) == plain(rows)
    finally:
        spark.conf.unset("spark.sql.adaptive.coalescePartitions.enabled")


def test_repeated_rows_nulls_and_clashing_columns(spark):
    docs = spark.createDataFrame(
        [(1, "some line of text", "a"), (1, "some line of text", "a"), (2, "Some Line of Text\nrest", "b"), (None, "some line of text\nmore", "c"), (3, "other", None)],
        "doc_id long, text string, keep string",
    )
    out = line_dedup.apply_bitmaps(docs, line_dedup.keep_bitmaps(docs))
    assert out.columns == docs.columns
    # the row without id counts as the smallest, so it keeps the line
    assert sorted(((r.doc_id or 0), r.text, r.keep or "") for r in out.collect()) == [(0, "some line of text\nmore", "c"), (1, "", "a"), (1, "", "a"), (2, "rest", "b"), (3, "other", "")]
    empty = docs.limit(0)
    assert line_dedup.apply_bitmaps(empty, line_dedup.keep_bitmaps(empty)).count() == 0


@settings(max_examples=60, deadline=None)
@given(st.sets(st.integers(0, 400), min_size=1), st.integers(0, 20))
def test_bitmap_round_trip(gone, more):
    n = max(gone) + 1 + more
    keep = line_dedup.kept_lines(line_dedup._packed(sorted(gone)), n)
    assert [i for i in range(n) if not keep[i]] == sorted(gone)


def test_very_long_text(spark):
    rows = [(1, "\n".join(f"line {i} of a long text" for i in range(50_000))), (2, "line 77 of a long text\nline 49999 of a LONG text")]
    assert got(spark, rows) == plain(rows)


@pytest.mark.parametrize("least", [1, 30])
def test_other_lengths(spark, least):
    rows = [(1, "ab\ncd ef"), (2, "ab\nxy"), (3, "cd ef " * 6), (4, "cd ef " * 6)]
    assert got(spark, rows, min_chars=least) == plain(rows, least)
