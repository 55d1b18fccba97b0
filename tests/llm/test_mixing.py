import hashlib
import re
from fractions import Fraction

from winnow.llm import mixing


def plain_targets(sizes):
    """Sharing, cutting, sharing again, in exact fractions."""
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(order)}
    left, open_, out = Fraction(3, 2) * sum(sizes.values()), set(order), {s: Fraction(0) for s in order}
    while open_ and left:
        total = sum(weight[s] for s in open_)
        share = {s: out[s] + left * weight[s] / total for s in open_}
        over = {s for s in open_ if share[s] > 2 * sizes[s]}
        out |= share
        left = sum(out[s] - 2 * sizes[s] for s in over)
        for s in over:
            out[s] = Fraction(2 * sizes[s])
        open_ -= over
        if not over:
            break
    return out


def check(spark, rows):
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, target string")
    got = mixing.rates(docs).collect()
    size = lambda t: len(re.findall(r"[^\x20\x09-\x0D]+", t or ""))
    sums = {}
    for _, t, s, _ in rows:
        sums[s] = sums.get(s, 0) + size(t)
    want = plain_targets(sums)
    assert len(got) == len(rows)
    for r in got:
        assert r._mx_size == size(r.text) and r._mx_source_size == sums[r.source]
        assert abs(r._mx_target - float(want[r.source])) < 1e-6
        rate = r._mx_target / r._mx_source_size if r._mx_source_size else 0
        u = int(hashlib.md5(f"{'' if r.doc_id is None else r.doc_id}:mix-1".encode()).hexdigest()[:13], 16) / 2**52
        assert r._mx_copies == int(rate) + (u < rate - int(rate)) and 0 <= r._mx_copies <= 2
    mixed = mixing.mix(docs)
    assert mixed.columns == docs.columns and mixed.count() == sum(r._mx_copies for r in got)


def test_capped_shares(spark):
    rows = [(i, "w " * n, s, "t") for i, (n, s) in enumerate([(3, "b"), (50, "a"), (1000, "c"), (7, None), (40, "Z"), (1, "é"), (900, "d")])]
    check(spark, rows)


def test_ties_nulls_and_empty_texts(spark):
    rows = [(1, None, "a", None), (1, "x y", "a", None), (1, "x y", "a", None), (None, "p q r", None, "k"), (2, "", "b", None), (3, " \t\n", "c", None), (4, "u v", "d", None)]
    check(spark, rows)
    empty = spark.createDataFrame([], "doc_id long, text string, source string")
    assert mixing.mix(empty).count() == 0


def test_whole_table_keeps_targets(spark, sf):
    rows = mixing.op5_source_mixing(spark, "/root/testdata/sf0.1").collect()
    assert all(0 <= r.taken <= 2 * r.size for r in rows)
    total = sum(r.size for r in rows)
    assert abs(sum(r.taken for r in rows) / (1.5 * total) - 1) < 0.05
    again = mixing.op5_source_mixing(spark, "/root/testdata/sf0.1").collect()
    assert sorted(map(tuple, rows)) == sorted(map(tuple, again))
