import hashlib
import zlib
from collections import Counter

from winnow.llm import sharding


def plain(rows, shards):
    """The definition in one place: fractional ranks within sources, one order, equal stretches."""
    h = lambda i: hashlib.md5(f"{'' if i is None else i}:shard-1".encode()).hexdigest()
    size = lambda t: len((t or "").encode()) + 1
    crc = lambda t: zlib.crc32((t or "").encode())
    key = lambda r: (h(r[0]), r[0] is not None, r[0] or 0, size(r[1]), crc(r[1]))
    placed = []
    for s in {r[2] for r in rows}:
        own = sorted((r for r in rows if r[2] == s), key=key)
        placed += [((k + 0.5) / len(own), s is None, s or "", key(r), r) for k, r in enumerate(own)]
    placed.sort(key=lambda p: p[:4])
    n = len(rows)
    out = []
    for at, p in enumerate(placed):
        shard = at * shards // n
        out.append((p[4][0], size(p[4][1]), crc(p[4][1]), shard, at - -(-shard * n // shards)))
    return sorted(out, key=str)


def check(spark, rows, shards=16):
    got = sharding.shard(spark.createDataFrame([(*r, 1) for r in rows], "doc_id long, text string, source string, shard int"), shards).collect()
    assert sorted(((r.doc_id, r.size, r.text_crc32, r.shard, r.slot) for r in got), key=str) == plain(rows, shards)
    return got


def test_matches_the_definition(spark):
    check(spark, [(i, f"text {i % 9} é", f"src{i % 3 if i % 2 else 0}") for i in range(500)])


def test_nulls_ties_and_few_rows(spark):
    check(spark, [(1, None, None), (1, None, None), (None, "", "a"), (None, "x", "a"), (2, "x", "b"), (2, "x", "b"), (3, "x", "b")])
    check(spark, [(1, "a", "s")])
    assert sharding.shard(spark.createDataFrame([], "doc_id long, text string, source string")).count() == 0


def test_every_shard_holds_the_mixture(spark):
    got = sharding.shard(spark.read.parquet("/root/testdata/sf0.1/documents.parquet")).collect()
    whole = Counter(r.source for r in got)
    per = Counter(r.shard for r in got)
    assert max(per.values()) - min(per.values()) <= 1
    by = Counter((r.shard, r.source) for r in got)
    assert all(abs(by[k, s] - whole[s] * per[k] / len(got)) <= 2 for k in per for s in whole)
