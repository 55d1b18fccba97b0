import itertools
import random

import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from winnow.llm import simhash


def plain_fingerprint(text):
    words = []
    for w in "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "").replace("\t", " ").replace("\n", " ").replace("\r", " ").replace("\x0b", " ").replace("\x0c", " ").split(" "):
        if w:
            words.append(w)
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 3]) for i in range(len(words) - 2)] or [" ".join(words)]
    h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def plain_components(fps):
    root = {f: f for f in fps}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in itertools.combinations(sorted(root), 2):
        if (a ^ b).bit_count() <= 3:
            root[max(find(a), find(b))] = min(find(a), find(b))
    return {f: find(f) for f in fps}


@settings(max_examples=200, deadline=None)
@given(st.text(alphabet="aB é\t\n\x0b\x1c Zß", max_size=60))
def test_fingerprint_matches_the_definition(text):
    assert simhash.fingerprint(text) == plain_fingerprint(text)


def signed(x):
    return x - (1 << 64) if x >> 63 else x


def spread(seed, groups=12, each=14):
    rng = random.Random(seed)
    out = [0]
    for _ in range(groups):
        base = rng.getrandbits(64)
        for _ in range(each):
            out.append(base)
            base ^= sum(1 << b for b in rng.sample(range(64), rng.randint(0, 4)))
    return out + [rng.getrandbits(64) for _ in range(60)]


def check(spark, fps, crowd):
    rows = [(i * 3 % len(fps), i, signed(f)) for i, f in enumerate(fps)]
    got = {
        (r.doc_id, r.tkey): r.component_id
        for r in simhash.components(spark.createDataFrame(rows, "doc_id long, tkey long, fp long"), crowd=crowd).collect()
    }
    root = plain_components(fps)
    least = {}
    for doc, _, f in rows:
        r = root[f % (1 << 64)]
        least[r] = min(least.get(r, doc), doc)
    assert got == {(doc, k): least[root[f % (1 << 64)]] for doc, k, f in rows}


def test_components_match_brute_force(spark):
    check(spark, spread(1), 256)


def test_crowded_halves_match_brute_force(spark):
    rng = random.Random(5)
    base = rng.getrandbits(64)
    near = [base ^ sum(1 << b for b in rng.sample(range(64), rng.randint(1, 5))) for _ in range(150)]
    check(spark, spread(2) + near, 1)


def test_links_equal_those_of_whole_word_balls(spark):
    """Every pair within 3 bits, as the form around whole fingerprints and as brute force find it."""
    rng = random.Random(9)
    fps = sorted({*spread(4, 8, 8), *[0xFFFF << 48 ^ sum(1 << b for b in rng.sample(range(64), rng.randint(0, 3))) for _ in range(60)]})
    nodes = spark.createDataFrame([(signed(f),) for f in fps], "fp long")
    for radius in (3, 2, 1):
        want = {tuple(sorted((signed(a), signed(b)))) for a, b in itertools.combinations(fps, 2) if (a ^ b).bit_count() <= radius}
        for found in (simhash.links(nodes, radius), simhash.links_whole(nodes, radius)):
            assert {(r.a, r.b) for r in found.collect()} == want and want


def test_whole_table_against_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()
    fps = {d.doc_id: plain_fingerprint(d.text) for d in docs}
    root = plain_components(list(fps.values()))
    least = {}
    for d, f in fps.items():
        least[root[f]] = min(least.get(root[f], d), d)
    want = {(d, f"{f:016x}", least[root[f]]) for d, f in fps.items()}
    assert {(r.doc_id, r.fingerprint, r.component_id) for r in simhash.op4_simhash_near_dedup(spark, sf).collect()} == want


def test_odd_rows(spark):
    docs = spark.createDataFrame(
        [(3, None, "x"), (1, "", "y"), (2, " \t\n", None), (None, "one two three four", None), (9, "One two THREE four", "z"), (9, "One two THREE four", "z"), (9, "else", "z")],
        "doc_id long, text string, _sh_tkey string",
    )
    got = sorted((r.doc_id or -1, r.fp == 0, r.component_id) for r in simhash.near_duplicates(docs).collect())
    assert got == [(-1, False, 9), (1, True, 1), (2, True, 1), (3, True, 1), (9, False, 9), (9, False, 9), (9, False, 9)]
    kept = simhash.keep_one(docs).collect()
    assert sorted((r.doc_id, r.text) for r in kept) == [(1, ""), (9, "One two THREE four"), (9, "else")]
    assert simhash.near_duplicates(docs.limit(0)).count() == 0


def test_unfolded_rows_are_never_broadcast(spark):
    """Their size is guessed from the fingerprints they unfold from, so a broadcast would send many times the guess to the driver."""
    rng = random.Random(3)
    fps = [rng.getrandbits(64) for _ in range(300)]
    nodes = spark.createDataFrame([(signed(f),) for f in fps + [f ^ 1 for f in fps[:20]]], "fp long")
    found = simhash.links(nodes)
    assert len(found.collect()) == 20
    assert "BroadcastHashJoin" not in found._jdf.queryExecution().executedPlan().toString()
    bucket = nodes.select(F.lit(0).alias("h"), simhash._word(0).alias("v"), "fp").repartition(4, "v")
    stars = simhash._stars(bucket, 3)
    assert stars.where("a <> b").count() >= 20
    stars.collect()
    assert "BroadcastHashJoin" not in stars._jdf.queryExecution().executedPlan().toString()
