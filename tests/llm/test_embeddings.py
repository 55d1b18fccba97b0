import math
import random

import numpy as np

from winnow.llm import embeddings


def plain(rows, threshold=0.98):
    ok = lambda v, lab: lab is not None and v is not None and all(x is not None and math.isfinite(x) for x in v) and any(v)
    n = len(rows)
    root = list(range(n))
    links = [0] * n

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(n):
        for j in range(i):
            (_, v, a), (_, w, b) = rows[i], rows[j]
            if ok(v, a) and ok(w, b) and a == b and len(v) == len(w):
                x, y = np.array(v, float), np.array(w, float)
                if x @ y / (np.linalg.norm(x) * np.linalg.norm(y)) >= threshold:
                    links[i] += 1
                    links[j] += 1
                    root[find(i)] = find(j)
    out = []
    for i in range(n):
        ids = [rows[j][0] for j in range(n) if find(j) == find(i) and rows[j][0] is not None]
        out.append((rows[i][0], links[i], min(ids) if ids else None))
    return sorted(out, key=str)


def check(spark, rows, **how):
    df = spark.createDataFrame([(i, v, lab, "x") for i, v, lab in rows], "vec_id long, embedding array<float>, label int, bucket string")
    got = embeddings.near_duplicates(df, **how).collect()
    assert sorted(((r.vec_id, r.n_links, r.component_id) for r in got), key=str) == plain([(i, None if v is None else [None if x is None else float(np.float32(x)) for x in v], lab) for i, v, lab in rows])
    assert all(r.kept == (r.vec_id == r.component_id) for r in got if r.vec_id is not None)


def clusters(seed, groups, each, noise, dim=16):
    rng = np.random.default_rng(seed)
    rows = []
    for g in range(groups):
        base = rng.standard_normal(dim)
        for _ in range(each):
            rows.append((base + noise * rng.standard_normal(dim)).tolist())
    random.Random(seed).shuffle(rows)
    return [(i * 7 % 1009, v, i % 3) for i, v in enumerate(rows)]


def test_clusters_match_brute_force(spark):
    check(spark, clusters(1, 12, 12, 0.05))


def test_a_group_of_many_blocks(spark):
    check(spark, [(i, v, 1) for i, v, _ in clusters(2, 2, 90, 0.05)], block=16)


def test_copies_scaled_vectors_and_unusable_ones(spark):
    v = [1.0, 2.0, 3.0]
    rows = [
        (5, v, 1), (3, v, 1), (4, [2.0, 4.0, 6.0], 1), (9, v, 2), (8, v, None), (7, None, 1), (6, [0.0, 0.0, 0.0], 1), (10, [0.0, 0.0, 0.0], 1),
        (11, [1.0, None, 3.0], 1), (12, [1.0, float("nan"), 3.0], 1), (13, [float("inf"), 2.0, 3.0], 1), (14, [1.0, 2.0], 1), (14, [1.0, 2.0], 1), (None, v, 1), (15, [], 1), (16, [-0.0, 1.0], 3), (17, [0.0, 1.0], 3),
    ]
    check(spark, rows)


def test_empty_table(spark):
    assert embeddings.near_duplicates(spark.createDataFrame([], "vec_id long, embedding array<float>, label int")).count() == 0


def test_recall_on_the_whole_table(spark):
    folder = "/root/testdata/sf0.1"
    rows = [(r.vec_id, r.embedding, r.label) for r in spark.read.parquet(f"{folder}/embeddings.parquet").collect()]
    e = np.array([r[1] for r in rows], float)
    e /= np.linalg.norm(e, axis=1, keepdims=True)
    near = (e @ e.T >= 0.98) & (np.array([r[2] for r in rows])[:, None] == np.array([r[2] for r in rows])[None, :])
    np.fill_diagonal(near, False)
    want = dict(zip([r[0] for r in rows], near.sum(axis=1).tolist(), strict=True))
    got = {r.vec_id: r.n_links for r in embeddings.op6_embedding_near_dedup(spark, folder).collect()}
    assert all(got[i] <= want[i] for i in want)
    assert sum(got.values()) >= 0.99 * sum(want.values())
