import itertools
import zlib

import numpy as np
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from winnow.llm import packing

PATH = packing.default_tokenizer()


def best_cost(places, penalties, total, length):
    """All ways to cut, by plain recursion over the candidates."""
    cost = {0: 0}
    for p, c in itertools.chain(zip(places, penalties, strict=True), [] if places and places[-1] == total else [(total, 0)]):
        cost[p] = min(cost[q] + length - (p - q) + c for q in cost if p - length <= q < p)
    return cost[total]


@settings(max_examples=200, deadline=None)
@given(st.lists(st.integers(1, 10), min_size=1, max_size=30), st.data())
def test_cuts_are_optimal(gaps, data):
    places = list(itertools.accumulate(gaps))
    penalties = [data.draw(st.sampled_from([0, 3, 9])) for _ in places]
    total = places[-1]
    penalties[-1] = 0
    chosen = packing.cuts(np.array(places), np.array(penalties), total, 10)
    assert chosen[-1] == total
    price, before = 0, 0
    for p in chosen:
        assert 0 < p - before <= 10
        price += 10 - (p - before) + dict(zip(places, penalties, strict=True)).get(p, 0)
        before = p
    assert price == best_cost(places, penalties, total, 10)


@settings(max_examples=150, deadline=None)
@given(st.text(max_size=80) | st.text(alphabet="ab 'sté\n\t\x85\xa0 ​.!?1２<|endoftext|>", max_size=80))
def test_ids_are_those_of_the_library(text):
    encode, _ = TOOLS
    assert encode(text).tolist() == [*SLOW.encode(text, add_special_tokens=False).ids, 1]


TOOLS = packing.tokenizer(PATH)
SLOW = Tokenizer.from_file(PATH)


def verify(rows, want, length=2048):
    """rows: pieces as tuples in the order of the columns; want: list of (doc_id, ids)."""
    by_seq = {}
    for r in rows:
        by_seq.setdefault(r[5], []).append(r)
    for pieces in by_seq.values():
        at = 0
        for r in sorted(pieces, key=lambda r: r[6]):
            assert r[6] == at
            at += r[2]
        assert at <= length and all(r[7] == at for r in pieces)
    left = sorted(((d, ids.tobytes()) for d, ids in want), key=str)
    have = []
    for d in {r[0] for r in rows}:
        mine = sorted((r for r in rows if r[0] == d), key=lambda r: (r[5], r[6]))
        current = None
        for r in mine:
            if r[1] == 0:
                current = []
                have.append((d, current, r[4]))
            assert sum(x[2] for x in current) == r[1]
            current.append(r)
    assert len(have) == len(left)
    pool = {}
    for d, ids in want:
        pool.setdefault((d, len(ids)), []).append(ids)
    for d, parts, tokens in have:
        options = pool[d, tokens]
        hit = next(i for i in options if all(zlib.crc32(i[p[1] : p[1] + p[2]].astype("<u4").tobytes()) == p[3] for p in parts))
        assert sum(p[2] for p in parts) == len(hit)


def test_every_id_lies_in_one_piece(spark):
    texts = [None, "", "short", "A sentence. " * 900, "x" * 30_000, "no ends here " * 3000, "short", "<|endoftext|> inside", "日本語 " * 500]
    docs = [(i if i != 4 else None, t, "z") for i, t in enumerate(texts)] + [(2, "short", "z")]
    rows = packing.pack(spark.createDataFrame(docs, "doc_id long, text string, start string"), PATH).collect()
    verify([tuple(r) for r in rows], [(i, TOOLS[0](t or "")) for i, t, _ in docs])
    assert packing.pack(spark.createDataFrame([], "doc_id long, text string"), PATH).count() == 0


def test_blocks_carry_tokens_on():
    rng = np.random.default_rng(1)
    docs = [(i, np.array([*rng.integers(2, 200, rng.integers(0, 900)), 1], np.uint32)) for i in range(300)] + [(999, np.arange(2, 60_000, dtype=np.uint32) % 50_000)]
    ends = np.zeros(50_300, bool)
    ends[5:40] = True
    rows = [r for out in packing.pieces_of(iter(docs), ends, 0, 256, 4) for r in out]
    verify(rows, docs, 256)
    assert sum(r[2] for r in rows) / (256 * len({r[5] for r in rows})) > 0.9


def test_little_padding_on_the_whole_table(spark):
    folder = "/root/testdata/sf0.01"
    rows = [tuple(r) for r in packing.op10_packing(spark, folder).collect()]
    texts = spark.read.parquet(f"{folder}/documents.parquet").collect()
    verify(rows, [(r.doc_id, TOOLS[0](r.text or "")) for r in texts])
    assert sum(r[2] for r in rows) / (2048 * len({r[5] for r in rows})) > 0.97
