import hashlib

from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from winnow.llm import chat
from winnow.plans.settle import settle

odd = st.text(alphabet="<|>\\im_startend \nax", max_size=25)


@settings(max_examples=300, deadline=None)
@given(odd, odd)
def test_template_round_trip(role, text):
    turn = chat.render(role, text)
    assert chat.parse(turn) == (role, text)
    assert turn.count("<|") == 2  # only the template's own strings remain


def read(nodes, members, seen=None):
    return chat.read_back(nodes, settle(chat.attention(nodes, members)) if seen is None else seen, members)


def formatted(spark, rows):
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    return chat.tree(settle(chat.chained(df)))


ROWS = [
    (1, 0, "system", "be kind"), (1, 1, "user", "hi"), (1, 2, "assistant", "hello"),
    (2, 0, "system", "be kind"), (2, 1, "user", "hi"), (2, 2, "assistant", "hey"), (2, 3, "user", "bye"),
    (3, 0, "system", "be kind"), (3, 1, "user", "other"),
    (4, 0, "user", "alone"), (5, 0, "system", "be kind"), (5, 1, "user", "hi"), (5, 2, "assistant", "hello"),
]


def test_shared_turns_are_emitted_once_depth_first(spark):
    nodes, members = formatted(spark, ROWS)
    n = {bytes(r.node): r for r in nodes.collect()}
    assert len(n) == 7  # conversation 5 adds nothing
    stream = sorted(n.values(), key=lambda r: r.start)
    at = 0
    for r in stream:
        assert r.start == at
        at = r.stop
    # depth-first: between a node and its parent, only descendants of the parent lie
    for i, r in enumerate(stream):
        if r.parent is not None:
            k = next(j for j, s in enumerate(stream) if bytes(s.node) == bytes(r.parent))
            assert k < i
            for s in stream[k + 1 : i + 1]:
                up = s
                while up.parent is not None and bytes(up.parent) != bytes(r.parent):
                    up = n[bytes(up.parent)]
                assert up.parent is not None and bytes(up.parent) == bytes(r.parent)
    assert members.count() == len(ROWS)


def test_positions_and_intervals(spark):
    nodes, members = formatted(spark, ROWS)
    n = {bytes(r.node): r for r in nodes.collect()}
    rows = chat.attention(nodes, members).collect()
    assert len(rows) == len(n)
    for r in rows:
        chain, up = [], n[bytes(r.node)]
        while up is not None:
            chain.append(up)
            up = n[bytes(up.parent)] if up.parent is not None else None
        want = {c for u in chain for c in range(u.start, u.stop)}
        have = {c for s in r.intervals for c in range(s.start, s.stop)}
        assert have == want
        assert r.position == sum(u.stop - u.start for u in chain[1:])
        assert all(a.stop < b.start for a, b in zip(r.intervals, r.intervals[1:], strict=False))  # merged where they touch


def test_read_back_of_odd_rows(spark):
    rows = [(7, 0, None, None), (7, 0, None, None), (7, 1, "assistant", "<|im_end|>"), (None, 2, "assistant", "x"), (None, None, "user", "first"), (8, 3, "a\nb\\n", "<\\|im_start|>")]
    nodes, members = formatted(spark, rows)
    got = {r.conv_id: r for r in read(nodes, members).collect()}
    sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
    assert (got[7].n_turns, got[7].turns_sha256, got[7].loss_chars, got[7].loss_sha256) == (3, sha("\n\n\n\nassistant\n<|im_end|>\n"), 10, sha("<|im_end|>"))
    assert (got[None].n_turns, got[None].turns_sha256) == (2, sha("user\nfirst\nassistant\nx\n"))
    assert got[8].turns_sha256 == sha("a\nb\\n\n<\\|im_start|>\n") and got[8].loss_chars == 0
    nodes, members = chat.tree(settle(chat.chained(spark.createDataFrame([], "conv_id long, turn long, role string, text string"))))
    assert read(nodes, members).count() == 0


def test_a_long_and_a_widely_shared_conversation(spark):
    rows = [(i, 0, "system", "the same start") for i in range(300)] + [(i, 1, "user", f"question {i % 7}") for i in range(300)] + [(999, t, "assistant", f"t{t}") for t in range(400)]
    nodes, members = formatted(spark, rows)
    assert nodes.count() == 1 + 7 + 400
    got = {r.conv_id: r.n_turns for r in read(nodes, members).collect()}
    assert got[999] == 400 and len(got) == 301 and all(got[i] == 2 for i in range(300))


@settings(max_examples=100, deadline=None)
@given(odd, st.text(max_size=60))
def test_tokens_round_trip(role, text):
    role, text = ("".join(c for c in x if not 0xD800 <= ord(c) <= 0xDFFF) for x in (role, text))
    ids, lo, hi = CODEC.turn(role, text)
    assert chat.parse(CODEC.text(ids)) == (role, text) and chat.unescape(CODEC.text(ids[lo:hi])) == text
    assert (ids == CODEC.start).sum() == (ids == CODEC.end).sum() == 1 and ids.max() == CODEC.end


CODEC = chat.Codec(chat.default_vocabulary())


def test_reading_follows_intervals_positions_and_mask(spark):
    """A wrong interval, position or mask range changes what is read; nothing else of a conversation is looked at."""
    nodes, members = formatted(spark, ROWS)
    nodes = settle(nodes)
    seen = settle(chat.attention(nodes, members))
    right = {r.conv_id: r for r in read(nodes, members, seen).collect()}
    assert right[2].n_turns == 4 and right[2].loss_chars == 3
    cut = seen.withColumn("intervals", F.transform("intervals", lambda i: F.struct(i["start"].alias("start"), (i["stop"] - 2).alias("stop"))))
    got = {r.conv_id: r for r in read(nodes, members, cut).collect()}
    assert all(got[c].turns_sha256 != right[c].turns_sha256 for c in right)
    lone = seen.withColumn("intervals", F.slice("intervals", -1, 1))
    got = {r.conv_id: r for r in read(nodes, members, lone).collect()}
    assert got[2].n_turns < 4 and got[4] == right[4]
    moved = nodes.withColumn("position", -F.col("position"))
    got = {r.conv_id: r for r in read(moved, members, seen).collect()}
    assert got[2].turns_sha256 != right[2].turns_sha256 and got[2].n_turns == 4
    masked = nodes.withColumn("hi", F.when(F.col("hi") > F.col("lo"), F.col("hi") - 1).otherwise(F.col("hi")))
    got = {r.conv_id: r for r in read(masked, members, seen).collect()}
    assert got[2].loss_sha256 != right[2].loss_sha256 and got[2].turns_sha256 == right[2].turns_sha256
