"""Packing by order-preserving dynamic programming.

Documents stay in the order of the table. Their tokens form one stream per input partition, which windows of at
most ``length`` tokens cover. Window cuts are chosen among document ends and sentence ends (and, only where a single sentence is
longer than a window, places inside it), so that padding plus penalties for cut documents is least. With P(j) the place of
candidate j and c(j) its penalty, cost(j) = c(j) + length - P(j) + min(cost(i) + P(i)) over the i at most
``length`` before j; a queue of rising values gives each minimum in constant time.

The stream is solved in blocks of ``block`` windows, the tokens after a block's last full window being carried
on, so memory doesn't grow with a partition. Nothing is shuffled; a lost task is done again from its split.

Defined cases: a null or empty text is its end token alone; ids may be null or repeat, each row is a document;
an empty table has no pieces; a document longer than a window lies in several.
"""

from __future__ import annotations

import zlib
from collections import deque
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from winnow.llm.common import table

LENGTH = 2048
END_ID = 1
#: Penalties in padding tokens: a document's end costs nothing.
SENTENCE, ANYWHERE = 24, 96
#: Where two neighbouring ends lie more than a window apart, so that some cut must fall inside a sentence, a place is offered each so many tokens.
EVERY = 128
BLOCK = 256

_PLAIN = 0x2000  # below it, both tokenizer libraries class characters alike


def tokenizer(path: str):
    """A function from texts to arrays of ids, and a table that tells which ids end a sentence.

    Ids are those of the tokenizers library; the same vocabulary as ranks in tiktoken gives equal ids several times
    faster and is used for texts of common characters without control strings.
    """
    import os

    import tiktoken
    from tokenizers import Tokenizer

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    slow = Tokenizer.from_file(path)
    vocabulary = slow.get_vocab(with_added_tokens=False)
    special = [t.content for t in slow.get_added_tokens_decoder().values()]
    char_of = _byte_letters()
    ranks = {}
    for token, i in vocabulary.items():
        if token not in special:
            ranks[bytes(char_of[c] for c in token)] = i
    pattern = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
    fast = tiktoken.Encoding("ranks", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
    ends = np.zeros(max(vocabulary.values()) + 2, bool)
    for raw, i in ranks.items():
        ends[i] = raw.rstrip(b" \"')")[-1:] in (b".", b"!", b"?", b"\n")
    ends[END_ID] = False

    def encode(text: str) -> np.ndarray:
        if any(t in text for t in special) or (not text.isascii() and max(text) >= chr(_PLAIN)):
            ids = slow.encode(text, add_special_tokens=False).ids
        else:
            ids = fast.encode_ordinary(text)
        return np.array([*ids, END_ID], np.uint32)

    return encode, ends


def _byte_letters() -> dict[str, int]:
    """The letter that stands for each byte in a byte-level vocabulary: itself if printable, else the next from 256 on."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


def cuts(places: np.ndarray, penalties: np.ndarray, total: int, length: int = LENGTH) -> list[int]:
    """The chosen window ends in a stream of ``total`` tokens, its end included: least padding plus penalties.

    ``places`` rise, lie within 1 to total and are at most ``length`` apart.
    """
    p = [0, *places.tolist()]
    c = [0, *penalties.tolist()]
    if p[-1] != total:
        p.append(total)
        c.append(0)
    best, back = [0] * len(p), [0] * len(p)
    queue: deque[int] = deque([0])
    value = [0] * len(p)  # cost + place, which rises along the queue
    for j in range(1, len(p)):
        at = p[j]
        while p[queue[0]] < at - length:
            queue.popleft()
        i = queue[0]
        best[j] = value[i] + length - at + c[j]
        back[j] = i
        value[j] = v = best[j] + at
        while queue and value[queue[-1]] >= v:
            queue.pop()
        queue.append(j)
    out, j = [], len(p) - 1
    while j:
        out.append(p[j])
        j = back[j]
    return out[::-1]


def candidates(ids: np.ndarray, doc_ends: np.ndarray, ends: np.ndarray, length: int = LENGTH) -> tuple[np.ndarray, np.ndarray]:
    """(places, penalties) of a stream: document ends, sentence ends within documents, and fallbacks between ends more than a window apart."""
    penalty = np.full(len(ids) + 1, -1, np.int64)
    penalty[np.flatnonzero(ends[ids]) + 1] = SENTENCE
    natural = penalty >= 0
    natural[doc_ends] = True
    natural[0] = natural[len(ids)] = True
    at = np.flatnonzero(natural)
    step = max(1, min(EVERY, length))
    for i in np.flatnonzero(np.diff(at) > length):
        extra = np.arange(at[i] + step, at[i + 1], step)
        penalty[extra] = ANYWHERE
    penalty[doc_ends] = 0
    places = np.flatnonzero(penalty[1:] >= 0) + 1
    return places, penalty[places]


PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, sequence_tokens long"


def pieces_of(docs: Iterator[tuple[int | None, np.ndarray]], ends: np.ndarray, first_sequence: int, length: int = LENGTH, block: int = BLOCK) -> Iterator[list[tuple]]:
    """Pieces in order, block by block; each holds ids that are one stretch of its document and of its sequence."""
    held: list[tuple[int | None, int, int, np.ndarray]] = []  # (id, ids before, tokens of the document, ids)
    have, sequence = 0, first_sequence

    def solved(last: bool) -> Iterator[tuple]:
        nonlocal held, have, sequence
        ids = np.concatenate([h[3] for h in held])
        bounds = np.cumsum([len(h[3]) for h in held])
        whole = np.array([h[1] + len(h[3]) == h[2] for h in held])
        chosen = cuts(*candidates(ids, bounds[whole], ends, length), len(ids), length)
        if not last:
            chosen = chosen[:-1]  # the last window may still grow
        piece, begin, k = [], 0, 0
        for stop in chosen:
            at = begin
            while at < stop:
                doc, before, tokens, own = held[k]
                top = int(bounds[k]) - len(own)
                upto = min(stop, int(bounds[k]))
                part = ids[at:upto]
                piece.append((doc, before + at - top, upto - at, zlib.crc32(part.astype("<u4").tobytes()), tokens, sequence, at - begin, stop - begin))
                at = upto
                if at == bounds[k]:
                    k += 1
            begin, sequence = stop, sequence + 1
        if k < len(held):
            doc, before, tokens, own = held[k]
            skip = begin - (int(bounds[k]) - len(own))
            held = [(doc, before + skip, tokens, own[skip:]), *held[k + 1 :]]
        else:
            held = []
        have = sum(len(h[3]) for h in held)
        yield from piece

    for doc, ids in docs:
        n = len(ids)
        for at in range(0, n, block * length):  # a huge document is fed in stretches
            part = ids[at : at + block * length]
            held.append((doc, at, n, part))
            have += len(part)
            if have >= block * length:
                yield list(solved(False))
    if held:
        yield list(solved(True))


def pack(docs: DataFrame, tokenizer_path: str, id_col: str = "doc_id", text_col: str = "text", length: int = LENGTH) -> DataFrame:
    """One row per piece. sequence_id is unique: the partition's number in its upper bits, a running number below."""

    def packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, ends = tokenizer(tokenizer_path)
        names = [x.split()[0] for x in PIECES.split(", ")]

        def rows() -> Iterator[tuple[int | None, np.ndarray]]:
            for b in batches:
                for at in range(0, b.num_rows, 256):
                    part = b.slice(at, 256)
                    for doc, text in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                        yield doc, encode(text or "")

        for out in pieces_of(rows(), ends, TaskContext.get().partitionId() << 33, length):
            cols = zip(*out, strict=True) if out else [[]] * len(names)
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], names=names)

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(packed, PIECES)


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def op10_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"), default_tokenizer())
