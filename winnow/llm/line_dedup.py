"""Line dedup: a line that several documents hold stays only in the one with the smallest id.

Line hashes are range-partitioned with document and position as secondary sort keys, so that one very
common line spreads over many partitions. Each partition streams through its sorted rows and marks every
line whose document isn't the first to hold it. Only the first key of a partition may have begun in an
earlier one; its rows wait for the owner, found from two claims per partition. What is returned is a
compressed keep bitmap per document, not text.

Defined cases: a null or empty text is one empty line; a null id counts as the smallest id, and rows with
equal ids count as one document (their lines never displace each other); repeated rows get equal bitmaps;
empty tables give empty results; other columns are carried along untouched by ``apply_bitmaps``.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from winnow.functions.textops import spare
from winnow.llm.common import id_or_low, id_or_null, table, text_key
from winnow.plans.settle import settle

MIN_CHARS = 10
_DROP, _WAIT, _CLAIM = 0, 1, 2
_LINES = "h1 long, h2 long, doc long, tkey long, pos int"
_MARKS = "kind int, h1 long, h2 long, doc long, tkey long, pos int"


def _keys(batches: Iterator[pa.RecordBatch], min_chars: int) -> Iterator[pa.RecordBatch]:
    """(doc, tkey, text) -> one row per line long enough to count, with the 128-bit hash of its key."""
    for b in batches:
        for at in range(0, b.num_rows, 512):  # bounds what one Arrow batch of long texts unfolds to
            part = b.slice(at, 512)
            text = pc.fill_null(part.column(2), "")
            lines = pc.split_pattern(pc.cast(text, pa.large_string()), "\n")
            counts = pc.list_value_length(lines).to_numpy(zero_copy_only=False)
            row = np.repeat(np.arange(part.num_rows), counts)
            pos = np.arange(len(row)) - np.repeat(np.cumsum(counts) - counts, counts)
            key = pc.ascii_lower(pc.ascii_trim_whitespace(lines.flatten()))
            long = pc.greater_equal(pc.utf8_length(key), min_chars).to_numpy(zero_copy_only=False)
            digest = b"".join([xxhash.xxh3_128_digest(k) for k in pc.cast(key.filter(pa.array(long)), pa.large_binary()).to_pylist()])
            h = np.frombuffer(digest, dtype="<i8").reshape(-1, 2)
            row = row[long]
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array(h[:, 0]),
                    pa.array(h[:, 1]),
                    part.column(0).take(pa.array(row)),
                    part.column(1).take(pa.array(row)),
                    pa.array(pos[long].astype(np.int32)),
                ],
                names=["h1", "h2", "doc", "tkey", "pos"],
            )


def _first_occurrences(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Sorted lines -> drops, the undecided rows of the partition's first key, and claims on its first and last keys."""
    first = last = None  # (h1, h2)
    owner = opened = None  # document of the current key; of the partition's first key

    def rows(kind, h1, h2, doc, tkey, pos):
        return pa.RecordBatch.from_arrays(
            [pa.array(np.full(len(h1), kind, np.int32)), *(pa.array(x) for x in (h1, h2, doc, tkey, pos))],
            names=["kind", "h1", "h2", "doc", "tkey", "pos"],
        )

    for b in batches:
        if not b.num_rows:
            continue
        h1, h2, doc, tkey, pos = (c.to_numpy(zero_copy_only=False) for c in b.columns)
        new = np.empty(len(h1), bool)
        new[0] = last is None or (h1[0], h2[0]) != last
        new[1:] = (h1[1:] != h1[:-1]) | (h2[1:] != h2[:-1])
        if first is None:
            first, opened = (h1[0], h2[0]), doc[0]
        start = np.maximum.accumulate(np.where(new, np.arange(len(h1)), -1))
        own = np.where(start >= 0, doc[np.maximum(start, 0)], owner if owner is not None else 0)
        wait = (h1 == first[0]) & (h2 == first[1])
        drop = ~wait & (doc != own)
        last, owner = (h1[-1], h2[-1]), own[-1]
        for kind, which in ((_DROP, drop), (_WAIT, wait)):
            if which.any():
                yield rows(kind, h1[which], h2[which], doc[which], tkey[which], pos[which])
    if first is not None:
        ends = np.array([first, last], dtype=np.int64)
        yield rows(_CLAIM, ends[:, 0], ends[:, 1], np.array([opened, owner]), np.zeros(2, np.int64), np.zeros(2, np.int32))


def _packed(positions: np.ndarray) -> bytes:
    """Bit i, from the lowest of the first byte on, tells whether line i stays; lines beyond the last bit stay."""
    bits = np.ones((int(max(positions)) // 8 + 1) * 8, np.uint8)
    bits[positions] = 0
    return zlib.compress(np.packbits(bits, bitorder="little").tobytes(), 6)


def kept_lines(bitmap: bytes | None, n: int) -> np.ndarray:
    """Unpacks a bitmap to n booleans."""
    keep = np.ones(n, bool)
    if bitmap is not None:
        bits = np.unpackbits(np.frombuffer(zlib.decompress(bitmap), np.uint8), bitorder="little")[:n]
        keep[: len(bits)] = bits
    return keep


def keep_bitmaps(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = MIN_CHARS) -> DataFrame:
    """(doc, tkey, keep): the compressed bitmap of each document that loses lines; all others keep every line."""
    lines = docs.select(id_or_low(id_col).alias("doc"), text_key(text_col).alias("tkey"), F.col(text_col).cast("string").alias("text")).mapInArrow(
        lambda it: _keys(it, min_chars), _LINES
    )
    order = ["h1", "h2", "doc", "tkey", "pos"]
    marks = settle(lines.repartitionByRange(*order).sortWithinPartitions(*order).mapInArrow(_first_occurrences, _MARKS))
    # two claims per partition: their number is bounded by the partitions, whatever the input
    claims = marks.where(F.col("kind") == _CLAIM).groupBy("h1", "h2").agg(F.min("doc").alias("owner"))
    late = marks.where(F.col("kind") == _WAIT).join(F.broadcast(claims), ["h1", "h2"]).where("doc > owner")
    drops = marks.where(F.col("kind") == _DROP).select("doc", "tkey", "pos").unionAll(late.select("doc", "tkey", "pos"))

    @F.pandas_udf("binary")
    def packed(at: pd.Series) -> pd.Series:
        return at.map(_packed)

    return drops.groupBy("doc", "tkey").agg(F.collect_set("pos").alias("at")).select("doc", "tkey", packed("at").alias("keep"))


def _with_bitmaps(docs: DataFrame, bitmaps: DataFrame, id_col: str, text_col: str) -> tuple[DataFrame, str, str]:
    """``docs`` plus keep, under a name that it doesn't have, which comes back as well."""
    doc, key, keep, bdoc, bkey = (spare(docs, f"_ld_{x}") for x in ("doc", "tkey", "keep", "bdoc", "bkey"))
    keyed = docs.withColumns({doc: id_or_low(id_col), key: text_key(text_col)})
    found = bitmaps.select(F.col("doc").alias(bdoc), F.col("tkey").alias(bkey), F.col("keep").alias(keep))
    return keyed.join(found, (F.col(doc) == F.col(bdoc)) & (F.col(key) == F.col(bkey)), "left"), doc, keep


def apply_bitmaps(docs: DataFrame, bitmaps: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` with the same columns, where texts that lose lines hold what stays, joined by newlines."""

    def one(text: str | None, keep: bytes) -> str:
        lines = (text or "").split("\n")
        return "\n".join([x for x, k in zip(lines, kept_lines(keep, len(lines)), strict=True) if k])

    @F.pandas_udf("string")
    def rebuilt(text: pd.Series, keep: pd.Series) -> pd.Series:
        return pd.Series([None if k is None else one(x, k) for x, k in zip(text, keep, strict=True)], dtype=object)

    left, _, keep = _with_bitmaps(docs, bitmaps, id_col, text_col)
    loses = F.col(keep).isNotNull()
    new = F.when(loses, rebuilt(F.when(loses, F.col(text_col)), keep)).otherwise(F.col(text_col))  # other texts don't go to Python
    return left.withColumn(text_col, new).select(*docs.columns)


def digest(docs: DataFrame, bitmaps: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_lines, n_dropped, kept_sha256) of every document under its bitmap."""

    def measured(batches):
        for b in batches:
            out = []
            for text, keep in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                lines = (text or "").split("\n")
                if keep is None:
                    out.append((len(lines), 0, hashlib.sha256((text or "").encode()).hexdigest()))
                else:
                    stay = kept_lines(keep, len(lines))
                    kept = "\n".join([x for x, k in zip(lines, stay, strict=True) if k])
                    out.append((len(lines), int(len(lines) - stay.sum()), hashlib.sha256(kept.encode()).hexdigest()))
            n, d, s = zip(*out, strict=True) if out else ((), (), ())
            yield pa.RecordBatch.from_arrays(
                [b.column(0), pa.array(n, pa.int64()), pa.array(d, pa.int64()), pa.array(s, pa.string())],
                names=["doc_id", "n_lines", "n_dropped", "kept_sha256"],
            )

    joined, doc, keep = _with_bitmaps(docs, bitmaps, id_col, text_col)
    out = joined.select(doc, F.col(text_col).cast("string"), keep).mapInArrow(
        measured, "doc_id long, n_lines long, n_dropped long, kept_sha256 string"
    )
    return out.withColumn("doc_id", id_or_null("doc_id"))


def op1_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return digest(docs, keep_bitmaps(docs))


OP1_SQL = r"""
WITH lines AS (
  SELECT doc_id, line, pos,
         translate(trim(line, chr(32)||chr(9)||chr(10)||chr(11)||chr(12)||chr(13)),
                   'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key
  FROM (SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line,
               generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS pos
        FROM documents)
), shared AS (
  SELECT key, min(doc_id) AS owner FROM lines WHERE length(key) >= 10
  GROUP BY key HAVING count(DISTINCT doc_id) > 1
), kept AS (
  SELECT l.doc_id, l.pos, l.line, s.owner IS NULL OR s.owner = l.doc_id AS stays
  FROM lines l LEFT JOIN shared s ON l.key = s.key
)
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (NOT stays) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (stays), '')) AS kept_sha256
FROM kept GROUP BY doc_id
"""
