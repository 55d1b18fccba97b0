"""Secret scans with an incremental ledger of blobs.

Every historical version of a text is addressed by the SHA-256 of its bytes. The ledger remembers which
(blob, rule, rule version) triples were scanned and what was found. A scan takes only the triples the ledger
lacks, reads each such blob once however many paths hold it, and joins the findings back to all paths.

A path may have any number of versions in one table: every row is a version of its own, its blob is scanned once however many
versions and paths share it, and each version gets its blob's findings. The ledger lies in a folder of the caller's, which later
runs go on with; it holds no text.

Defined cases: a null text is the empty blob; ids may be null or repeat, every row gets its findings;
empty tables give empty results; other columns are never read.
"""

from __future__ import annotations

import hashlib
import re
import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from winnow.llm.common import table
from winnow.plans.settle import checkpoint_dir


@dataclass(frozen=True)
class Rule:
    """A pattern, the group whose length counts and its least length. A match that is too short is dropped after matching."""

    name: str
    version: int
    pattern: str
    group: int = 0
    least: int = 1
    either_case: bool = False
    hint: str = ""  # a text without this string can't match

    def compiled(self) -> re.Pattern:
        return re.compile(self.pattern, re.ASCII | (re.IGNORECASE if self.either_case else 0))


#: The three base kinds in their listed order, then further kinds.
RULES = (
    Rule("assign", 1, r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 8, True),
    Rule("access", 1, r"AKIA[A-Z0-9]+", 0, 16, False, "AKIA"),
    Rule("hex", 1, r"[0-9a-f]{32,}", 0, 32),  # maximal runs: the short ones are dropped anyway
    Rule("pem", 1, r"-----BEGIN [A-Z ]*PRIVATE KEY-----", 0, 1, False, "-----BEGIN "),
    Rule("signed", 1, r"eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}", 0, 1, False, "eyJ"),
    Rule("login_url", 1, r"[a-z][a-z0-9+.-]{1,20}://[^\s:/@]{1,64}:[^\s:/@]{1,64}@", 0, 1, False, "://"),
)
BASE = ("assign", "access", "hex")

#: What the ledger holds; spans are start:end in code points, end exclusive, joined by commas.
LEDGER = "blob string, rule string, version int, spans string"


def find(text: str, rules: tuple[Rule, ...] = RULES) -> dict[str, list[tuple[int, int]]]:
    """Spans by kind: leftmost, non-overlapping within a kind."""
    return {r.name: _spans(text, r, r.compiled()) for r in rules}


def _spans(text: str, rule: Rule, pattern: re.Pattern) -> list[tuple[int, int]]:
    if rule.hint and rule.hint not in text:
        return []
    return [m.span() for m in pattern.finditer(text) if m.end(rule.group) - m.start(rule.group) >= rule.least]


def paths(versions: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(path, blob, text): every version with its content address."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    return versions.select(F.col(id_col).alias("path"), F.sha2(text.cast("binary"), 256).alias("blob"), text.alias("text"))


def unseen(versions: DataFrame, ledger: DataFrame | None, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """(blob, text, due): each distinct blob with the names of the rules whose present version hasn't scanned it."""
    if ledger is None:
        return versions.dropDuplicates(["blob"]).select("blob", "text", F.array(*[F.lit(r.name) for r in rules]).alias("due"))
    present = ledger.where(F.concat_ws(":", "rule", "version").isin([f"{r.name}:{r.version}" for r in rules]))
    done = present.groupBy(F.col("blob").alias("_seen")).agg(F.collect_set("rule").alias("_done"))
    due = F.array_except(F.array(*[F.lit(r.name) for r in rules]), F.coalesce("_done", F.array().cast("array<string>")))
    # the join comes before the texts are made distinct, so that scanned blobs never reach that shuffle
    left = versions.join(done, versions.blob == done["_seen"], "left").select("blob", "text", due.alias("due"))
    return left.where(F.size("due") > 0).dropDuplicates(["blob"])


def scan(blobs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """Ledger rows for (blob, text, due): one per blob and due rule, with empty spans where nothing was found."""

    def scanned(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ready = [(r, r.compiled()) for r in rules]
        for b in batches:
            out = []
            for blob, text, due in zip(*(c.to_pylist() for c in b.columns), strict=True):
                for rule, pattern in ready:
                    if rule.name in due:
                        spans = ",".join(f"{s}:{e}" for s, e in _spans(text, rule, pattern))
                        out.append((blob, rule.name, rule.version, spans))
            yield pa.RecordBatch.from_pylist(
                [dict(zip(("blob", "rule", "version", "spans"), x, strict=True)) for x in out],
                schema=pa.schema([("blob", pa.string()), ("rule", pa.string()), ("version", pa.int32()), ("spans", pa.string())]),
            )

    return blobs.select("blob", "text", "due").mapInArrow(scanned, LEDGER)


def update(spark: SparkSession, versions: DataFrame, ledger_path: str, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """Appends to the ledger at ``ledger_path`` what ``versions`` adds and returns the whole ledger.

    A crashed run leaves the ledger as it was or with whole committed files; a rerun scans only the rest.
    """
    try:
        ledger = spark.read.schema(LEDGER).parquet(ledger_path)
        ledger.limit(0).count()
    except Exception as e:
        if "PATH_NOT_FOUND" not in str(e):
            raise
        ledger = None
    scan(unseen(paths(versions), ledger, rules), rules).write.mode("append").parquet(ledger_path)
    return spark.read.schema(LEDGER).parquet(ledger_path)


def findings(versions: DataFrame, ledger: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """Joins the present rules' findings back: (path, found), found a list of (kind, start, end) by start, then rule order."""
    by_blob = (
        ledger.where(F.col("spans") != "")
        .where(F.concat_ws(":", "rule", "version").isin([f"{r.name}:{r.version}" for r in rules]))
        .dropDuplicates(["blob", "rule"])
        .groupBy(F.col("blob").alias("_blob"))
        .agg(F.collect_list(F.struct("rule", "spans")).alias("found"))
    )
    hits = versions.select("path", "blob").join(by_blob, F.col("blob") == F.col("_blob"), "left")
    return hits.select("path", "found")


def digest(found: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    order = {r.name: i for i, r in enumerate(rules)}

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for hits in b.column(1).to_pylist():
                every = sorted(
                    (int(s.split(":")[0]), order[h["rule"]], f"{h['rule']}:{s}") for h in hits or () for s in h["spans"].split(",")
                )
                n = [sum(x[1] == order[k] for x in every) for k in BASE]
                base = ",".join(x[2] for x in every if x[2].split(":")[0] in BASE)
                out.append((*n, hashlib.sha256(base.encode()).hexdigest(), ",".join(x[2] for x in every)))
            cols = list(zip(*out, strict=True)) if out else [[]] * 5
            kinds = [pa.int64()] * 3 + [pa.string()] * 2
            yield pa.RecordBatch.from_arrays(
                [b.column(0), *(pa.array(c, k) for c, k in zip(cols, kinds, strict=True))],
                names=["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"],
            )

    return found.select(F.col("path").cast("long"), "found").mapInArrow(
        rows, "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string"
    )


def op2_secret_scan(spark: SparkSession, sf_dir: str, ledger_path: str | None = None) -> DataFrame:
    """Brings the ledger up to date with every blob of the table and reads the findings back from it.

    Without a ``ledger_path`` the ledger is a new one in the shared checkpoint folder, to which every blob is unseen.
    """
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    ledger = update(spark, docs, ledger_path or f"{checkpoint_dir(spark)}/secret-ledger-{uuid.uuid4().hex}")
    return digest(findings(paths(docs), ledger))
