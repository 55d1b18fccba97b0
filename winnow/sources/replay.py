"""A batch and stream source that replays a documents table in micro-batches, by the Python Data Source API."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, arrival timestamp"


def _rows(path: str, batch: int, batches: int):
    """Rows whose id falls to the batch, arriving a minute apart per id from a fixed day on."""
    import datetime as dt

    import pyarrow.compute as pc
    import pyarrow.dataset as ds

    table = ds.dataset(path).to_table(columns=["doc_id", "text", "lang", "source", "n_chars"])
    ids = table.column("doc_id")
    quotient = pc.multiply(pc.floor(pc.divide(pc.cast(ids, "double"), float(batches))), float(batches))
    mine = table.filter(pc.equal(pc.subtract(pc.cast(ids, "double"), quotient), float(batch)))
    start = dt.datetime(2024, 1, 1, tzinfo=dt.timezone.utc)
    for r in mine.sort_by("doc_id").to_pylist():
        yield r["doc_id"], r["text"], r["lang"], r["source"], r["n_chars"], start + dt.timedelta(minutes=r["doc_id"])


class _Batch(InputPartition):
    pass


class _Reader(DataSourceReader):
    def __init__(self, path: str, batches: int):
        self.path, self.batches = path, batches

    def partitions(self):
        return [_Batch(i) for i in range(self.batches)]

    def read(self, partition):
        yield from _rows(self.path, partition.value, self.batches)


class _Stream(SimpleDataSourceStreamReader):
    """Offset = batches already given."""

    def __init__(self, path: str, batches: int):
        self.path, self.batches = path, batches

    def initialOffset(self):
        return {"batch": 0}

    def read(self, start):
        b = start["batch"]
        if b >= self.batches:
            return iter([]), start
        return _rows(self.path, b, self.batches), {"batch": b + 1}

    def readBetweenOffsets(self, start, end):
        for b in range(start["batch"], end["batch"]):
            yield from _rows(self.path, b, self.batches)

    def commit(self, end):
        pass


class DocumentReplay(DataSource):
    """Options: path (a local or mounted Parquet file, for tests and demonstrations), batches (10)."""

    @classmethod
    def name(cls) -> str:
        return "document_replay"

    def schema(self) -> str:
        return SCHEMA

    def _how(self):
        return self.options["path"], int(self.options.get("batches", "10"))

    def reader(self, schema):
        return _Reader(*self._how())

    def simpleStreamReader(self, schema):
        return _Stream(*self._how())


def register(spark: SparkSession) -> None:
    spark.dataSource.register(DocumentReplay)
