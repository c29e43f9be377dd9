"""The recursive-matrix graph as a data source, read at once or as a stream.

    spark.dataSource.register(RmatSource)
    spark.read.format("rmat").option("scale", 10).load()

Rows are the drawn pairs of the generator with the same scale, edge factor and seed: loops and repeats are in them, as in any raw edge list.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from hashlib import md5

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader

#: Rows of a batch.
BATCH = 4096


def pairs(counters: Iterable[int], scale: int, seed: int, abcd: tuple[int, int, int, int] = (57, 19, 19, 5)) -> Iterator[tuple[int, int]]:
    """The pair of each counter: one quarter of the matrix is drawn for every bit, lowest first."""
    a, b, c, _ = abcd
    for i in counters:
        src = dst = 0
        for level in range(scale):
            r = int.from_bytes(md5(f"{i}|{level}|{seed}".encode()).digest()[:4], "big") * 100 >> 32
            src |= (r >= a + b) << level
            dst |= (a <= r < a + b or r >= a + b + c) << level
        yield src, dst


def drawn_for(counters: DataFrame, scale: int, seed: int = 42) -> DataFrame:
    """(src, dst) for each row of a table with one column of counters, drawn as the source draws them, in the tasks that read the table."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = list(pairs(batch.column(0).to_pylist(), scale, seed))
            yield pa.RecordBatch.from_arrays([pa.array([p[k] for p in found], pa.int64()) for k in (0, 1)], names=["src", "dst"])

    return counters.where(F.col(counters.columns[0]).isNotNull()).mapInArrow(run, "src long, dst long")


class _Settings:
    def __init__(self, options: dict) -> None:
        self.scale, self.seed = int(options.get("scale", "10")), int(options.get("seed", "42"))
        self.rows = int(options.get("edgeFactor", "16")) << self.scale
        self.parts = max(1, int(options.get("partitions", "8")))
        self.step = max(1, int(options.get("rowsPerBatch", str(self.rows))))


class RmatReader(DataSourceReader):
    """One partition for each range of counters, drawn by itself, so that a lost one is drawn again with the same rows."""

    def __init__(self, options: dict) -> None:
        self.of = _Settings(options)

    def partitions(self) -> list[InputPartition]:
        n, k = self.of.rows, self.of.parts
        return [InputPartition((n * i // k, n * (i + 1) // k)) for i in range(k)]

    def read(self, partition: InputPartition) -> Iterator[pa.RecordBatch]:
        begin, end = partition.value
        for at in range(begin, end, BATCH):
            found = list(pairs(range(at, min(end, at + BATCH)), self.of.scale, self.of.seed))
            yield pa.RecordBatch.from_arrays([pa.array([p[k] for p in found], pa.int64()) for k in (0, 1)], names=["src", "dst"])


class RmatStream(SimpleDataSourceStreamReader):
    """`rowsPerBatch` counters in each micro-batch until all are drawn; offsets are counters, so a batch can be replayed."""

    def __init__(self, options: dict) -> None:
        self.of = _Settings(options)

    def initialOffset(self) -> dict:
        return {"next": 0}

    def read(self, start: dict) -> tuple[Iterator[tuple], dict]:
        end = {"next": min(self.of.rows, start["next"] + self.of.step)}
        return self.readBetweenOffsets(start, end), end

    def readBetweenOffsets(self, start: dict, end: dict) -> Iterator[tuple]:
        return pairs(range(start["next"], end["next"]), self.of.scale, self.of.seed)


class RmatSource(DataSource):
    """Options: scale (10), edgeFactor (16), seed (42), partitions (8), and for streams rowsPerBatch."""

    @classmethod
    def name(cls) -> str:
        return "rmat"

    def schema(self) -> str:
        return "src long, dst long"

    def reader(self, schema) -> DataSourceReader:
        return RmatReader(self.options)

    def simpleStreamReader(self, schema) -> SimpleDataSourceStreamReader:
        return RmatStream(self.options)


def read_rmat(spark: SparkSession, scale: int, **options: int) -> DataFrame:
    spark.dataSource.register(RmatSource)
    return spark.read.format("rmat").options(scale=scale, **options).load()
