"""Session helpers: input tables, staged tables in the shared folder, bounded labelled samples."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tricount.functions.lineage import ensure_folder

#: Words of a text, as a Java and DuckDB pattern.
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def unused(df: DataFrame, name: str) -> str:
    """A name for a further column that the table does not have."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share, from spark.checkpoint.dir; where that is unset, the context's, or a temporary one if all runs in one process, as in tests."""
    ensure_folder(spark)
    return spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()


class Stages:
    """Tables written to the shared folder to cut lineage; reading one again never repeats what made it."""

    def __init__(self, spark: SparkSession, name: str) -> None:
        self.spark = spark
        self.root = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
        self.number = 0
        self.paths: dict[int, str] = {}

    def folder(self) -> str:
        """A new folder's path."""
        self.number += 1
        return f"{self.root}/{self.number:03d}"

    def write(self, df: DataFrame, *by: str) -> DataFrame:
        """The rows as written; with `by`, in a folder for each value of these columns."""
        path = self.folder()
        df.write.partitionBy(*by).parquet(path) if by else df.write.parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        self.paths[id(out)] = path
        return out

    def drop(self, *frames: DataFrame) -> None:
        """Removes tables that nothing reads any more."""
        for df in frames:
            self._remove(self.paths.pop(id(df)))

    def keep_only(self, *frames: DataFrame) -> None:
        """Removes all tables but these, which the rows that are handed out still read."""
        kept = {id(df) for df in frames}
        for key in [k for k in self.paths if k not in kept]:
            self._remove(self.paths.pop(key))

    def _remove(self, name: str) -> None:
        path = self.spark._jvm.org.apache.hadoop.fs.Path(name)
        path.getFileSystem(self.spark._jsparkSession.sessionState().newHadoopConf()).delete(path, True)


def fold(column: Column | str, of: int) -> Column:
    """crc32 of the id as text, modulo `of`; null ids fall into fold 0."""
    column = F.col(column) if isinstance(column, str) else column
    return F.coalesce(F.crc32(column.cast("string")) % F.lit(of), F.lit(0)).cast("int")


#: Bytes of a text up to which a labelled row may be learned from.
LEARNED_BYTES = 1 << 17


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, train: Column, bound: int, longest: int = LEARNED_BYTES) -> list[tuple[str, object]]:
    """(text, label) of at most `bound` labelled ids that satisfy `train`, chosen by the hash of the id, one row each, of texts of at most `longest` bytes.

    `bound` rows of ids are broadcast, and `bound` texts come to the driver, so both sizes are limited. Null labels, ids and texts
    are left out; of rows that repeat an id the smallest text is taken. The same rows come back on every run, in the same order.
    """
    picked = (
        labels.where(train & F.col("doc_id").isNotNull() & F.col(label).isNotNull())
        .groupBy("doc_id").agg(F.max(label).alias("label"))
        .orderBy(F.xxhash64("doc_id"), "doc_id").limit(bound)
    )
    fit = docs.select("doc_id", "text").where(F.col("text").isNotNull() & (F.octet_length("text") <= longest))
    rows = fit.join(F.broadcast(picked), "doc_id").groupBy("doc_id").agg(F.min("text").alias("text"), F.max("label").alias("label")).collect()
    rows.sort(key=lambda r: (r.doc_id, r.text))
    return [(r.text, r.label) for r in rows]
