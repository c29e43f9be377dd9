"""Exact copies: group by a 128-bit content hash, compare bytes inside the groups, keep one id."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tricount.llm.common import Stages, unused

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def normalised(text: Column) -> Column:
    """The text with A-Z lower-cased and every other character as it is; null becomes empty."""
    text = F.coalesce(text, F.lit(""))
    ascii_only = F.octet_length(text) == F.char_length(text)
    return F.when(ascii_only, F.lower(text)).otherwise(F.translate(text, _UPPER, _LOWER))


def content_hash(text: Column) -> Column:
    return F.unhex(F.md5(text.cast("binary")))


def exact_copies(docs: DataFrame, keep: str = "min", fingerprint: Callable[[Column], Column] = content_hash) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256 of the normalised text.

    Texts are equal when their normalised bytes are. `keep` names which id of a group stays, "min" or "max". Groups come
    from `fingerprint`; within each, the smallest and the largest text are compared byte by byte, both by partial
    aggregation, so a group of any size ships one text per map task. Where they differ the fingerprints collided, and
    those groups are formed again by the text itself.

    Null or empty texts form one group. Rows that repeat an id count one by one in group_size and share kept. A group
    whose ids are all null has a null keep_id and none is kept. Other columns are ignored. An empty table gives no rows.
    """
    spark = docs.sparkSession
    stages = Stages(spark, "exact")
    best = F.min if keep == "min" else F.max
    norm = docs.select(F.col("doc_id").alias("id"), normalised(F.col("text")).alias("norm"))
    hashed = norm.withColumn("h", fingerprint(F.col("norm")))
    groups = stages.write(
        hashed.groupBy("h")
        .agg(best("id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"), F.min("norm").alias("lo"), F.max("norm").alias("hi"))
        .select("h", "keep_id", "group_size", (F.col("lo") == F.col("hi")).alias("same"))
    )
    rows = hashed.select("id", "h", F.unhex(F.sha2(F.col("norm").cast("binary"), 256)).alias("sha"))
    out = rows.join(groups.where("same").drop("same"), "h")
    collided = groups.where("not same").select("h")
    if not collided.isEmpty():
        again = hashed.join(collided, "h", "left_semi")
        split = again.groupBy("h", "norm").agg(best("id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"))
        told = again.join(split, ["h", "norm"]).select("h", "id", F.unhex(F.sha2(F.col("norm").cast("binary"), 256)).alias("sha"), "keep_id", "group_size")
        out = out.unionByName(told)
    return out.select(
        F.col("id").alias("doc_id"), "keep_id", "group_size",
        F.coalesce(F.col("id") == F.col("keep_id"), F.lit(False)).alias("kept"),
        F.lower(F.hex("sha")).alias("text_sha256"),
    )


def drop_copies(docs: DataFrame, keep: str = "max") -> DataFrame:
    """The documents that stay, with all their columns. Rows with a null id carry no identity to drop them by, and stay."""
    name = unused(docs, "kept_id")
    kept = exact_copies(docs, keep).where("kept").select(F.col("doc_id").alias(name)).distinct()
    known = docs.where("doc_id is not null").join(kept, F.col("doc_id") == F.col(name), "left_semi")
    return known.unionByName(docs.where("doc_id is null"))


SQL = """
WITH t AS (SELECT doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS norm FROM documents)
SELECT doc_id, max(doc_id) OVER g AS keep_id, count(*) OVER g AS group_size, doc_id = max(doc_id) OVER g AS kept, sha256(norm) AS text_sha256
FROM t WINDOW g AS (PARTITION BY norm)
"""
