"""Connected components of a link table, by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tricount.llm.common import Stages


def _stars(links: DataFrame, both_ways: bool) -> DataFrame:
    """Hangs neighbours on the smallest id around each node: larger neighbours if `both_ways`, else smaller ones and the node."""
    if both_ways:
        seen = links.union(links.select("b", "a"))
    else:
        seen = links.select(F.greatest("a", "b"), F.least("a", "b"))
    seen = seen.toDF("node", "near")
    least = seen.groupBy("node").agg(F.least(F.min("near"), F.col("node")).alias("least"))
    joined = seen.join(least, "node")
    if both_ways:
        out = joined.where("near > node").select(F.col("near").alias("a"), F.col("least").alias("b"))
    else:
        out = joined.select(F.col("near").alias("a"), F.col("least").alias("b")).union(least.select("node", "least"))
    return out.where("a <> b").distinct()


def components(links: DataFrame, stages: Stages) -> DataFrame:
    """(node, label) for every node of `links` (a, b), label being the smallest node reachable. The tables of finished rounds are removed."""
    now = stages.write(links.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
    mark = None
    while True:
        after = stages.write(_stars(_stars(now, True), False))
        stages.drop(now)
        now = after
        sums = now.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("a", "b"))).first()
        if tuple(sums) == mark:
            break
        mark = tuple(sums)
    return now.select(F.col("a").alias("node"), F.col("b").alias("label")).union(now.select("b", "b").distinct())
