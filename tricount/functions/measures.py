"""Network measures and cost measures. Ratios are rounded to six places; counts stay exact."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tricount.functions import kernels
from tricount.operators import prep
from tricount.operators.blocks import vertex_counts
from tricount.operators.count import attach_lists, forward_grouped

_WEDGE_TYPE = "decimal(38,0)"


def pairs_of(d: Column) -> Column:
    """C(d, 2), in a type that holds sums over hubs."""
    d = d.cast("decimal(19,0)")
    return F.floor(d * (d - 1) / 2).cast(_WEDGE_TYPE)


def wedge_total(edges: DataFrame) -> DataFrame:
    return prep.degrees(edges).agg(F.coalesce(F.sum(pairs_of(F.col("deg"))), F.lit(0)).cast(_WEDGE_TYPE).alias("wedges"))


def transitivity(edges: DataFrame) -> DataFrame:
    """(triangles, wedges, transitivity): three times the triangles over all wedges; null without a wedge."""
    both = forward_grouped(edges).crossJoin(wedge_total(edges))  # one row each
    ratio = F.round(3.0 * F.col("triangles") / F.when(F.col("wedges") > 0, F.col("wedges").cast("double")), 6)
    return both.select("triangles", F.col("wedges").cast("long").alias("wedges"), ratio.alias("transitivity"))


def local_clustering(edges: DataFrame, low_degree: str = "zero") -> DataFrame:
    """(v, d, t, c): the share of neighbour pairs that are linked. Below degree 2, c is 0 ("zero") or null ("null"), or the vertex is left out ("skip")."""
    c = 2.0 * F.col("t") / (F.col("d").cast("double") * (F.col("d") - 1))
    low = F.lit(0.0) if low_degree == "zero" else F.lit(None).cast("double")
    out = vertex_counts(edges).select("v", "d", "t", F.when(F.col("d") > 1, F.round(c, 6)).otherwise(low).alias("c"))
    return out.where("d > 1") if low_degree == "skip" else out


def average_clustering(edges: DataFrame, over: str = "all") -> DataFrame:
    return local_clustering(edges, "zero" if over == "all" else "skip").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("c"), 6).alias("clustering"))


def clustering_by_degree(edges: DataFrame) -> DataFrame:
    """Mean local clustering by the binary logarithm of the degree."""
    return local_clustering(edges).groupBy((F.length(F.bin("d")) - 1).alias("log_degree")).agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("c"), 5).alias("clustering"))


def wedge_counts(edges: DataFrame) -> DataFrame:
    """Neighbour pairs to look at: without orientation, oriented by id, and oriented by degree."""
    out = {"unoriented": wedge_total(edges)}
    for name, order in (("by_id", "id"), ("by_degree", "degree")):
        d = prep.orient(edges, order=order).groupBy("src").agg(F.count(F.lit(1)).alias("deg"))
        out[name] = d.agg(F.coalesce(F.sum(pairs_of(F.col("deg"))), F.lit(0)).alias("wedges"))
    rows = [df.select(F.col("wedges").cast("long").alias(name)) for name, df in out.items()]
    return rows[0].crossJoin(rows[1]).crossJoin(rows[2])  # one row each


def degree_stats(edges: DataFrame) -> DataFrame:
    return prep.degrees(edges).agg(
        F.count(F.lit(1)).alias("n"), F.max("deg").alias("max_deg"), F.round(F.avg("deg"), 6).alias("mean_deg"), F.round(F.stddev_pop("deg"), 6).alias("std_deg")
    )


def list_bound(edges: DataFrame, order: str = "degree") -> DataFrame:
    """(max_out, rows, ok): the longest out-list against the root of the number of rows of the edge array."""
    lists = prep.orient(edges, order=order).groupBy("src").agg(F.count(F.lit(1)).alias("n"))
    out = lists.agg(F.max("n").alias("max_out"), (2 * F.sum("n")).alias("rows"))
    return out.withColumn("ok", F.col("max_out") * F.col("max_out") <= F.col("rows"))


def work_bound(edges: DataFrame) -> DataFrame:
    """Merge steps at most: the sum of both list lengths over oriented edges (forward), and over all edges with whole lists (edge_iterator)."""
    o = prep.orient(edges)
    d = o.groupBy("src").agg(F.count(F.lit(1)).alias("n"))
    forward = o.join(d.toDF("src", "du"), "src").join(d.toDF("dst", "dv"), "dst", "left").agg(F.sum(F.col("du") + F.coalesce("dv", F.lit(0))).alias("forward"))
    whole = prep.degrees(edges).agg(F.sum(F.col("deg") * F.col("deg")).alias("edge_iterator"))
    return forward.crossJoin(whole)  # one row each


def list_reuse(edges: DataFrame) -> DataFrame:
    """(fetches, lists, reuse, bytes): lists that counting fetches, how many there are, how often each is fetched, and the bytes of all fetches at 8 for each id.

    What a device's cache rate and memory traffic are about: the higher the reuse, the more a list that stays near saves.
    """
    o = prep.orient(edges)
    d = o.groupBy("src").agg(F.count(F.lit(1)).alias("n"))
    both = o.join(d.toDF("src", "du"), "src").join(d.toDF("dst", "dv"), "dst")
    fetched = both.agg((2 * F.count(F.lit(1))).alias("fetches"), (8 * F.coalesce(F.sum(F.col("du") + F.col("dv")), F.lit(0))).alias("bytes"))
    there = d.agg(F.count(F.lit(1)).alias("lists"))
    return fetched.crossJoin(there).select("fetches", "lists", F.round(F.try_divide("fetches", "lists"), 6).alias("reuse"), "bytes")  # one row each


def travel_sums(oriented: DataFrame) -> DataFrame:
    """(src_first, dst_first): list elements that travel through the second join, by which end's lists are joined first."""
    d = oriented.groupBy("src").agg(F.count(F.lit(1)).alias("n"))
    both = oriented.join(d.toDF("src", "du"), "src").join(d.toDF("dst", "dv"), "dst", "left")
    return both.agg(F.coalesce(F.sum("du"), F.lit(0)).alias("src_first"), F.coalesce(F.sum("dv"), F.lit(0)).alias("dst_first"))


def order_ablation(edges: DataFrame) -> DataFrame:
    """(order, wedges, max_out) under each order of vertices."""
    out = None
    for order in ("degree", "id", "random"):
        d = prep.orient(edges, order=order).groupBy("src").agg(F.count(F.lit(1)).alias("n"))
        row = d.agg(F.sum(pairs_of(F.col("n"))).cast("long").alias("wedges"), F.max("n").alias("max_out")).select(F.lit(order).alias("order"), "wedges", "max_out")
        out = row if out is None else out.unionByName(row)
    return out


def read_counters(edges: DataFrame) -> DataFrame:
    """(triangles, steps, lazy_reads, eager_reads) of merging both lists of every oriented edge, as the two kernels count them while they run."""
    o = prep.orient(edges)
    both = attach_lists(o, prep.out_lists(o)).select("nu", "nv")
    sums = {}
    for kernel in ("merge", "merge_eager"):
        run = both.mapInArrow(kernels.counted(kernel), kernels.COUNTED)
        sums[kernel] = run.agg(*[F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in ("triangles", "steps", "reads")])
    lazy, eager = sums["merge"].withColumnRenamed("reads", "lazy_reads"), sums["merge_eager"].select(F.col("reads").alias("eager_reads"))
    return lazy.crossJoin(eager).select("triangles", "steps", "lazy_reads", "eager_reads")  # one row each


def graph_summary(edges: DataFrame) -> DataFrame:
    """(nodes, edges, edge_rows, triangles): undirected edges and rows of the edge array are told apart."""
    size = edges.agg(F.count(F.lit(1)).alias("edges"))
    both = prep.vertex_count(edges).withColumnRenamed("n", "nodes").crossJoin(size).crossJoin(forward_grouped(edges))  # one row each
    return both.select("nodes", "edges", (2 * F.col("edges")).alias("edge_rows"), "triangles")


def triangle_edge_ratio(edges: DataFrame) -> DataFrame:
    return graph_summary(edges).select(F.round(F.col("triangles") / F.col("edges"), 6).alias("ratio"))
