"""Triangles as rows, and what is read off them: counts per vertex and edge, trusses, typed triangles, samples."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tricount.functions.lineage import checkpointed
from tricount.operators import blocks, prep
from tricount.operators.count import triangles_of
from tricount.sources.generators import draw


def list_triangles(edges: DataFrame, order: str = "degree") -> DataFrame:
    """(a, b, c), each triangle once, lowest rank first. Under the degree order from blocks of lists, so that two-paths are never shuffled."""
    return blocks.block_triangles(edges) if order == "degree" else triangles_of(prep.orient(edges, order=order))


def vertex_triangles(edges: DataFrame) -> DataFrame:
    """(v, t) of every vertex that has an edge; 0 where it is in no triangle."""
    return blocks.vertex_counts(edges).select("v", "t")


def _sides() -> Column:
    """The three edges (u, v) of a triangle (a, b, c)."""
    return F.array(*[F.struct(F.least(x, y).alias("u"), F.greatest(x, y).alias("v")) for x, y in (("a", "b"), ("a", "c"), ("b", "c"))])


def edge_support(edges: DataFrame) -> DataFrame:
    """(u, v, support): in how many triangles each edge is."""
    return blocks.edge_counts(edges)


def top_vertices(edges: DataFrame, k: int = 10) -> DataFrame:
    return vertex_triangles(edges).orderBy(F.desc("t"), "v").limit(k)


def truss(edges: DataFrame, k: int, max_rounds: int = 50) -> DataFrame:
    """Edges of the k-truss: each is in k - 2 triangles of what is left. Rounds cut their lineage."""
    left = checkpointed(edges)
    n = left.count()
    for _ in range(max_rounds):
        after = checkpointed(edge_support(left).where(F.col("support") >= k - 2).select("u", "v"))
        m = after.count()
        left = after
        if m == n:
            return left
        n = m
    raise RuntimeError(f"the {k}-truss has not settled after {max_rounds} rounds")


def vertices_without_triangle(edges: DataFrame) -> DataFrame:
    return prep.degrees(edges).select("v").join(list_triangles(edges).select(F.explode(F.array("a", "b", "c")).alias("v")), "v", "left_anti")


def typed_triangles(edges: DataFrame, types: DataFrame) -> DataFrame:
    """(ta, tb, tc, n) from a map (v, type): triangles by the sorted types of their corners, added up where blocks of lists are met."""
    return blocks.typed_counts(edges, types)


def _chances(method: str, share: int) -> tuple[float, float]:
    """How likely a triangle is in the sample, and how likely one is of which a triangle on the same edge is in it."""
    if method == "edges":
        return (share / 100) ** 3, (share / 100) ** 2
    if method == "colours":
        return 1 / share**2, 1 / share
    if method == "wedges":
        return share / 100, share / 100
    raise ValueError(f"unknown method {method!r}")


def _estimated(counted: DataFrame, method: str, share: int) -> DataFrame:
    """Adds estimate and std_error to kept triangles and `shared`, the pairs of kept triangles that have an edge in common.

    Of such a pair both are kept more often than chance, so the variance of `kept` is kept * (1 - q) + 2 * shared * (1 - q / r), each
    estimated from the sample: q is a triangle's chance, r its chance beside a kept neighbour. Other pairs are independent.
    """
    q, r = _chances(method, share)
    spread = F.col("kept") * F.lit(1 - q) + F.col("shared") * F.lit(2 * (1 - q / r))
    return counted.withColumns({"estimate": F.round(F.col("kept") * F.lit(1 / q), 6), "std_error": F.round(F.sqrt(spread) * F.lit(1 / q), 6)})


def _pairs_on_edges(triangles: DataFrame, *by: str) -> DataFrame:
    """kept triangles, and shared: pairs of them with an edge in common, for each value of `by`."""
    per_edge = triangles.select(*by, F.explode(_sides()).alias("e")).groupBy(*by, "e.u", "e.v").agg(F.count(F.lit(1)).alias("s"))
    sums = {"kept": F.expr("coalesce(sum(s), 0) DIV 3"), "shared": F.expr("coalesce(sum(s * (s - 1) DIV 2), 0)")}
    return per_edge.groupBy(*by).agg(*[c.alias(name) for name, c in sums.items()])


def approx_triangles(edges: DataFrame, method: str, share: int, seed: int = 1) -> DataFrame:
    """One row: kept (triangles or closed wedges found in the sample), shared (pairs of them with an edge in common), the estimate and its standard error. Samples are drawn by hashes, so reruns agree.

    "edges": edges are kept with `share` hundredths; a triangle survives with the cube of it. "colours": vertices get one of `share` colours and edges of one colour stay;
    a triangle survives with 1 / share^2. "wedges": oriented wedges are kept with `share` hundredths, and those an edge closes are counted; each triangle has one, so none are shared.
    """
    if method == "wedges":
        o = prep.orient(edges)
        wedges = o.select("src", F.col("dst").alias("u")).join(o.select("src", F.col("dst").alias("v")), "src").where("u < v")
        some = wedges.where(draw(F.col("src"), F.col("u"), F.col("v"), seed) % 100 < share)
        closed = some.join(edges, ["u", "v"], "left_semi").agg(F.count(F.lit(1)).alias("kept"), F.lit(0).cast("long").alias("shared"))
        return _estimated(closed, method, share)
    return _estimated(_pairs_on_edges(list_triangles(edges.where(_kept(method, share, seed)))), method, share)


def _kept(method: str, share: int, seed: Column | int, u: Column | None = None, v: Column | None = None) -> Column:
    """Whether the sample of a seed has the edge (u, v)."""
    u, v = F.col("u") if u is None else u, F.col("v") if v is None else v
    if method == "edges":
        return draw(u, v, seed) % 100 < share
    if method == "colours":
        return draw(u, seed) % share == draw(v, seed) % share
    raise ValueError(f"unknown method {method!r}")


def approx_accuracy(edges: DataFrame, method: str, share: int, seeds: int = 20) -> DataFrame:
    """For each seed 1..seeds: kept, shared, estimate and std_error as approx_triangles gives them, the relative error, and whether the true count is within two standard errors.

    Triangles are listed once and marked by each seed's draws, so the samples are those of approx_triangles. A graph without triangles gives no rows.
    """
    t = checkpointed(list_triangles(edges)).withColumn("seed", F.explode(F.sequence(F.lit(1), F.lit(seeds))))
    sides = [_kept(method, share, F.col("seed"), F.least(x, y), F.greatest(x, y)) for x, y in (("a", "b"), ("a", "c"), ("b", "c"))]
    found = _pairs_on_edges(t.where(sides[0] & sides[1] & sides[2]), "seed")
    every = t.groupBy("seed").agg(F.count(F.lit(1)).alias("true_count")).join(found, "seed", "left").fillna(0, ["kept", "shared"])
    off = F.col("estimate") - F.col("true_count")
    rated = _estimated(every, method, share).withColumns({"rel_error": F.round(off / F.col("true_count"), 6), "within": F.abs(off) <= 2 * F.col("std_error")})
    return rated.select("seed", "kept", "shared", "estimate", "std_error", "rel_error", "within")
