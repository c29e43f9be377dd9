"""Synthetic graphs. Random numbers come from hashes of counters, so that any engine makes the same graph."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tricount.functions.lineage import checkpointed
from tricount.operators.prep import canonical_edges

#: Levels of a recursive matrix whose bits of both ids fit one number.
LEVELS = 31


def draw(*parts: Column | int | str) -> Column:
    """The first 32 bits of the md5 of the parts joined by "|"."""
    text = F.concat_ws("|", *[p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts])
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long")


def hundredths(h: Column) -> Column:
    return F.shiftright(h * 100, 32)


def rmat_pairs(counter: Column, df: DataFrame, scale: int, abcd: tuple[int, int, int, int] = (57, 19, 19, 5), seed: int = 42) -> DataFrame:
    """A recursive-matrix pair for each row of df, from its counter."""
    a, b, c, _ = abcd
    # What a draw adds to both ids at level 0, in one number: the source's bit in the high half, the target's in the low one. So each draw is made once.
    bits = F.array(*[F.lit(((r >= a + b) << 32) + (a <= r < a + b or r >= a + b + c)).cast("long") for r in range(100)])
    # The optimizer copies what makes a column into each filter on it and each use of it, but not through a generator.
    drawn = df.select(F.explode(F.array(counter)).alias("c"))
    add = lambda x, level: 2 * x + F.element_at(bits, (hundredths(draw(F.col("c"), level, seed)) + 1).cast("int"))
    levels = [F.sequence(F.lit(min(scale, low + LEVELS) - 1), F.lit(low), F.lit(-1)) for low in range(0, scale, LEVELS)] or [F.array().cast("array<int>")]
    both = drawn.select(F.explode(F.array(F.array(*[F.aggregate(x, F.lit(0).cast("long"), add) for x in levels]))).alias("x"))
    half = lambda take: reduce(lambda x, y: x + y, [F.shiftleft(take(F.col("x")[k]), k * LEVELS) for k in range(len(levels))])
    return both.select(half(lambda x: F.shiftright(x, 32)).alias("src"), half(lambda x: x.bitwiseAND(F.lit((1 << 32) - 1))).alias("dst"))


def rmat(spark: SparkSession, scale: int, edge_factor: int = 16, abcd: tuple[int, int, int, int] = (57, 19, 19, 5), seed: int = 42) -> DataFrame:
    """A recursive-matrix graph of 2^scale ids from edge_factor * 2^scale drawn pairs."""
    return canonical_edges(rmat_pairs(F.col("id"), spark.range(edge_factor << scale), scale, abcd, seed))


def rmat_from(df: DataFrame, key_cols: list[str], scale: int, seed: int = 42) -> DataFrame:
    """The same with the rows of a table as counters."""
    return canonical_edges(rmat_pairs(F.concat_ws("-", *key_cols), df, scale, seed=seed))


def small_world(spark: SparkSession, n: int, k: int, beta: float, seed: int = 42) -> DataFrame:
    """A ring where each vertex links to its k nearest; a share beta of the links goes to random vertices instead."""
    return small_world_of(spark.range(n), n, k, beta, seed)


def small_world_of(ids: DataFrame, n: int, k: int, beta: float, seed: int = 42) -> DataFrame:
    """The same on ready ids, 0 to n - 1."""
    links = ids.select(F.col("id").alias("i"), F.explode(F.sequence(F.lit(1), F.lit(k // 2))).alias("j"))
    moved = hundredths(draw(F.col("i"), F.col("j"), "a", seed)) < round(100 * beta)
    to = F.when(moved, draw(F.col("i"), F.col("j"), "b", seed) % n).otherwise((F.col("i") + F.col("j")) % n)
    return canonical_edges(links.select(F.col("i").alias("src"), to.alias("dst")))


def preferential(spark: SparkSession, n: int, k: int, seed: int = 42) -> DataFrame:
    """Preferential attachment: new vertices link to ends of earlier edges, drawn evenly, which favours vertices by degree.

    Every edge has two slots. A new edge copies a slot: its source is known at once, its target needs the slot it copied to be known. Slots that copy
    targets point further back, and pointers double each round until all end in a known vertex, so rounds grow with the logarithm of the chain.
    """
    return preferential_of(spark.range(n), k, seed)


def preferential_of(ids: DataFrame, k: int, seed: int = 42) -> DataFrame:
    """The same on ready ids from 0 up, which join in their order."""
    spark = ids.sparkSession
    core = k * (k + 1) // 2
    pairs = [(a, b) for a in range(1, k + 1) for b in range(a)]
    first = spark.createDataFrame([(e, a, b) for e, (a, b) in enumerate(pairs)], "edge long, src long, dst long")
    drawn = ids.where(F.col("id") > k).select(F.explode(F.sequence((F.col("id") - k - 1) * k, (F.col("id") - k) * k - 1)).alias("id"))
    new = drawn.select((core + F.col("id")).alias("edge"), (k + 1 + F.expr(f"id DIV {k}")).alias("src"), (draw(F.col("id"), seed) % (2 * (core + F.expr(f"id DIV {k}") * k))).alias("slot"))
    source = F.when(F.expr("slot DIV 2") < core, F.lit(None)).otherwise(k + 1 + F.expr(f"(slot DIV 2 - {core}) DIV {k}"))
    # `known` is the target where it needs no other edge's target; else `link` is the edge whose target it is.
    known = F.when((F.col("slot") % 2 == 0) & (F.expr("slot DIV 2") >= core), source)
    asked = new.select("edge", "src", known.alias("known"), F.expr("slot DIV 2").alias("link"), (F.col("slot") % 2).alias("side"))
    settled = asked.join(F.broadcast(first.select(F.col("edge").alias("link"), F.col("src").alias("fs"), F.col("dst").alias("fd"))), "link", "left").select(
        "edge", "src", F.coalesce("known", F.when(F.col("link") < core, F.when(F.col("side") == 0, F.col("fs")).otherwise(F.col("fd")))).alias("known"), "link"
    )
    now = checkpointed(settled)
    while now.where("known is null").limit(1).count():
        back = now.select(F.col("edge").alias("link"), F.col("known").alias("k2"), F.col("link").alias("l2"))
        moved = now.where("known is null").join(back, "link").select("edge", "src", F.col("k2").alias("known"), F.col("l2").alias("link"))
        now = checkpointed(now.where("known is not null").unionByName(moved))
    return canonical_edges(first.select("src", "dst").union(now.select("src", F.col("known").alias("dst"))))


def fixture_graph(spark: SparkSession, kind: str, n: int, m: int = 0) -> DataFrame:
    """Graphs with a known count: complete, cycle, star, path, wheel, bipartite (n by m), cliques (n of size m), ring (n, degree m), empty."""
    i = spark.range(n).withColumnRenamed("id", "src")
    at = F.col("src")
    upto = lambda a, b: F.explode(F.when(b >= a, F.sequence(a, b)).otherwise(F.array().cast("array<bigint>")))
    long = lambda x: F.lit(x).cast("long")
    if kind == "complete":
        pairs = i.select(at, upto(at + 1, long(n - 1)).alias("dst"))
    elif kind in ("cycle", "ring"):
        pairs = i.select(at, F.explode(F.sequence(long(1), long(m // 2 if kind == "ring" else 1))).alias("j")).select(at, ((at + F.col("j")) % n).alias("dst"))
    elif kind == "star":
        pairs = i.where("src > 0").select(at, long(0).alias("dst"))
    elif kind == "path":
        pairs = i.where("src > 0").select(at, (at - 1).alias("dst"))
    elif kind == "wheel":
        pairs = i.select(F.explode(F.array(F.struct(at.alias("src"), ((at + 1) % n).alias("dst")), F.struct(at.alias("src"), long(n).alias("dst")))).alias("e")).select("e.*")
    elif kind == "bipartite":
        pairs = i.select(at, F.explode(F.sequence(long(n), long(n + m - 1))).alias("dst"))
    elif kind == "cliques":
        pairs = spark.range(n * m).select(F.col("id").alias("src"), upto(F.col("id") + 1, F.expr(f"(id DIV {m} + 1) * {m} - 1")).alias("dst"))
    elif kind == "empty":
        pairs = i.select(at, at.alias("dst")).where(F.lit(False))
    else:
        raise ValueError(f"unknown graph {kind!r}")
    return canonical_edges(pairs)


def complete_graph(ids: DataFrame) -> DataFrame:
    """All pairs of different values of a column, which are few: they are gathered as one list."""
    one = ids.toDF("x").where("x is not null").distinct().agg(F.sort_array(F.collect_list("x")).alias("xs"))
    return canonical_edges(one.select("xs", F.explode("xs").alias("src")).select("src", F.explode("xs").alias("dst")))


def complete_bipartite(left: DataFrame, right: DataFrame) -> DataFrame:
    """All pairs of values of two columns, which are few: ids 2k and 2k + 1."""
    lists = [df.toDF("x").where("x is not null").distinct().agg(F.collect_list("x").alias(name)) for df, name in ((left, "l"), (right, "r"))]
    both = lists[0].crossJoin(lists[1])  # one row each
    return canonical_edges(both.select("r", F.explode("l").alias("a")).select((2 * F.col("a")).alias("src"), F.explode("r").alias("b")).select("src", (2 * F.col("b") + 1).alias("dst")))


def kron_power(edges: DataFrame, n: int, p: int) -> DataFrame:
    """The p-th Kronecker power of a loop-free graph with ids below n: it has (6 T)^p / 6 triangles."""
    both = edges.select(F.explode(F.array(F.struct(F.col("u").alias("src"), F.col("v").alias("dst")), F.struct(F.col("v").alias("src"), F.col("u").alias("dst")))).alias("e")).select("e.*")
    grow = lambda x, y: x.select((F.col("src") * n).alias("hs"), (F.col("dst") * n).alias("hd")).crossJoin(F.broadcast(y)).select((F.col("hs") + F.col("src")).alias("src"), (F.col("hd") + F.col("dst")).alias("dst"))
    return canonical_edges(reduce(grow, [both] * p))  # the broadcast side is the small fixed graph
