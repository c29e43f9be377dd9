"""From any pairs to oriented edges: input checks, canonical form, sorting, node arrays, orientation, lists, dense ids.

Forms used throughout: *edges* are unique undirected pairs (u, v) with u < v; an *edge array* has both directions as (src, dst);
*oriented* edges (src, dst) run from the lower to the higher rank, where rank is (degree, id).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tricount.functions.lineage import checkpointed

#: Ids below this can be packed in pairs into one signed 64-bit key.
PACK_LIMIT = 1 << 31


def validate_edges(array: DataFrame) -> DataFrame:
    """One row that counts what an edge array must not hold: nulls, loops, repeats, and rows without their reverse."""
    whole = array.where("src is not null and dst is not null")
    pairs = whole.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"))
    ends = pairs.select(F.least("src", "dst").alias("u"), F.greatest("src", "dst").alias("v"), "n").groupBy("u", "v").agg(F.count(F.lit(1)).alias("sides"), F.sum("n").alias("n"))
    one = F.lit(1).cast("long")
    counted = ends.agg(
        F.coalesce(F.sum(F.when(F.col("u") == F.col("v"), F.col("n"))), F.lit(0)).alias("loops"),
        F.coalesce(F.sum(F.when(F.col("u") == F.col("v"), F.col("n") - 1).otherwise(F.col("n") - F.col("sides"))), F.lit(0)).alias("repeats"),
        F.coalesce(F.sum(F.when((F.col("u") != F.col("v")) & (F.col("sides") == 1), one)), F.lit(0)).alias("one_way"),
    )
    nulls = array.agg(F.coalesce(F.sum((F.col("src").isNull() | F.col("dst").isNull()).cast("long")), F.lit(0)).alias("nulls"))
    return nulls.crossJoin(counted)  # one row each


def canonical_edges(pairs: DataFrame, src: str = "src", dst: str = "dst", mode: str = "repair") -> DataFrame:
    """Edges of any pairs. mode "repair" drops nulls and loops and makes pairs unique; "strict" raises on an edge array that breaks its
    contract; "trust" takes the rows of an edge array with src < dst as they are, without a shuffle."""
    a, b = F.col(src), F.col(dst)
    if mode == "trust":
        return pairs.where(a < b).select(a.alias("u"), b.alias("v"))
    if mode == "strict":
        broken = validate_edges(pairs.select(a.alias("src"), b.alias("dst"))).first().asDict()
        if any(broken.values()):
            raise ValueError(f"not an edge array: {broken}")
        return canonical_edges(pairs, src, dst, "trust")
    if mode != "repair":
        raise ValueError(f"unknown mode {mode!r}")
    return pairs.where(a.isNotNull() & b.isNotNull() & (a != b)).select(F.least(a, b).alias("u"), F.greatest(a, b).alias("v")).distinct()


def edge_array(edges: DataFrame) -> DataFrame:
    """Both directions of every edge, in one pass."""
    both = F.array(F.struct(F.col("u").alias("src"), F.col("v").alias("dst")), F.struct(F.col("v").alias("src"), F.col("u").alias("dst")))
    return edges.select(F.explode(both).alias("e")).select("e.src", "e.dst")


def vertex_count(edges: DataFrame, mode: str = "distinct") -> DataFrame:
    """n: the largest id plus one ("max_id", for dense ids), the vertices that have an edge ("distinct"), or an estimate of these ("approx")."""
    if mode == "max_id":
        return edges.agg((F.coalesce(F.max("v"), F.lit(-1)) + 1).alias("n"))
    ends = edges.select(F.explode(F.array("u", "v")).alias("x"))
    return ends.agg((F.countDistinct("x") if mode == "distinct" else F.approx_count_distinct("x")).alias("n"))


def degrees(edges: DataFrame) -> DataFrame:
    """(v, deg) of every vertex that has an edge."""
    return edges.select(F.explode(F.array("u", "v")).alias("v")).groupBy("v").agg(F.count(F.lit(1)).alias("deg"))


def pack_edge(src: Column, dst: Column, layout: str = "src_major") -> Column:
    """A 64-bit key of two ids, the first or the second in the high half; ids outside [0, 2^31) raise."""
    high, low = (src, dst) if layout == "src_major" else (dst, src)
    fits = (F.least(src, dst) >= 0) & (F.greatest(src, dst) < PACK_LIMIT)
    return F.when(fits, F.shiftleft(high.cast("long"), 32).bitwiseOR(low.cast("long"))).otherwise(F.raise_error(F.lit("ids do not fit a packed key")).cast("long"))


def unpack_edge(key: Column, layout: str = "src_major") -> tuple[Column, Column]:
    high, low = F.shiftright(key, 32), key.bitwiseAND(F.lit(PACK_LIMIT * 2 - 1))
    return (high, low) if layout == "src_major" else (low, high)


def sort_edges(array: DataFrame, key: str = "pair", layout: str = "src_major", total: bool = False) -> DataFrame:
    """Rows clustered and sorted by the major end, then the other. `total` sorts the whole table (for export), else each partition.
    key "packed" sorts one 64-bit number, which Spark's radix sort takes whole, instead of two columns."""
    major, minor = ("src", "dst") if layout == "src_major" else ("dst", "src")
    if key == "pair":
        return array.orderBy(major, minor) if total else array.repartition(major).sortWithinPartitions(major, minor)
    packed = array.select(pack_edge(F.col("src"), F.col("dst"), layout).alias("key"))
    packed = packed.orderBy("key") if total else packed.repartition(F.shiftright("key", 32)).sortWithinPartitions("key")
    src, dst = unpack_edge(F.col("key"), layout)
    return packed.select(src.alias("src"), dst.alias("dst"))


def prefix_sum(df: DataFrame, order: str, value: str) -> DataFrame:
    """df with `running`, the sum of `value` over all rows up to this one by `order` (unique), and `before`, without this one.

    Two levels: rows fall into even ranges of `order`, sums of ranges add up over that small table, and each range adds up by itself.
    """
    cut = _ranged(df, order)
    inside = F.sum(value).over(W.partitionBy("__part").orderBy("__at").rowsBetween(W.unboundedPreceding, W.currentRow))
    out = cut.join(F.broadcast(_starts(cut, F.sum(value))), "__part").withColumn("running", F.col("__start") + inside)
    return out.withColumn("before", F.col("running") - F.col(value)).drop("__part", "__at", "__start")


def node_array(array: DataFrame, fill_isolated: bool = False) -> DataFrame:
    """(v, offset, deg): where each vertex's run starts among rows sorted by src, and its length. `fill_isolated` adds ids from 0 to the largest without a row; it asks for the largest id first."""
    runs = array.groupBy(F.col("src").alias("v")).agg(F.count(F.lit(1)).alias("deg"))
    if fill_isolated:
        top = array.agg(F.max(F.greatest("src", "dst"))).first()[0]
        runs = array.sparkSession.range(0 if top is None else top + 1).toDF("v").join(runs, "v", "left").select("v", F.coalesce("deg", F.lit(0).cast("long")).alias("deg"))
    return prefix_sum(runs, "v", "deg").select("v", F.col("before").alias("offset"), "deg")


def degrees_from_node(node: DataFrame, rows: DataFrame | None = None) -> DataFrame:
    """Degrees as differences of neighbouring offsets; after the last one comes the sentinel, the number of rows. Ranges of ids hand their first offset to the range before."""
    width = 1 << 16
    ranged = node.withColumn("range", F.expr(f"v DIV {width}"))
    firsts = ranged.groupBy("range").agg(F.min_by("offset", "v").alias("first"), F.max(F.col("offset") + F.col("deg")).alias("end"))
    after = firsts.select("range", F.coalesce(F.lead("first").over(W.orderBy("range")), "end").alias("next_range"))  # a row for each 65,536 ids
    following = F.lead("offset").over(W.partitionBy("range").orderBy("v"))
    return ranged.join(after, "range").select("v", (F.coalesce(following, "next_range") - F.col("offset")).alias("deg"))


def _hashed(v: Column) -> Column:
    return F.conv(F.substring(F.md5(v.cast("string")), 1, 8), 16, 10).cast("long")


def _ranks(edges: DataFrame, deg: DataFrame | None, order: str) -> DataFrame:
    """(v, rank): what orders vertices, ties always by id."""
    if order == "degeneracy":
        return degeneracy_order(edges)
    deg = degrees(edges) if deg is None else deg
    return deg.select("v", {"degree": F.col("deg"), "random": _hashed(F.col("v"))}[order].alias("rank"))


def mark_backward(edges: DataFrame, deg: DataFrame | None = None, order: str = "degree") -> DataFrame:
    """The edge array with `backward`: true where src ranks above dst. order: "degree", "id", "random" (by a hash) or "degeneracy"."""
    array = edge_array(edges)
    if order == "id":
        return array.withColumn("backward", F.col("src") > F.col("dst"))
    rank = _ranks(edges, deg, order)
    both = array.join(rank.toDF("src", "rs"), "src").join(rank.toDF("dst", "rd"), "dst")
    return both.select("src", "dst", (F.struct("rs", "src") > F.struct(F.col("rd"), F.col("dst"))).alias("backward"))


def orient(edges: DataFrame, deg: DataFrame | None = None, order: str = "degree") -> DataFrame:
    """Oriented edges. Works on the undirected pairs, so half the rows are never made."""
    if order == "id":
        return edges.select(F.col("u").alias("src"), F.col("v").alias("dst"))
    rank = _ranks(edges, deg, order)
    both = edges.join(rank.toDF("u", "ru"), "u").join(rank.toDF("v", "rv"), "v")
    up = F.struct("ru", "u") < F.struct(F.col("rv"), F.col("v"))
    return both.select(F.when(up, F.col("u")).otherwise(F.col("v")).alias("src"), F.when(up, F.col("v")).otherwise(F.col("u")).alias("dst"))


def preprocess(edges: DataFrame, plan: str = "filter_first") -> DataFrame:
    """Oriented edges, clustered by src and sorted. "filter_first" drops backward rows before the sort, which then moves half the rows; "sort_first" sorts the whole
    edge array, marks and removes. Both give the same rows."""
    if plan == "filter_first":
        return sort_edges(orient(edges))
    marked = mark_backward(edges)
    ordered = marked.repartition("src").sortWithinPartitions("src", "dst")
    # The place in the sorted array keeps the filter above the sort: the optimizer would push it down, and both plans would be one.
    placed = ordered.withColumn("place", F.monotonically_increasing_id())
    return placed.where((F.col("place") >= 0) & ~F.col("backward")).select("src", "dst")


def unzip(records: DataFrame, column: str = "e") -> DataFrame:
    return records.select(F.col(column)["src"].alias("src"), F.col(column)["dst"].alias("dst"))


def zip_records(array: DataFrame, column: str = "e") -> DataFrame:
    return array.select(F.struct("src", "dst").alias(column))


def out_lists(oriented: DataFrame) -> DataFrame:
    """(v, nbrs): sorted out-lists; with the degree order none is longer than the root of the number of rows of the edge array."""
    return oriented.groupBy(F.col("src").alias("v")).agg(F.sort_array(F.collect_list("dst")).alias("nbrs"))


def to_adjacency(array: DataFrame) -> DataFrame:
    return out_lists(array)


def to_edge_array(adjacency: DataFrame) -> DataFrame:
    return adjacency.select(F.col("v").alias("src"), F.explode("nbrs").alias("dst"))


def _ranged(df: DataFrame, order: str) -> DataFrame:
    """df in even ranges of `order`, one for each partition and sorted within, with the range's number `__part` and the place in it, `__at`.

    Ranges are drawn from a sample of the rows, so keys that crowd together make no range large. They are drawn once: the rows are checkpointed.
    """
    cut = df.repartitionByRange(order).sortWithinPartitions(order)
    return checkpointed(cut.withColumn("__part", F.spark_partition_id()).withColumn("__at", F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))))


def _starts(cut: DataFrame, part_sum: Column) -> DataFrame:
    """(__part, __start): what the ranges before hold; one row for each partition, so it may be broadcast and the window sees few rows."""
    sums = cut.groupBy("__part").agg(part_sum.alias("n"))
    return sums.select("__part", F.coalesce(F.sum("n").over(W.orderBy("__part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("__start"))


def dense_ids(keys: DataFrame, column: str) -> DataFrame:
    """(key, id): ids from 0 in the order of the keys (strings by bytes), nulls left out. A key's id is its place in its range and what the ranges before hold."""
    cut = _ranged(keys.select(F.col(column).alias("key")).where("key is not null").distinct(), "key")
    return cut.join(F.broadcast(_starts(cut, F.count(F.lit(1)))), "__part").select("key", (F.col("__start") + F.col("__at")).alias("id"))


def degeneracy_order(edges: DataFrame, rounds: int = 1000) -> DataFrame:
    """(v, rank): the round in which a vertex falls, when all vertices of degree at most k go at once and k is the smallest degree left.

    Cuts its lineage each round; raises where vertices are left after `rounds`.
    """
    left, out, turn, floor = checkpointed(edges), None, 0, 0
    while turn < rounds:
        deg = degrees(left)
        least = deg.agg(F.min("deg")).first()[0]
        if least is None:
            break
        floor = max(floor, least)
        fall = checkpointed(deg.where(F.col("deg") <= floor).select("v", F.lit(turn).cast("long").alias("rank")))
        out = fall if out is None else out.union(fall)
        gone = fall.select("v")
        left = checkpointed(left.join(gone.toDF("u"), "u", "left_anti").join(gone, "v", "left_anti").select("u", "v"))
        turn += 1
    if turn == rounds and not left.isEmpty():
        raise RuntimeError(f"vertices are left after {rounds} rounds")
    everyone = degrees(edges).select("v")
    known = everyone.withColumn("rank", F.lit(0).cast("long")).limit(0) if out is None else out
    return everyone.join(known, "v", "left").select("v", F.coalesce("rank", F.lit(turn).cast("long")).alias("rank"))
