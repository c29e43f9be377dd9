"""Exact triangle counts. Each method takes edges (u, v) and gives one row, `triangles`."""

from __future__ import annotations

import math
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tricount.functions import kernels
from tricount.functions.lineage import checkpointed, once
from tricount.operators import blocks, prep

#: Edges up to which the one-task methods agree to run.
LOCAL_LIMIT = 5_000_000
#: Edges up to which lists are carried along edges in joins. Beyond, a list would be shuffled as often as it is long, and the count comes from blocks of lists instead.
JOINED_LIMIT = 4_000_000
#: Bytes of lists, before compression, that edges may carry through the join of forward_grouped(); beyond, the count comes from blocks of lists too.
JOINED_BYTES = 1 << 31
#: Bytes of lists that its edges may carry at most where Spark may broadcast edges and lists. Files of edges take a fraction of these and Spark goes by files, so it would gather them in the driver.
BROADCAST_BYTES = 1 << 25
#: Hubs (of some 20 bytes each) up to which their table is broadcast.
HUBS_LIMIT = 100_000


def _total(column: str, df: DataFrame, parts: int = 1) -> DataFrame:
    """The sum of a column, 0 for no rows, divided by how often a triangle is seen."""
    return df.agg(F.expr(f"CAST(coalesce(sum({column}), 0) DIV {parts} AS BIGINT)").alias("triangles"))


def attach_lists(oriented: DataFrame, lists: DataFrame, first: str = "dst") -> DataFrame:
    """Oriented edges with the out-lists of both ends, nu and nv. The list joined first is carried through the second join; ends without a list fall out, as they close nothing."""
    of_src, of_dst = lists.toDF("src", "nu"), lists.toDF("dst", "nv")
    return oriented.join(of_dst, "dst").join(of_src, "src") if first == "dst" else oriented.join(of_src, "src").join(of_dst, "dst")


def forward_lists(edges: DataFrame, kernel: str = "array_intersect", order: str = "degree", first: str = "dst", partitions: int | None = None) -> DataFrame:
    """Sum over oriented edges of the size of the intersection of both out-lists: a triangle is found once, at the edge between its two lowest vertices. With `partitions`, joined lists are dealt over so many tasks."""
    oriented = prep.orient(edges, order=order)
    both = attach_lists(oriented, prep.out_lists(oriented), first)
    both = both.select("nu", "nv").repartition(partitions) if partitions else both
    if kernel in kernels.KERNELS:
        return _total("triangles", both.select("nu", "nv").mapInArrow(kernels.counted(kernel), kernels.COUNTED))
    if kernel != "array_intersect":
        raise ValueError(f"unknown kernel {kernel!r}")
    return _total("n", both.select(F.size(F.array_intersect("nu", "nv")).cast("long").alias("n")))


def forward_grouped(edges: DataFrame, order: str = "degree", split_over: int | None = None) -> DataFrame:
    """The same with one row per source: its list is exploded beside itself, so only the lists of targets are joined."""
    edges = once(edges)
    n = edges.count()
    if n > JOINED_LIMIT:
        return blocks.count_blocks(edges)
    # A list is no longer than the edges, nor than the root of twice their number in the degree order.
    most = 8 * n * (math.isqrt(2 * n) if order == "degree" else n)
    join = "merge" if most > BROADCAST_BYTES else None
    oriented = prep.orient(edges, prep.degrees(edges).hint(join) if join else None, order)
    if most > JOINED_BYTES and _carried(oriented) > JOINED_BYTES:
        return blocks.count_blocks(edges)
    return grouped_total(prep.out_lists(oriented), split_over, join)


def _carried(oriented: DataFrame) -> int:
    """Bytes of the sources' lists that edges carry."""
    sizes = oriented.groupBy("src").agg(F.count(F.lit(1)).alias("k"))
    return 8 * int(sizes.agg(F.sum(F.col("k").cast("double") * F.col("k"))).first()[0] or 0)


def grouped_total(lists: DataFrame, split_over: int | None = None, join: str | None = None) -> DataFrame:
    """The count from ready out-lists (v, nbrs). Only lists of two or more can hold a triangle's lowest vertex, and only lists that are not empty close one. With `split_over`, targets that more lists name are split (see join_hubs), and `join` is the hint of the join with lists."""
    spread = lists.where(F.size("nbrs") > 1).select(F.col("v").alias("src"), F.col("nbrs").alias("nu"), F.explode("nbrs").alias("dst"))
    both = join_hubs(spread, lists.toDF("dst", "nv"), split_over, join)
    return _total("n", both.select(F.size(F.array_intersect("nu", "nv")).cast("long").alias("n")))


def join_hubs(rows: DataFrame, lists: DataFrame, split_over: int | None, join: str | None = None) -> DataFrame:
    """rows (src, dst, ...) with the lists (dst, ...) of their targets, joined on all columns that both have but src.

    A target of more than `split_over` rows is split: its rows are dealt by a hash of the source over so many parts that each holds about that many, and its list, short under
    the degree order as high degrees come last, is copied to each. The table of such targets has at most one row for every `split_over` rows; it is written first, and broadcast only if it is small.
    """
    hinted = lambda df: df.hint(join) if join else df
    keys = [c for c in lists.columns if c in rows.columns and c != "src"]
    if split_over is None:
        return rows.join(hinted(lists), keys)
    hubs = checkpointed(rows.groupBy(*keys).agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > split_over).select(*keys, F.ceil(F.col("n") / F.lit(split_over)).cast("int").alias("parts")))
    many = hubs.count()
    if not many:
        return rows.join(hinted(lists), keys)
    near = F.broadcast(hubs) if many <= HUBS_LIMIT else hubs
    dealt = rows.join(near, keys, "left").withColumn("salt", F.coalesce(F.pmod(F.xxhash64("src"), F.col("parts")).cast("int"), F.lit(0))).drop("parts")
    copied = lists.join(near, keys, "left").withColumn("salt", F.explode(F.sequence(F.lit(0), F.coalesce("parts", F.lit(1)) - 1))).drop("parts")
    return dealt.join(hinted(copied), [*keys, "salt"])


def forward_salted(edges: DataFrame, salt_over: int = 1 << 16, order: str = "degree", split_over: int | None = None) -> DataFrame:
    """The list count with heavy lists cut up, so that no row holds much more than `salt_over` ids whatever the order of vertices.

    A vertex with n out-neighbours deals them by hash to a power of two of parts, one where n is small. The parts of the finer cut nest in those of the coarser one, so an
    edge meets each part of the finer list with the one part of the other list that can share ids with it. `split_over` splits targets that many edges name (see join_hubs).
    """
    o = prep.orient(edges, order=order)
    parts = o.groupBy(F.col("src").alias("v")).agg(F.count(F.lit(1)).alias("n")).select("v", F.expr(f"shiftleft(1, CAST(ceil(log2(greatest(n / {salt_over}D, 1D))) AS INT))").alias("k"))
    within = lambda value, k: value.bitwiseAND(k - 1)
    dealt = o.join(parts.toDF("src", "k"), "src").select(F.col("src").alias("v"), within(F.xxhash64("dst"), F.col("k")).alias("part"), "dst")
    lists = dealt.groupBy("v", "part").agg(F.collect_list("dst").alias("nbrs"))
    both = o.join(parts.toDF("src", "ku"), "src").join(parts.toDF("dst", "kv"), "dst")
    spread = both.withColumn("part", F.explode(F.sequence(F.lit(0), F.greatest("ku", "kv") - 1)))
    met = spread.select("src", "dst", within(F.col("part"), F.col("ku")).cast("long").alias("pu"), within(F.col("part"), F.col("kv")).cast("long").alias("pv"))
    joined = join_hubs(met.join(lists.toDF("src", "pu", "nu"), ["src", "pu"]), lists.toDF("dst", "pv", "nv"), split_over)
    return _total("n", joined.select(F.size(F.array_intersect("nu", "nv")).cast("long").alias("n")))


def forward_exploded(edges: DataFrame) -> DataFrame:
    """One row per list element: several rows work on one edge, each asking for one closing edge by a semi-join."""
    o = prep.orient(edges)
    rows = o.join(o.select("src", F.col("dst").alias("w")), "src").where("dst <> w")
    return rows.join(o.toDF("dst", "w"), ["dst", "w"], "left_semi").agg(F.count(F.lit(1)).alias("triangles"))


def forward_bitmap(edges: DataFrame) -> DataFrame:
    """Out-lists as sparse bit sets of 64 ids a word: words of both ends meet in a join (beyond JOINED_LIMIT edges, in blocks of lists), and shared bits are counted."""
    edges = once(edges)
    if edges.count() > JOINED_LIMIT:
        return blocks.count_blocks(edges)
    o = prep.orient(edges)
    words = o.select(F.col("src").alias("v"), F.expr("dst DIV 64").alias("word"), F.expr("shiftleft(1L, CAST(dst % 64 AS INT))").alias("bit")).groupBy("v", "word").agg(F.bit_or("bit").alias("bits"))
    of_src = o.join(words.toDF("src", "word", "bu"), "src")
    both = of_src.join(words.toDF("dst", "word", "bv"), ["dst", "word"])
    return _total("n", both.select(F.bit_count(F.col("bu").bitwiseAND(F.col("bv"))).cast("long").alias("n")))


def forward_paths(edges: DataFrame) -> DataFrame:
    """Directed two-paths s, a, b kept where the edge s, b exists; a task makes those of a block of sources and looks each up at once, so none is shuffled."""
    return blocks.count_blocks(edges)


def triangles_of(oriented: DataFrame) -> DataFrame:
    """(a, b, c) of every triangle, in the order of rank."""
    hop = oriented.toDF("a", "b").join(oriented.toDF("b", "c"), "b")
    return hop.join(oriented.toDF("a", "c"), ["a", "c"], "left_semi").select("a", "b", "c")


def forward_wedges(edges: DataFrame) -> DataFrame:
    """Pairs of out-neighbours of a vertex, joined to the edge that closes them."""
    o = prep.orient(edges)
    wedges = o.select("src", F.col("dst").alias("u")).join(o.select("src", F.col("dst").alias("v")), "src").where("u < v")
    return wedges.join(edges.select("u", "v"), ["u", "v"]).agg(F.count(F.lit(1)).alias("triangles"))


def edge_iterator(edges: DataFrame) -> DataFrame:
    """The baseline without orientation: whole neighbour lists of both ends of each edge are intersected, and a triangle is seen at its three edges. Beyond JOINED_LIMIT edges whole lists are not carried: the lists of blocks are halved by degree first, and a triangle is seen once."""
    edges = once(edges)
    if edges.count() > JOINED_LIMIT:
        return blocks.count_blocks(edges)
    lists = prep.to_adjacency(prep.edge_array(edges))
    both = edges.join(lists.toDF("u", "nu"), "u").join(lists.toDF("v", "nv"), "v")
    return _total("n", both.select(F.size(F.array_intersect("nu", "nv")).cast("long").alias("n")), 3)


def node_iterator(edges: DataFrame) -> DataFrame:
    """Pairs of neighbours of every vertex that have an edge, seen once from each corner."""
    a = prep.edge_array(edges)
    wedges = a.select("src", F.col("dst").alias("u")).join(a.select("src", F.col("dst").alias("v")), "src").where("u < v")
    return _total("n", wedges.join(edges, ["u", "v"], "left_semi").select(F.lit(1).cast("long").alias("n")), 3)


def brute_force(edges: DataFrame) -> DataFrame:
    """Ordered triples of ids, for checks on small graphs; beyond JOINED_LIMIT edges from blocks of lists."""
    edges = once(edges)
    if edges.count() > JOINED_LIMIT:
        return blocks.count_blocks(edges)
    hop = edges.toDF("a", "b").join(edges.toDF("b", "c"), "b")
    return hop.join(edges.toDF("a", "c"), ["a", "c"]).agg(F.count(F.lit(1)).alias("triangles"))


def matrix(edges: DataFrame) -> DataFrame:
    """The sum of (L L) * L over the strictly upper matrix L of oriented edges: products by a join on the inner index, then cell by cell."""
    l = prep.orient(edges)  # noqa: E741
    product = l.toDF("i", "k").join(l.toDF("k", "j"), "k").groupBy("i", "j").agg(F.count(F.lit(1)).alias("x"))
    return _total("x", product.join(l.toDF("i", "j"), ["i", "j"]))


def hub_hybrid(edges: DataFrame, hubs: int = 256, degree_over: int | None = None) -> DataFrame:
    """Dense counting among the `hubs` highest ranks (of these, with `degree_over`, only vertices of a higher degree), lists for the rest.

    Triangles whose lowest vertex is no hub come from the lists. The others lie among hubs wholly, a block of at most hubs^2 / 2 edges, which one task
    multiplies as a matrix.
    """
    deg = prep.degrees(edges)
    high = deg if degree_over is None else deg.where(F.col("deg") > degree_over)
    top = high.orderBy(F.desc("deg"), F.desc("v")).limit(hubs).select(F.col("v").alias("src"), F.lit(True).alias("hub"))
    o = prep.orient(edges, deg)
    marked = o.join(F.broadcast(top), "src", "left")
    below = attach_lists(marked.where("hub IS NULL").select("src", "dst"), prep.out_lists(o)).select(F.size(F.array_intersect("nu", "nv")).cast("long").alias("n"))

    def multiplied(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        pairs = [(b.column("src").to_numpy(), b.column("dst").to_numpy()) for b in batches]
        if pairs:
            s, d = (np.concatenate(x) for x in zip(*pairs, strict=True))
            ids, at = np.unique(np.concatenate([s, d]), return_inverse=True)
            m = np.zeros((len(ids), len(ids)))
            m[at[: len(s)], at[len(s) :]] = 1
            yield pa.RecordBatch.from_pydict({"n": [int(round(float(((m @ m) * m).sum())))]})

    block = marked.where("hub").select("src", "dst").coalesce(1).mapInArrow(multiplied, "n long")
    return _total("n", below.unionByName(block))


def _one_task(edges: DataFrame, counter, limit: int) -> DataFrame:
    edges = once(edges)
    if edges.count() > limit:
        return blocks.count_blocks(edges, min(limit, blocks.BLOCK_EDGES))
    return _total("triangles", edges.coalesce(1).mapInArrow(counter, "triangles long"))


def _marked_total(start, dst) -> int:
    """Triangles of out-lists one behind the other (list v is dst[start[v] : start[v + 1]]), by marking one list and looking up those of its members."""
    import numpy as np

    total = 0
    mark = np.zeros(len(start) - 1, dtype=bool)
    for v in range(len(start) - 1):
        own = dst[start[v] : start[v + 1]]
        if len(own) > 1:
            mark[own] = True
            total += sum(int(mark[dst[start[w] : start[w + 1]]].sum()) for w in own)
            mark[own] = False
    return total


def forward_local_lists(adjacency: DataFrame, limit: int = LOCAL_LIMIT) -> DataFrame:
    """The single-threaded baseline for ready neighbour lists (v, nbrs) of both directions: degrees are list lengths and no edges are sorted. More than `limit` edges are counted by one task for each block of lists."""

    def counter(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        held = [(b.column("v").to_numpy(), np.diff(b.column("nbrs").offsets.to_numpy()), b.column("nbrs").flatten().to_numpy()) for b in batches]
        total = 0
        if sum(len(v) for v, _, _ in held):
            v, size, near = (np.concatenate(x) for x in zip(*held, strict=True))
            by_id = np.argsort(v)
            rank = np.empty(len(v), dtype=np.int64)
            rank[np.lexsort((v, size))] = np.arange(len(v))
            own, other = np.repeat(rank, size), rank[by_id][np.searchsorted(v[by_id], near)]
            up = other > own
            out = np.bincount(own[up], minlength=len(v))
            begins = np.concatenate([[0], np.cumsum(out)])
            # Lists move to the place of their rank as they are; nothing is compared.
            kept = np.add.reduceat(up, np.concatenate([[0], np.cumsum(size)[:-1]])) if len(up) else np.zeros(len(v), dtype=np.int64)
            at = np.repeat(begins[rank], kept) + np.arange(int(kept.sum())) - np.repeat(np.cumsum(kept) - kept, kept)
            dst = np.empty(len(at), dtype=np.int64)
            dst[at] = other[up]
            total = _marked_total(begins, dst)
        yield pa.RecordBatch.from_pydict({"triangles": [total]})

    n = adjacency.agg(F.coalesce(F.sum(F.size("nbrs")), F.lit(0))).first()[0] // 2
    if n > limit:
        return blocks.count_blocks(_half(adjacency), min(limit, blocks.BLOCK_EDGES))
    return _total("triangles", adjacency.where(F.size("nbrs") > 0).coalesce(1).mapInArrow(counter, "triangles long"))


def _half(adjacency: DataFrame) -> DataFrame:
    """Edges (u, v) of neighbour lists of both directions."""
    return prep.canonical_edges(prep.to_edge_array(adjacency), mode="trust")


def forward_local(edges: DataFrame, limit: int = LOCAL_LIMIT) -> DataFrame:
    """The single-threaded baseline: one task orients, builds sorted lists and intersects. More than `limit` edges are counted by one task for each block of lists."""

    def counter(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        pairs = [np.stack([b.column("u").to_numpy(), b.column("v").to_numpy()]) for b in batches]
        total = 0
        if pairs and sum(p.shape[1] for p in pairs):
            uv = np.concatenate(pairs, axis=1)
            _, at = np.unique(uv, return_inverse=True)
            at = at.reshape(uv.shape)
            deg = np.bincount(at.ravel())
            rank = np.empty(len(deg), dtype=np.int64)
            rank[np.lexsort((np.arange(len(deg)), deg))] = np.arange(len(deg))
            src, dst = np.sort(rank[at], axis=0)
            order = np.lexsort((dst, src))
            total = _marked_total(np.searchsorted(src[order], np.arange(len(deg) + 1)), dst[order])
        yield pa.RecordBatch.from_pydict({"triangles": [total]})

    return _one_task(edges, counter, limit)


def adjacency_input(adjacency: DataFrame) -> DataFrame:
    """The count from ready neighbour lists (v, nbrs) of both directions: degrees are list sizes, so no edge array is sorted or grouped.

    Each list asks for the degrees of its members and keeps those ranked above its own vertex. Beyond JOINED_LIMIT edges
    the lists are cut into blocks, which have the degrees of their vertices as sizes too.
    """
    adjacency = once(adjacency)
    if adjacency.agg(F.coalesce(F.sum(F.size("nbrs").cast("long")), F.lit(0))).first()[0] > 2 * JOINED_LIMIT:
        return blocks.count_blocks(_half(adjacency))
    deg = adjacency.select("v", F.size("nbrs").cast("long").alias("deg"))
    spread = adjacency.select("v", F.size("nbrs").cast("long").alias("deg"), F.explode("nbrs").alias("w"))
    up = spread.join(deg.toDF("w", "dw"), "w").where(F.struct("deg", "v") < F.struct(F.col("dw"), F.col("w")))
    return grouped_total(prep.out_lists(up.select(F.col("v").alias("src"), F.col("w").alias("dst"))))


def forward_dynamic(edges: DataFrame, limit: int = LOCAL_LIMIT) -> DataFrame:
    """The original sequential form, a reference for checks: vertices go from the highest degree down, and the lists that are intersected hold only what has been passed."""

    def counter(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        near: dict[int, list[int]] = {}
        for b in batches:
            for u, v in zip(b.column("u").to_pylist(), b.column("v").to_pylist(), strict=True):
                near.setdefault(u, []).append(v)
                near.setdefault(v, []).append(u)
        place = {v: k for k, v in enumerate(sorted(near, key=lambda v: (-len(near[v]), -v)))}
        passed: dict[int, set[int]] = {v: set() for v in near}
        total = 0
        for v in place:
            for w in near[v]:
                if place[w] > place[v]:
                    total += len(passed[v] & passed[w])
                    passed[w].add(place[v])
        yield pa.RecordBatch.from_pydict({"triangles": [total]})

    return _one_task(edges, counter, limit)


METHODS = {
    "forward_lists": forward_lists, "forward_grouped": forward_grouped, "forward_salted": forward_salted, "forward_exploded": forward_exploded, "forward_bitmap": forward_bitmap,
    "forward_paths": forward_paths, "forward_wedges": forward_wedges, "edge_iterator": edge_iterator, "node_iterator": node_iterator, "brute_force": brute_force,
    "matrix": matrix, "hub_hybrid": hub_hybrid, "forward_local": forward_local, "forward_dynamic": forward_dynamic,
}


def triangle_total(edges: DataFrame, method: str = "auto", **options) -> DataFrame:
    """The number of triangles by any method; "auto" asks the planner, which measures the graph first. For that edges are written once, so that what makes them runs once."""
    if method == "auto":
        from tricount.plans.planner import choose

        edges = once(edges)
        method, options = choose(edges)
    return METHODS[method](edges, **options)
