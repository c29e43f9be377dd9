"""Counting by several workers: strided edges, replicated lists, independent subgraphs."""

from __future__ import annotations

from collections.abc import Iterator
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tricount.functions.lineage import once
from tricount.operators import blocks, count, prep
from tricount.sources.generators import draw

#: Bytes of out-lists up to which they are replicated to every executor: a broadcast is built on the driver, which needs several times its size.
REPLICATE_LIMIT = 1 << 27
#: Edges of a subgraph that one task holds (some 100 bytes each while it counts).
GROUP_EDGES = 4_000_000
#: Classes by which pairs of classes are counted at once, at most if no more are asked for.
FINE_CLASSES = 256
#: Pairs of list elements that a task looks at at once.
LOOKED_AT = 1 << 20


def _numbered(oriented: DataFrame) -> DataFrame:
    """Rows with their place `no` in the array sorted by (src, dst): the start of the source's run plus the place in it."""
    lists = prep.out_lists(oriented)
    runs = prep.prefix_sum(lists.select("v", "nbrs", F.size("nbrs").cast("long").alias("n")), "v", "n")
    return runs.select(F.col("v").alias("src"), F.posexplode("nbrs").alias("at", "dst"), "before").select("src", "dst", (F.col("before") + F.col("at")).alias("no"))


def count_by_worker(edges: DataFrame, workers: int) -> DataFrame:
    """(worker, edges, triangles): worker w takes every edge whose place in the sorted array is w modulo the number of workers."""
    oriented = prep.orient(edges)
    dealt = _numbered(oriented).withColumn("worker", F.pmod("no", F.lit(workers)).cast("int")).select("src", "dst", "worker")
    lists = prep.out_lists(oriented)
    both = dealt.join(lists.toDF("dst", "nv"), "dst", "left").join(lists.toDF("src", "nu"), "src")
    found = F.coalesce(F.size(F.array_intersect("nu", "nv")), F.lit(0)).cast("long")
    return both.select("worker", found.alias("n")).groupBy("worker").agg(F.count(F.lit(1)).alias("edges"), F.sum(F.greatest("n", F.lit(0))).alias("triangles"))


def list_bytes(lists: DataFrame) -> int:
    """Bytes of out-lists as rows: 8 for each element, and some 48 for each list."""
    return lists.agg(F.coalesce(F.sum(F.size("nbrs").cast("long") * 8 + 48), F.lit(0))).first()[0]


def device_slices(oriented: DataFrame, devices: int, split: str = "hash") -> DataFrame:
    """Oriented edges with `slice`, the device that counts them: by hash, by stride of the place in the sorted array, or by ranges of it."""
    if split == "strided":
        cut = _numbered(oriented).withColumn("slice", F.pmod("no", F.lit(devices)))
    elif split == "range":
        cut = _numbered(oriented).withColumn("slice", F.expr(f"least(no DIV greatest({oriented.count()} DIV {devices}, 1), {devices - 1})"))
    else:
        cut = oriented.withColumn("slice", F.pmod(F.xxhash64("src", "dst"), F.lit(devices)))
    return cut.select("src", "dst", F.col("slice").cast("int").alias("slice"))


def count_slices(cut: DataFrame, lists: DataFrame, replicate: bool) -> DataFrame:
    """(slice, edges, triangles) of sliced edges, with lists that go to every executor whole or are shuffled."""
    near = F.broadcast(lists) if replicate else lists
    both = cut.join(near.toDF("src", "nu"), "src").join(near.toDF("dst", "nv"), "dst", "left")
    found = F.when(F.col("nv").isNull(), 0).otherwise(F.size(F.array_intersect("nu", "nv"))).cast("long")
    return both.select("slice", found.alias("n")).groupBy("slice").agg(F.count(F.lit(1)).alias("edges"), F.sum("n").alias("triangles"))


def count_replicated(edges: DataFrame, devices: int, split: str = "hash", limit: int = REPLICATE_LIMIT) -> DataFrame:
    """(slice, edges, triangles): lists are made once and go to every executor, edges are split by hash, stride or range of the source.

    Lists are only replicated where their size, measured first, is within `limit` bytes; beyond it the same slices are counted with shuffled lists. Beyond
    count.JOINED_LIMIT edges slices are counted from blocks of lists, which lie in the shared folder for all devices (the hash is another one then).
    """
    edges = once(edges)
    if edges.count() > count.JOINED_LIMIT:
        return blocks.slice_counts(edges, devices, split)
    oriented = prep.orient(edges)
    lists = prep.out_lists(oriented)
    return count_slices(device_slices(oriented, devices, split), lists, list_bytes(lists) <= limit)


class Prepared:
    """Oriented edges and out-lists made once and kept, from which any number of devices count. A device is so many cores: its slice is dealt over that many tasks."""

    def __init__(self, edges: DataFrame, cores_each: int, limit: int = REPLICATE_LIMIT) -> None:
        self.oriented = prep.orient(edges).persist()
        self.lists = prep.out_lists(self.oriented).persist()
        self.cores_each = cores_each
        self.edges = self.oriented.count()
        self.replicate = list_bytes(self.lists) <= limit

    def count(self, devices: int) -> DataFrame:
        """(slice, edges, triangles), on devices * cores_each tasks and no more."""
        tasks = devices * self.cores_each
        cut = self.oriented.withColumn("slice", F.pmod(F.xxhash64("src", "dst"), F.lit(devices)).cast("int"))
        dealt = cut.repartition(tasks, "slice", F.pmod(F.xxhash64("dst", "src"), F.lit(self.cores_each))) if tasks > 1 else cut.coalesce(1)
        return count_slices(dealt, self.lists, self.replicate)

    def drop(self) -> None:
        self.lists.unpersist()
        self.oriented.unpersist()


def cores_of(spark: SparkSession) -> int:
    return spark.sparkContext.defaultParallelism


def _colour(v: Column, rho: int, seed: int) -> Column:
    return (draw(v, seed) % rho).cast("int")


def subgraph_edges(edges: DataFrame, rho: int, variant: str = "multiset", seed: int = 1) -> DataFrame:
    """Edges copied to the subgraphs that need them: key (three classes), u, v, and the classes of both ends.

    "multiset": keys are the sorted triples of classes, repeats allowed; an edge goes to the rho keys that its two classes can be part of.
    "weighted": keys are triples of different classes; an edge goes to every one that holds its classes, and what is seen several times is weighed.
    """
    cu, cv = _colour(F.col("u"), rho, seed), _colour(F.col("v"), rho, seed)
    marked = edges.select("u", "v", cu.alias("cu"), cv.alias("cv"))
    if variant == "multiset":
        third = marked.withColumn("x", F.explode(F.sequence(F.lit(0), F.lit(rho - 1))))
        return third.select(F.sort_array(F.array("cu", "cv", "x")).alias("key"), "u", "v", "cu", "cv")
    triples = F.array(*[F.array(F.lit(i), F.lit(j), F.lit(k)) for i in range(rho) for j in range(i) for k in range(j)])
    fits = F.filter(triples, lambda t: F.array_contains(t, F.col("cu")) & F.array_contains(t, F.col("cv")))
    return marked.select(F.explode(fits).alias("key"), "u", "v", "cu", "cv")


def local_triangles(u: np.ndarray, v: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Triangles of the edges (u, v) that one task holds, as arrays of their corners: edges are oriented by degree, and for each edge the out-list of its target is looked up in that of its source."""
    ids, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    n = len(ids)
    degree = np.bincount(at, minlength=n)
    order = np.lexsort((np.arange(n), degree))
    rank = np.empty(n, dtype=np.int64)
    rank[order] = np.arange(n)
    ends = np.sort(rank[at].reshape(2, -1), axis=0)
    key = np.sort(ends[0] * n + ends[1])
    src, dst = key // n, key % n
    begin = np.searchsorted(src, np.arange(n + 1))
    size = (begin[1:] - begin[:-1])[dst]
    upto = np.concatenate([[0], np.cumsum(size)])
    name = ids[order]
    first = 0
    while first < len(src):
        last = max(first + 1, int(np.searchsorted(upto, upto[first] + LOOKED_AT, side="right")) - 1)
        edge = np.repeat(np.arange(first, last), size[first:last])
        third = dst[begin[dst[edge]] + np.arange(len(edge)) - (upto[edge] - upto[first])]
        asked = src[edge] * n + third
        spot = np.minimum(np.searchsorted(key, asked), len(key) - 1)
        hit = key[spot] == asked
        yield name[src[edge[hit]]], name[dst[edge[hit]]], name[third[hit]]
        first = last


def count_partitioned(edges: DataFrame, rho: int = 4, variant: str = "multiset", seed: int = 1, budget: int = GROUP_EDGES) -> DataFrame:
    """One row, `triangles`: every subgraph is held and counted by one task on its own, and each triangle adds up to one.

    A multiset key counts only triangles whose own classes are the key. In the weighted form a triangle with 1, 2 or 3 different classes is seen in
    C(rho - 1, 2), rho - 2 or 1 subgraphs; weights are integers over the common denominator C(rho - 1, 2) (rho - 2).
    The largest subgraph is measured first; beyond `budget` edges there are more classes, until it fits (so a graph of any size can be counted).
    Edges lie once in files of the shared folder, one for each pair of classes; a task reads the few that make its subgraph, so copies of edges are read but never moved or stored.
    """
    if variant == "weighted" and rho < 3:
        raise ValueError("the weighted form needs 3 classes or more")
    spark, edges = edges.sparkSession, once(edges)
    fine = rho
    while 2 * fine <= FINE_CLASSES:
        fine *= 2
    pairs = _class_pairs(edges, fine, seed)
    while (keys := _keys_within(pairs, fine, rho, variant, budget)) is None:
        rho *= 2
        if rho > 1 << 10:
            raise ValueError(f"subgraphs of {budget} edges cannot hold this graph: one vertex has too many edges")
        if rho > fine:
            fine = rho
            pairs = _class_pairs(edges, fine, seed)
    one, two = (comb(rho - 1, 2), rho - 2) if variant == "weighted" else (1, 1)
    folder = blocks.Folder(blocks.fresh_uri(spark))
    there = {(int(x) % rho, int(y) % rho) for x, y in pairs[:, :2]}
    there = {(min(p), max(p)) for p in there}

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for batch in batches:
            held.append([batch.column(c).to_numpy() for c in ("u", "v", "cu", "cv")])
            n += batch.num_rows
            if n >= blocks.CUT_EDGES:
                yield _by_pair(held, rho)
                held, n = [], 0
        if n:
            yield _by_pair(held, rho)

    def kept(group: pa.Table) -> pa.Table:
        u, v = (np.concatenate(x) for x in zip(*[blocks._unpacked(x.as_py(), 2) for x in group.column("data")], strict=True))
        order = np.lexsort((v, u))
        folder.save(f"pair-{group.column('pair')[0].as_py()}", u=u[order], v=v[order])
        return pa.table({"n": pa.array([len(u)], pa.int64())})

    marked = edges.select(F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v"), _colour(F.col("u"), rho, seed).alias("cu"), _colour(F.col("v"), rho, seed).alias("cv"))
    marked.mapInArrow(cut, "pair long, data binary").groupBy("pair").applyInArrow(kept, "n long").agg(F.sum("n")).collect()

    def counted(key: tuple[int, ...]) -> int:
        mine = [p for p in _pairs_of(key, variant) if p in there]
        if not mine:
            return 0
        held = [folder.load(f"pair-{i * rho + j}") for i, j in mine]
        u, v = (np.concatenate(x) for x in zip(*held, strict=True))
        ids, at = np.unique(np.concatenate([u, v]), return_index=True)
        size = [len(x) for x, _ in held]
        of = np.concatenate([np.repeat([p[0] for p in mine], size), np.repeat([p[1] for p in mine], size)])[at]
        total = 0
        for corners in local_triangles(u, v):
            own = np.sort(np.stack([of[np.searchsorted(ids, c)] for c in corners]), axis=0)
            if variant == "multiset":
                total += int((own == np.array(key)[:, None]).all(axis=0).sum())
            else:
                kinds = 1 + (own[1:] != own[:-1]).sum(axis=0)
                total += int(np.choose(kinds - 1, [two, one, one * two]).sum())
        return total

    def tasks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in batch.column("id").to_pylist():
                yield pa.RecordBatch.from_pydict({"w": pa.array([counted(tuple(keys[k].tolist()))], pa.int64())})

    found = spark.range(0, len(keys), 1, max(1, min(len(keys), 8 * cores_of(spark)))).mapInArrow(tasks, "w long")
    return found.agg(F.coalesce(F.sum("w"), F.lit(0)).alias("w")).select(F.expr(f"CAST(w DIV {one * two} AS BIGINT)").alias("triangles"))


def _class_pairs(edges: DataFrame, classes: int, seed: int) -> np.ndarray:
    """Rows (class, class, edges) of the pairs of classes that have edges: at most classes^2, which the driver holds. A draw's class among fewer classes that divide these is its remainder."""
    cu, cv = _colour(F.col("u"), classes, seed), _colour(F.col("v"), classes, seed)
    sizes = edges.select(F.least(cu, cv).alias("x"), F.greatest(cu, cv).alias("y")).groupBy("x", "y").agg(F.count(F.lit(1)).alias("n")).toArrow()
    return np.stack([c.to_numpy().astype(np.int64) for c in sizes.columns], axis=1)


def _pairs_of(key: tuple[int, ...], variant: str) -> list[tuple[int, int]]:
    """The pairs of classes whose edges a subgraph holds: two places of a multiset key, or any two classes of a weighted one, twice the same too."""
    i, j, k = sorted(key)
    return sorted({(i, j), (i, k), (j, k)} | ({(i, i), (j, j), (k, k)} if variant == "weighted" else set()))


def _keys_within(pairs: np.ndarray, fine: int, rho: int, variant: str, budget: int) -> np.ndarray | None:
    """The keys (rows of three classes) of the subgraphs that can count something, or None where a subgraph has more than `budget` edges."""
    size = np.zeros((rho, rho), dtype=np.int64)
    x, y = pairs[:, 0] % rho, pairs[:, 1] % rho
    np.add.at(size, (np.minimum(x, y), np.maximum(x, y)), pairs[:, 2])
    size = np.maximum(size, size.T)
    alone = np.diag(size).copy()
    keys = [np.zeros((0, 3), dtype=np.int64)]
    for i in range(rho):
        own, rest = size[i, i + 1 :], size[i + 1 :, i + 1 :]
        edges = own[:, None] + own[None, :] + rest
        useful = (own[:, None] > 0) & (own[None, :] > 0) & (rest > 0)
        if variant == "weighted":
            edges = edges + alone[i] + alone[i + 1 :, None] + alone[None, i + 1 :]
            useful = edges > 0
        elif max(int(alone[i]), int((alone[i] + np.delete(size[i], i)).max(initial=0))) > budget:
            return None
        if np.triu(edges, 1).max(initial=0) > budget:
            return None
        j, k = np.nonzero(np.triu(useful, 1))
        keys.append(np.stack([np.full(len(j), i), i + 1 + j, i + 1 + k], axis=1))
        if variant == "multiset" and alone[i]:
            with_two = np.flatnonzero(size[i])  # the class itself among them
            keys.append(np.sort(np.stack([np.full(len(with_two), i), np.full(len(with_two), i), with_two], axis=1), axis=1))
    return np.concatenate(keys)


def _by_pair(held: list, rho: int) -> pa.RecordBatch:
    """Edges as packed rows of their pair of classes, the end of the lower class first."""
    u, v, cu, cv = (np.concatenate(x) for x in zip(*held, strict=True))
    turned = cu > cv
    u, v = np.where(turned, v, u), np.where(turned, u, v)
    pair = np.minimum(cu, cv).astype(np.int64) * rho + np.maximum(cu, cv)
    order = np.lexsort((v, u, pair))
    u, v, pair = u[order], v[order], pair[order]
    first = np.flatnonzero(np.concatenate([[True], pair[1:] != pair[:-1]]))
    ends = [*first[1:].tolist(), len(pair)]
    data = [blocks._packed(u[a:b], v[a:b]) for a, b in zip(first.tolist(), ends, strict=True)]
    return pa.RecordBatch.from_pydict({"pair": pa.array(pair[first]), "data": pa.array(data, pa.binary())})


def partition_costs(edges: DataFrame, rho: int, variant: str = "multiset", seed: int = 1) -> DataFrame:
    """One row: copies of edges, groups, and the edges of the largest group."""
    sizes = subgraph_edges(edges, rho, variant, seed).groupBy("key").agg(F.count(F.lit(1)).alias("n"))
    return sizes.agg(F.sum("n").alias("copies"), F.count(F.lit(1)).alias("groups"), F.max("n").alias("largest"))
