"""Edges (u, v) of the graphs that the given tables hold, and of edge lists in files."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from math import comb

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tricount.functions.lineage import checkpointed, written
from tricount.operators.blocks import Folder, _mixed, _packed, _unpacked, fresh_uri
from tricount.operators.count import triangle_total
from tricount.operators.prep import canonical_edges, dense_ids

#: A group of more members than this is never paired by one task.
GROUP_TILE = 2048
#: Parts of the members that meet two by two in a task, at least; members of sets in a part on average, at most; bytes of bits, or of 64 for each pair, that a task holds.
PAIR_BLOCKS, PAIR_MEMBERS, PAIR_BYTES = 8, 1_000_000, 1 << 26
#: Pairs of members from which they are shuffled packed, if there are over SHARED for each member of a set; pairs made unique at once, and bits of the ids of second members that lie in one part.
PACKED_OVER, SHARED, MADE_PAIRS, CELL_BITS = 1 << 24, 8, 1 << 22, 16
#: Pairs of members made at once, and how many members come again and again.
CROSSED, RUN = 1 << 18, 256
#: Classes of members in a part on average where they are counted by matrices; that is done unless their pairs are fewer than the square of the classes over SPARSE.
MATRIX_CLASSES, SPARSE = 2048, 32
#: Vectors scored at once against a block of others.
VECTOR_TILE = 1024
#: Different words that a task holds at most (some 15 bytes each), and of a file; words of texts and pairs held at once; pairs of a part on average (16 bytes each), and parts that the pairs of one word go to.
NAMED_WORDS, LISTED_WORDS, HELD_TOKENS, HELD_PAIRS, PART_PAIRS, PIECES = 1 << 24, 1 << 20, 1 << 20, 1 << 22, 1 << 21, 64


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _sets(df: DataFrame, group: list[str], member: str) -> DataFrame:
    """Members that share a group, at least two, as sets `xs`."""
    there = F.col(member).isNotNull()
    for g in group:
        there &= F.col(g).isNotNull()
    return df.where(there).groupBy(*group).agg(F.collect_set(member).alias("xs")).where(F.size("xs") > 1).select("xs")


def edges_from_projection(df: DataFrame, group: list[str], member: str) -> DataFrame:
    """Members that share a group. Each group is gathered once as a set and pairs its members where it lies; pairs are made unique.

    The sizes of groups are measured first. Where pairs outnumber what _tiled_pairs() would move, it makes them unique before they leave a task; else they are shuffled once, packed where they are many.
    """
    sets = _sets(df, group, member)
    n = F.size("xs").cast("double")
    size = sets.agg(F.sum(n).alias("members"), F.sum(n * (n - 1) / 2).alias("pairs"), F.max(n).alias("largest")).first()
    parts = max(PAIR_BLOCKS, -(-int(size.members or 0) // PAIR_MEMBERS))
    if (size.largest or 0) > GROUP_TILE or (size.pairs or 0) > 8 * (parts + 1) * (size.members or 0):
        return _tiled_pairs(sets, df.schema[member].dataType)
    if (size.pairs or 0) > max(PACKED_OVER, SHARED * (size.members or 0)) and isinstance(df.schema[member].dataType, T.IntegralType):
        return _packed_pairs(sets, df.schema[member].dataType, max(1, -(-int(size.pairs) // PART_PAIRS)))
    pairs = F.flatten(F.transform("xs", lambda x: F.transform(F.filter("xs", lambda y: y > x), lambda y: F.struct(x.alias("u"), y.alias("v")))))
    return sets.select(F.explode(pairs).alias("p")).select("p.u", "p.v").distinct()


def _packed_pairs(sets: DataFrame, kind: T.DataType, parts: int) -> DataFrame:
    """Unique pairs (u < v) of members of sets `xs`. A task makes the pairs of some sets at a time and shuffles those that differ, compressed, to parts, which make them unique; there they take a byte or two each."""

    def paired(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0

        def sent() -> pa.RecordBatch:
            u, v = _pairs_of_sets(*(np.concatenate(x) for x in zip(*held, strict=True)))
            # Pairs are dealt by runs of the same u and the same range of v, so that those of a frequent member are dealt over several parts.
            near = v >> CELL_BITS
            first = np.flatnonzero(np.concatenate([[True], (u[1:] != u[:-1]) | (near[1:] != near[:-1])]))
            run = np.diff(first, append=len(u))
            of = (_mixed(_mixed(u[first]).view(np.int64) + near[first]) % np.uint64(parts)).astype(np.int64)
            order = np.argsort(of, kind="stable")
            run, first = run[order], first[order]
            at = np.repeat(first - (np.cumsum(run) - run), run) + np.arange(len(u))
            u, v = u[at], v[at]
            ends = np.concatenate([[0], np.cumsum(run)])[np.searchsorted(of[order], np.arange(parts + 1))]
            there = np.flatnonzero(np.diff(ends)).tolist()
            return pa.RecordBatch.from_pydict({"part": pa.array(there, pa.int64()), "data": pa.array([_packed(u[ends[k] : ends[k + 1]], v[ends[k] : ends[k + 1]]) for k in there], pa.binary())})

        for batch in batches:
            xs = batch.column("xs")
            x, begin = xs.flatten().to_numpy(), xs.offsets.to_numpy().astype(np.int64)
            begin, size = begin - begin[0], np.diff(begin)
            upto = np.concatenate([[0], np.cumsum(size * (size - 1) // 2)])
            first = 0
            while first < len(size):
                last = max(first + 1, int(np.searchsorted(upto, upto[first] + MADE_PAIRS - n, side="right")) - 1)
                held.append((x[begin[first] : begin[last]], size[first:last]))
                n += int(upto[last] - upto[first])
                first = last
                if first < len(size) or n >= MADE_PAIRS:
                    yield sent()
                    held, n = [], 0
        if n:
            yield sent()

    def gathered(group: pa.Table) -> pa.Table:
        u, v = (np.concatenate(x) for x in zip(*[_unpacked(x.as_py(), 2) for x in group.column("data")], strict=True))
        least, low = int(u.min()), int(v.min())
        wide = int(v.max()) - low + 1
        if (int(u.max()) - least + 1) * wide < 1 << 63:
            key = _different((u - least) * wide + (v - low))
            return pa.table({"u": key // wide + least, "v": key % wide + low})
        order = np.lexsort((v, u))
        u, v = u[order], v[order]
        new = np.concatenate([[True], (u[1:] != u[:-1]) | (v[1:] != v[:-1])])
        return pa.table({"u": u[new], "v": v[new]})

    dealt = sets.select(F.col("xs").cast("array<long>").alias("xs")).mapInArrow(paired, "part long, data binary")
    return dealt.groupBy("part").applyInArrow(gathered, "u long, v long").select(F.col("u").cast(kind).alias("u"), F.col("v").cast(kind).alias("v"))


def _different(key: np.ndarray) -> np.ndarray:
    """The different values of an array that is not empty, sorted."""
    key = np.sort(key)
    return key[np.concatenate([[True], key[1:] != key[:-1]])]


def _pairs_of_sets(x: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The different pairs (u < v), sorted, of members of sets of two and more that lie one behind the other in `x`. Members at each distance in a sorted set are paired at once, larger sets first, so that those too small are at the end."""
    ids, code = np.unique(x, return_inverse=True)
    place = np.empty(len(size), dtype=np.int64)
    place[order := np.argsort(-size, kind="stable")] = np.arange(len(size))
    code = np.sort(np.repeat(place, size) * len(ids) + code) % len(ids)
    size = size[order]
    end = np.cumsum(size)
    left = np.repeat(end, size) - np.arange(len(code))  # members of the set from here on
    found = []
    for gap in range(1, int(size[0])):
        upto = int(end[np.searchsorted(-size, -gap) - 1])
        at = np.flatnonzero(left[: upto - gap] > gap)
        found.append(code[at] * len(ids) + code[at + gap])
    key = _different(np.concatenate(found))
    u = key // len(ids)
    return ids[u], ids[key - u * len(ids)]


def _classes(sets: DataFrame) -> DataFrame:
    """(sets, xs): members of sets `xs` that lie in the same sets, and the numbers of these; written. The members of such a class meet each other and the same others, so they are looked at once."""
    numbered = written(sets.select(F.monotonically_increasing_id().alias("n"), F.col("xs").cast("array<long>").alias("xs")))
    of = numbered.select(F.explode("xs").alias("x"), "n").groupBy("x").agg(F.sort_array(F.collect_list("n")).alias("sets"))
    return written(of.groupBy("sets").agg(F.collect_list("x").alias("xs")))


class ClassPart:
    """The classes of a part: `place` and `set` of each class and set it lies in, and the members of class k as x[begin[k] : begin[k + 1]]."""

    def __init__(self, folder: Folder, part: int) -> None:
        (self.place, self.set), (self.begin,), (self.x,) = (folder.load(f"{kind}-{part}") for kind in ("sets", "begin", "members"))
        self.size = np.diff(self.begin)

    def met(self, other: ClassPart) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """The classes of both that lie in a common set, each pair once, sorted by this part's class."""
        both = np.intersect1d(self.set, other.set)
        if not len(both):
            return

        def inside(p: ClassPart) -> tuple[np.ndarray, np.ndarray]:
            at = np.minimum(np.searchsorted(both, p.set), len(both) - 1)
            here = both[at] == p.set
            return p.place[here].astype(np.int64), at[here]

        yield from unique_pairs(*inside(self), *inside(other), len(both))

    def members(self, classes: np.ndarray) -> np.ndarray:
        """The members of some classes, sorted."""
        size = self.size[classes]
        upto = np.cumsum(size) - size
        return np.sort(self.x[np.repeat(self.begin[classes] - upto, size) + np.arange(int(size.sum()))])


def _class_parts(classes: DataFrame, parts: int) -> tuple[Folder, list[int]]:
    """Classes by parts in files of the shared folder, and which of the parts have any."""
    folder = Folder(fresh_uri(classes.sparkSession))

    def kept(group: pa.Table) -> pa.Table:
        part = group.column("part")[0].as_py()
        sets, xs = (group.column(name).combine_chunks() for name in ("sets", "xs"))
        size, of = np.diff(sets.offsets.to_numpy()), np.diff(xs.offsets.to_numpy())
        folder.save(f"sets-{part}", place=np.repeat(np.arange(len(size), dtype=np.int32), size), set=sets.flatten().to_numpy())
        folder.save(f"begin-{part}", begin=np.concatenate([[0], np.cumsum(of)]).astype(np.int64))
        x = xs.flatten().to_numpy()
        folder.save(f"members-{part}", x=x[np.lexsort((x, np.repeat(np.arange(len(of)), of)))])
        return pa.table({"part": pa.array([part], pa.int64())})

    dealt = classes.withColumn("part", F.pmod(F.xxhash64("sets"), F.lit(parts))).groupBy("part").applyInArrow(kept, "part long")
    return folder, sorted(r.part for r in dealt.collect())


def _for_two(spark: SparkSession, parts: list[int], run: Callable[[int, int], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    """The rows that `run` gives for each two of the parts, and for each part with itself; a task for each."""
    two = [(i, j) for k, i in enumerate(parts) for j in parts[k:]]

    def tasks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in batch.column("id").to_pylist():
                yield from run(*two[k])

    return spark.range(0, len(two), 1, max(1, len(two))).mapInArrow(tasks, schema)


def _tiled_pairs(sets: DataFrame, kind: T.DataType) -> DataFrame:
    """Unique pairs (u < v) of members of sets `xs`. Classes of members that lie in the same sets fall into parts by hash, and a task reads two of the parts: pairs of classes are made unique there, as
    bit sets or by sorting, and then give those of their members. No pairs are shuffled, and a member and its sets are written once."""
    classes = _classes(sets)
    size = classes.agg(F.sum(F.size("sets").cast("long"))).first()[0] or 0
    folder, parts = _class_parts(classes, max(PAIR_BLOCKS, -(-size // PAIR_MEMBERS)))

    def pairs(i: int, j: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        one, other = ClassPart(folder, i), ClassPart(folder, j)
        for x, y in one.met(other):
            if i == j:
                for k in np.unique(x[(x == y) & (one.size[x] > 1)]).tolist():
                    own = one.x[one.begin[k] : one.begin[k + 1]]
                    yield from ((a[a < b], b[a < b]) for a, b in _crossed(own, own))
                x, y = x[x < y], y[x < y]
            single = (one.size[x] == 1) & (other.size[y] == 1)
            yield one.x[one.begin[x[single]]], other.x[other.begin[y[single]]]
            x, y = x[~single], y[~single]
            start = np.flatnonzero(np.concatenate([[True], x[1:] != x[:-1]])) if len(x) else x
            for a, b in zip(start, np.append(start, len(x))[1:], strict=True):
                yield from _crossed(one.x[one.begin[x[a]] : one.begin[x[a] + 1]], other.members(y[a:b]))

    def run(i: int, j: int) -> Iterator[pa.RecordBatch]:
        def batch() -> pa.RecordBatch:
            a, b = (np.concatenate(x) for x in zip(*held, strict=True))
            return pa.RecordBatch.from_arrays([pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b))], names=["u", "v"])

        held, n = [], 0
        for a, b in pairs(i, j):
            held.append((a, b))
            n += len(a)
            if n >= CROSSED:
                yield batch()
                held, n = [], 0
        if n:
            yield batch()

    met = _for_two(sets.sparkSession, parts, run, "u long, v long")
    return met.select(F.col("u").cast(kind).alias("u"), F.col("v").cast(kind).alias("v"))


def _crossed(a: np.ndarray, b: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Each of `a` with each of `b`, some CROSSED at a time. Runs of `b` come again and again, as the members of `a` take turns: encoded and compressed, such rows take a fraction of those in another order."""
    for k in range(0, len(a), RUN):
        own = a[k : k + RUN]
        step = max(1, CROSSED // (len(own) * RUN)) * RUN
        for s in range(0, len(b), step):
            some = b[s : s + step]
            whole = len(some) // RUN * RUN
            for runs in (some[:whole].reshape(-1, 1, RUN), some[whole:].reshape(1, 1, -1)):
                if runs.size:
                    shape = (len(runs), len(own), runs.shape[2])
                    yield np.broadcast_to(own[None, :, None], shape).ravel(), np.broadcast_to(runs, shape).ravel()


def triangles_from_projection(df: DataFrame, group: list[str], member: str) -> DataFrame:
    """One row, `triangles`, of the graph of edges_from_projection(), whose edges are not made where they are dense: then classes of members that lie in the same sets are counted by matrix products."""
    classes = _classes(_sets(df, group, member))
    n = classes.count()
    met = F.col("n").cast("double")
    pairs = classes.select(F.explode("sets").alias("set")).groupBy("set").agg(F.count(F.lit(1)).alias("n")).agg(F.sum(met * (met - 1) / 2)).first()[0] or 0
    if SPARSE * pairs < n * n:
        return triangle_total(edges_from_projection(df, group, member))
    return _class_triangles(classes, max(1, -(-n // MATRIX_CLASSES)))


def _class_triangles(classes: DataFrame, parts: int) -> DataFrame:
    """A task takes two parts of the classes and meets them with each part from the second on. A triangle's corners lie in three classes, in two, or in one; how many members these have is the weight."""
    folder, parts = _class_parts(classes, parts)

    def run(i: int, j: int) -> Iterator[pa.RecordBatch]:
        def matrix(a: tuple[int, ClassPart], b: tuple[int, ClassPart], kind: type) -> np.ndarray:
            out = np.zeros((len(a[1].size), len(b[1].size)), dtype=kind)
            for x, y in a[1].met(b[1]):
                out[x, y] = 1
            return np.triu(out, 1) if a[0] == b[0] else out

        one, other = ((k, ClassPart(folder, k)) for k in (i, j))
        w, their = one[1].size, other[1].size
        edges = matrix(one, other, np.float32)
        two, their_two = w * (w - 1) // 2, their * (their - 1) // 2
        total = sum(int(a @ (edges @ b.astype(np.float64)).astype(np.int64)) for a, b in ((two, their), (w, their_two)))
        if i == j:
            total += sum(comb(int(k), 3) for k in w)
        for k in parts[parts.index(j) :]:
            third = k, ClassPart(folder, k)
            # Sums of whole numbers are exact up to 2^24 in one kind and 2^53 in the other.
            kind = np.float32 if third[1].size.sum() < 1 << 24 else np.float64
            through = (matrix(one, third, kind) * third[1].size.astype(kind)) @ matrix(other, third, kind).T
            total += int(w @ ((edges * through).astype(np.int64) @ their))
        yield pa.RecordBatch.from_pydict({"n": pa.array([total], pa.int64())})

    return _for_two(classes.sparkSession, parts, run, "n long").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("triangles"))


def unique_pairs(a: np.ndarray, of_a: np.ndarray, b: np.ndarray, of_b: np.ndarray, sets: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Each pair (x, y) once for which some set has x in `a` and y in `b`; of_a and of_b number the sets, below `sets`."""
    xs, x = np.unique(a, return_inverse=True)
    ys, y = np.unique(b, return_inverse=True)
    order = np.lexsort((of_a, x))
    x, of_x = x[order], of_a[order]
    by_set = np.argsort(of_b, kind="stable")
    y, begin = y[by_set], np.searchsorted(of_b[by_set], np.arange(sets + 1))
    size = np.diff(begin)[of_x]
    starts = np.searchsorted(x, np.arange(len(xs) + 1))
    width = -(-len(ys) // 8)
    if sets * width <= PAIR_BYTES and len(x) * width <= 16 * int(size.sum()):
        bits = np.zeros((sets, 8 * width), dtype=bool)
        bits[of_b[by_set], y] = True
        bits = np.packbits(bits, axis=1)
        first = 0
        while first < len(xs):
            last = max(first + 1, int(np.searchsorted(starts, starts[first] + max(1, PAIR_BYTES // (8 * width)), side="right")) - 1)
            last = min(last, first + max(1, PAIR_BYTES // (64 * width)))
            reached = np.bitwise_or.reduceat(bits[of_x[starts[first] : starts[last]]], starts[first:last] - starts[first], axis=0)
            row, column = np.nonzero(np.unpackbits(reached, axis=1))
            yield xs[first + row], ys[column]
            first = last
        return
    upto = np.concatenate([[0], np.cumsum(size)])
    first = 0
    while first < len(xs):
        last = max(first + 1, int(np.searchsorted(upto[starts], upto[starts[first]] + PAIR_BYTES // 64, side="right")) - 1)
        span = slice(starts[first], starts[last])
        each = np.repeat(np.arange(starts[first], starts[last]), size[span])
        at = begin[of_x[each]] + np.arange(len(each)) - (upto[each] - upto[starts[first]])
        pair = np.unique(x[each] * len(ys) + y[at])
        yield xs[pair // len(ys)], ys[pair % len(ys)]
        first = last


def copurchase(spark: SparkSession, sf_dir: str, where: Column | None = None) -> DataFrame:
    return edges_from_projection(_lines(spark, sf_dir, where), ["l_orderkey"], "l_partkey")


def cosupply_order(spark: SparkSession, sf_dir: str, where: Column | None = None) -> DataFrame:
    return edges_from_projection(_lines(spark, sf_dir, where), ["l_orderkey"], "l_suppkey")


def cosupply_part(spark: SparkSession, sf_dir: str, where: Column | None = None) -> DataFrame:
    return edges_from_projection(_lines(spark, sf_dir, where), ["l_partkey"], "l_suppkey")


def _lines(spark: SparkSession, sf_dir: str, where: Column | None) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem")
    return lines if where is None else lines.where(where)


def tripartite(spark: SparkSession, sf_dir: str, where: Column | None = None) -> DataFrame:
    """Customers, parts and suppliers of an order line: ids 3k, 3k + 1, 3k + 2."""
    lines = _lines(spark, sf_dir, where).join(table(spark, sf_dir, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    c, p, s = 3 * F.col("o_custkey"), 3 * F.col("l_partkey") + 1, 3 * F.col("l_suppkey") + 2
    three = F.array(*[F.struct(a.alias("src"), b.alias("dst")) for a, b in ((c, p), (c, s), (p, s))])
    return canonical_edges(lines.select(F.explode(three).alias("e")).select("e.src", "e.dst"))


def order_part(spark: SparkSession, sf_dir: str, where: Column | None = None) -> DataFrame:
    """Orders and their parts, a bipartite graph: ids 2k and 2k + 1."""
    return canonical_edges(_lines(spark, sf_dir, where).select((2 * F.col("l_orderkey")).alias("src"), (2 * F.col("l_partkey") + 1).alias("dst")))


def coactive(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users with an event of the same type in the same hour."""
    return edges_from_projection(*_active(spark, sf_dir))


def coactive_triangles(spark: SparkSession, sf_dir: str) -> DataFrame:
    return triangles_from_projection(*_active(spark, sf_dir))


def _active(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, list[str], str]:
    return table(spark, sf_dir, "events").select("event_type", F.date_trunc("hour", "ts").alias("hour"), "user_id"), ["event_type", "hour"], "user_id"


def edges_from_sequence(df: DataFrame, bucket: Column, order: list[str], key: str) -> DataFrame:
    """Keys of rows that follow each other by `order`, of which `bucket` must be a coarser form. Rows pair up inside buckets; the last of a bucket meets the first of the next one in a table of one row per bucket."""
    rows = df.select(bucket.alias("bucket"), F.struct(*order).alias("at"), F.col(key).alias("src"))
    inside = rows.withColumn("dst", F.lead("src").over(W.partitionBy("bucket").orderBy("at"))).select("src", "dst")
    ends = rows.groupBy("bucket").agg(F.max_by("src", "at").alias("src"), F.min_by("src", "at").alias("first"))
    across = ends.select("src", F.lead("first").over(W.orderBy("bucket")).alias("dst"))
    return canonical_edges(inside.union(across))


def nextactor(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users of consecutive events."""
    return edges_from_sequence(table(spark, sf_dir, "events"), F.date_trunc("hour", "ts"), ["ts", "event_id"], "user_id")


def edges_from_tokens(df: DataFrame, text: str) -> DataFrame:
    """Different words next to each other; ids are ranks of the words in byte order.

    The words are found and numbered first. Tasks then read the texts again with the list of all words, make pairs of numbers unique as far as they hold them, and shuffle them compressed.
    Beyond NAMED_WORDS words, which a task would not hold, pairs of words are shuffled and numbered by joins.
    """
    spark = df.sparkSession
    words = df.select(F.regexp_extract_all(F.lower(text), F.lit("[a-z]+"), F.lit(0)).alias("w")).where(F.size("w") > 1)

    def apart(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for found, a, b in _neighbours(batches):
            there = np.unique(np.concatenate([a, b]))
            yield pa.RecordBatch.from_arrays([found.take(pa.array(there)), pa.array(np.where(np.arange(len(there)) == 0, len(a), 0))], names=["word", "n"])

    met = written(words.mapInArrow(apart, "word string, n long"))
    ids = dense_ids(met, "word")
    size = ids.agg(F.count(F.lit(1)).alias("words")).crossJoin(met.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("pairs"))).first()
    if size.words > NAMED_WORDS:
        return _numbered_by_joins(words, ids)
    folder = Folder(fresh_uri(spark))

    def listed(group: pa.Table) -> pa.Table:
        part = group.column("part")[0].as_py()
        folder.save(f"words-{part}", word=group.sort_by("id").column("key").combine_chunks())
        return pa.table({"part": pa.array([part], pa.int64())})

    listed_parts = ids.withColumn("part", F.expr(f"id DIV {LISTED_WORDS}")).groupBy("part").applyInArrow(listed, "part long")
    files = sorted(r.part for r in listed_parts.collect())
    all_words, parts = max(size.words, 1), max(1, -(-size.pairs // PART_PAIRS))

    def paired(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, held, n = None, [], 0

        def sent() -> pa.RecordBatch:
            u, v = np.divmod(np.unique(np.concatenate(held)), all_words)
            # The pairs of a frequent word are dealt over PIECES parts, by ranges of the other word.
            of = (_mixed(u * PIECES + v * PIECES // all_words) % np.uint64(parts)).astype(np.int64)
            order = np.argsort(of, kind="stable")
            ends = np.searchsorted(of[order], np.arange(parts + 1))
            there = np.flatnonzero(np.diff(ends)).tolist()
            data = [_packed(u[order[ends[k] : ends[k + 1]]], v[order[ends[k] : ends[k + 1]]]) for k in there]
            return pa.RecordBatch.from_pydict({"part": pa.array(there, pa.int64()), "data": pa.array(data, pa.binary())})

        for found, a, b in _neighbours(batches):
            if known is None:
                known = pa.chunked_array([folder.read(f"words-{k}").column("word").combine_chunks() for k in files], pa.string())
            at = pc.index_in(known, value_set=found)
            place = np.flatnonzero(at.is_valid().to_numpy())
            number = np.zeros(len(found), dtype=np.int64)
            number[at.drop_null().to_numpy()] = place
            x, y = number[a], number[b]
            held.append(np.unique(np.minimum(x, y) * all_words + np.maximum(x, y)))
            n += len(held[-1])
            if n >= HELD_PAIRS:
                yield sent()
                held, n = [], 0
        if n:
            yield sent()

    def gathered(group: pa.Table) -> pa.Table:
        u, v = (np.concatenate(x) for x in zip(*[_unpacked(x.as_py(), 2) for x in group.column("data")], strict=True))
        u, v = np.divmod(np.unique(u * all_words + v), all_words)
        return pa.table({"u": u, "v": v})

    return words.mapInArrow(paired, "part long, data binary").groupBy("part").applyInArrow(gathered, "u long, v long")


def _neighbours(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.Array, np.ndarray, np.ndarray]]:
    """(words, a, b) for some HELD_TOKENS words of lists `w` at a time: the different words, and the places in them of those next to each other in a list that differ."""
    held, n = [], 0

    def cut() -> tuple[pa.Array, np.ndarray, np.ndarray]:
        found = pa.chunked_array([x.flatten() for x in held]).combine_chunks().dictionary_encode()
        code, size = found.indices.to_numpy(), np.concatenate([np.diff(x.offsets.to_numpy()) for x in held])
        inside = np.ones(len(code), dtype=bool)
        inside[np.cumsum(size)[size > 0] - 1] = False
        at = np.flatnonzero(inside[:-1] & (code[:-1] != code[1:])) if len(code) else np.zeros(0, dtype=np.int64)
        return found.dictionary, code[at], code[at + 1]

    for batch in batches:
        held.append(batch.column("w"))
        n += len(held[-1].flatten())
        if n >= HELD_TOKENS:
            yield cut()
            held, n = [], 0
    if held:
        yield cut()


def _numbered_by_joins(words: DataFrame, ids: DataFrame) -> DataFrame:
    pairs = words.select(F.explode(F.arrays_zip(F.slice("w", 1, F.size("w") - 1).alias("a"), F.slice("w", 2, F.size("w") - 1).alias("b"))).alias("p"))
    named = canonical_edges(pairs.select("p.a", "p.b"), "a", "b")
    numbered = named.join(ids.toDF("u", "iu"), "u").join(ids.toDF("v", "iv"), "v")
    return numbered.select(F.least("iu", "iv").alias("u"), F.greatest("iu", "iv").alias("v"))


def bigram(spark: SparkSession, sf_dir: str) -> DataFrame:
    return edges_from_tokens(table(spark, sf_dir, "documents"), "text")


def nation_trade(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nations of customers and of the suppliers of their order lines; trade within a nation is a loop and goes."""
    nation_of = lambda name, key, nation: table(spark, sf_dir, name).select(key, nation)
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey").join(table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    traded = lines.groupBy("o_custkey", "l_suppkey").agg(F.count(F.lit(1)).alias("n")).join(nation_of("customer", "c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    return canonical_edges(traded.join(nation_of("supplier", "s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey")), "c_nationkey", "s_nationkey")


def _runs(df: DataFrame, key: str, text: str, width: int) -> DataFrame:
    """(key, run): every run of `width` words of a text as one string, once for each key."""
    words = df.select(F.col(key).alias("key"), F.regexp_extract_all(F.lower(text), F.lit("[a-z]+"), F.lit(0)).alias("w")).where(F.size("w") >= width)
    starts = F.sequence(F.lit(1), F.size("w") - (width - 1))
    return words.select("key", F.explode(F.transform(starts, lambda k: F.array_join(F.slice("w", k, width), " "))).alias("run")).distinct()


def bench_leak(spark: SparkSession, sf_dir: str, width: int = 8) -> DataFrame:
    """Documents and benchmark items that share a run of words, a bipartite graph: ids 2k and 2k + 1. Only runs that an item has are kept of the documents."""
    items = _runs(table(spark, sf_dir, "benchmark"), "item_id", "text", width).toDF("item", "run")
    shared = _runs(table(spark, sf_dir, "documents"), "doc_id", "text", width).join(items, "run")
    return canonical_edges(shared.select((2 * F.col("key")).alias("src"), (2 * F.col("item") + 1).alias("dst")))


def pagelink(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages that share a link target below the root, without a further slash."""
    links = table(spark, sf_dir, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="(/[^"/]*)"'), F.lit(1))).alias("target"))
    return edges_from_projection(links, ["target"], "page_id")


def edges_from_vectors(df: DataFrame, k: int = 10, id_col: str = "vec_id", vector_col: str = "embedding", scale: int = 1 << 20, block: int = 4096) -> DataFrame:
    """Each vector and its k nearest others by inner product of floor(scale * x), ties to the smaller id. All pairs are scored, in blocks of
    `block` vectors against all; a task keeps k per vector, and each block's edges are written. Shorter vectors count as padded by zeros; vectors that are null or hold null or
    non-finite components take no part. Vectors are written as integers once."""
    x = F.transform(F.col(vector_col), lambda e: e.cast("double"))
    whole = df.select(F.col(id_col).cast("long").alias("id"), x.alias("x")).where("id is not null and x is not null")
    whole = whole.where(~F.exists("x", lambda e: e.isNull() | F.isnan(e) | (F.abs(e) == F.lit(float("inf")))))
    # An id is one vertex, so one vector: the largest where it has several.
    rows = checkpointed(whole.groupBy("id").agg(F.max("x").alias("x")).select("id", F.transform("x", lambda e: F.floor(e * scale).cast("double")).alias("x")))
    size = rows.agg(F.max(F.size("x")).alias("width"), F.max(F.array_max(F.transform("x", F.abs))).alias("largest")).first()
    width = size.width or 0
    if width * (size.largest or 0) ** 2 >= 1 << 53:
        raise ValueError("products of these vectors are too large for exact sums: take a smaller scale")
    last, near = None, None
    while ask := (rows if last is None else rows.where(F.col("id") > last)).orderBy("id").limit(block).collect():
        last = ask[-1].id
        queries = np.zeros((len(ask), width))
        for row, r in zip(queries, ask, strict=True):
            row[: len(r.x)] = r.x
        shared = df.sparkSession.sparkContext.broadcast((np.array([r.id for r in ask]), queries))

        def best(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            ids, queries = shared.value
            for batch in batches:
                for a in range(0, batch.num_rows, VECTOR_TILE):
                    part = batch.slice(a, VECTOR_TILE)
                    own, lists = part.column("id").to_numpy(), part.column("x")
                    sizes = np.diff(lists.offsets.to_numpy())
                    x = np.zeros((len(own), queries.shape[1]))
                    x[np.arange(queries.shape[1])[None, :] < sizes[:, None]] = lists.flatten().to_numpy()
                    score = queries @ x.T
                    score[ids[:, None] == own[None, :]] = -np.inf
                    least = np.partition(score, -k, axis=1)[:, -k][:, None] if len(own) > k else -np.inf
                    q, c = np.nonzero((score >= least) & np.isfinite(score))  # ties at the k-th score all stay for now
                    yield pa.RecordBatch.from_arrays([pa.array(ids[q]), pa.array(own[c]), pa.array(score[q, c])], names=["src", "dst", "s"])

        part = checkpointed(rows.mapInArrow(best, "src long, dst long, s double").withColumn("r", F.row_number().over(W.partitionBy("src").orderBy(F.desc("s"), "dst"))).where(F.col("r") <= k).select("src", "dst"))
        near = part if near is None else near.unionByName(part)
    if near is None:
        return rows.select(F.col("id").alias("u"), F.col("id").alias("v")).limit(0)
    return canonical_edges(near)


def knn(spark: SparkSession, sf_dir: str) -> DataFrame:
    return edges_from_vectors(table(spark, sf_dir, "embeddings"))


GRAPHS = {f.__name__: f for f in (copurchase, cosupply_order, cosupply_part, tripartite, order_part, coactive, nextactor, knn, bigram, pagelink, nation_trade, bench_leak)}


def load_graph(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return GRAPHS[name](spark, sf_dir)


_PAIR = T.StructType([T.StructField("src", T.LongType()), T.StructField("dst", T.LongType())])


def edges_from_file(spark: SparkSession, path: str, fmt: str = "csv", sep: str = "\t", comment: str = "#", mode: str = "repair") -> DataFrame:
    """Edges of a parquet, orc, json or text edge list with the columns src and dst; lines of a text list that start with `comment` are skipped."""
    if fmt == "csv":
        pairs = spark.read.schema(_PAIR).csv(path, sep=sep, comment=comment)
    else:
        pairs = spark.read.format(fmt).schema(_PAIR).load(path)
    return canonical_edges(pairs, mode=mode)


def edges_from_table(spark: SparkSession, name: str, src: str = "src", dst: str = "dst", mode: str = "repair") -> DataFrame:
    """Edges of two columns of a table or view of the catalog."""
    return canonical_edges(spark.table(name), src, dst, mode)


def edges_from_jdbc(spark: SparkSession, url: str, name: str, key: str, bounds: tuple[int, int], parts: int, src: str = "src", dst: str = "dst", mode: str = "repair") -> DataFrame:
    """Edges of a database table, read by `parts` tasks over ranges of a numeric column."""
    reader = spark.read.format("jdbc").option("url", url).option("dbtable", name).option("partitionColumn", key)
    return canonical_edges(reader.option("lowerBound", bounds[0]).option("upperBound", bounds[1]).option("numPartitions", parts).load(), src, dst, mode)


def write_edge_list(edges: DataFrame, path: str, fmt: str = "csv", sep: str = "\t") -> None:
    """One line or row per undirected edge, in files that edges_from_file reads."""
    rows = edges.select(F.col("u").alias("src"), F.col("v").alias("dst")).write.mode("overwrite")
    rows.csv(path, sep=sep) if fmt == "csv" else rows.format(fmt).save(path)


def write_bucketed(array: DataFrame, name: str, buckets: int) -> None:
    """A table of rows bucketed and sorted by src, which later joins on src need not shuffle."""
    array.write.bucketBy(buckets, "src").sortBy("src", "dst").mode("overwrite").saveAsTable(name)
