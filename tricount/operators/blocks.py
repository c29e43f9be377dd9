"""Triangles by blocks of out-lists that lie once in the shared folder: nothing that grows with the two-paths is shuffled, and a task holds two blocks.

Vertices fall into blocks by a hash of the id. A block's file has the out-lists of its vertices, ids replaced by dense numbers that run through the blocks; a task takes one block
as sources and reads all blocks as targets, one after another. Files are read by the Python workers, so spark.checkpoint.dir must be a path or URI that pyarrow opens.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.feather as feather
from pyarrow import fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tricount.functions.lineage import ensure_folder, once
from tricount.operators import prep

#: Edges of a block on average; a task holds some 100 bytes for each while it prepares a block, and two blocks while it counts.
BLOCK_EDGES = 1_000_000
#: Words of 64 ids looked up at once, edges cut and sorted at once, and vertices whose ids a task remembers.
LOOKED_AT, CUT_EDGES, NAMES = 1 << 19, 1 << 19, 1 << 22
#: Words of the table that holds the lists of some sources at a time, or those of one source if these are more.
TABLE_WORDS = 1 << 22


def _mixed(v: np.ndarray) -> np.ndarray:
    x = v.astype(np.int64).view(np.uint64)
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


def _packed(*columns: np.ndarray) -> bytes:
    """Columns of 64-bit integers as compressed bytes: differences, low bytes first together, then the higher ones."""
    planes = b"".join(np.ascontiguousarray(np.diff(x, prepend=np.int64(0)).astype("<i8").view(np.uint8).reshape(-1, 8).T).tobytes() for x in columns)
    return len(columns[0]).to_bytes(8, "little") + pa.Codec("zstd").compress(planes, asbytes=True)


def _unpacked(data: bytes, columns: int) -> list[np.ndarray]:
    n = int.from_bytes(data[:8], "little")
    planes = np.frombuffer(pa.Codec("zstd").decompress(data[8:], 8 * n * columns, asbytes=True), dtype=np.uint8).reshape(columns, 8, n)
    return [np.cumsum(np.ascontiguousarray(p.T).view("<i8").ravel()) for p in planes]


class Folder:
    """Files of arrays, one for each kind and block. A file is written under another name first, so a repeated task leaves a whole one."""

    def __init__(self, uri: str) -> None:
        self.uri = uri

    def _at(self) -> tuple[pafs.FileSystem, str]:
        return pafs.FileSystem.from_uri(self.uri) if ":" in self.uri.split("/")[0] else (pafs.LocalFileSystem(), self.uri)

    def save(self, name: str, **columns: np.ndarray | pa.Array) -> None:
        fs, root = self._at()
        fs.create_dir(root, recursive=True)
        part = f"{root}/{name}-{uuid.uuid4().hex}"
        with fs.open_output_stream(part) as out:
            feather.write_feather(pa.table(columns), out, compression="zstd")
        fs.move(part, f"{root}/{name}")

    def read(self, name: str) -> pa.Table:
        fs, root = self._at()
        with fs.open_input_file(f"{root}/{name}") as source:
            return feather.read_table(source)

    def load(self, name: str) -> list[np.ndarray]:
        return [c.combine_chunks().to_numpy(zero_copy_only=False) if c.num_chunks != 1 else c.chunk(0).to_numpy(zero_copy_only=False) for c in self.read(name).columns]

    def drop(self, name: str) -> None:
        fs, root = self._at()
        fs.delete_file(f"{root}/{name}")


def fresh_uri(spark: SparkSession) -> str:
    """A new folder of the shared one."""
    ensure_folder(spark)
    return f"{spark.conf.get('spark.checkpoint.dir', None) or spark.sparkContext.getCheckpointDir()}/blocks-{uuid.uuid4().hex}"


class Lists:
    """Out-lists in files, as list_blocks() leaves them. `base` is the number of each block's first vertex, with the number of all vertices at the end."""

    def __init__(self, folder: Folder, base: np.ndarray) -> None:
        self.folder, self.base, self.blocks = folder, base, len(base) - 1
        self.words = int(base[-1]) // 64 + 1
        self.known: dict[int, np.ndarray] = {}
        self.edges = 0

    def read(self, block: int) -> tuple[np.ndarray, np.ndarray]:
        """(place of the source in its block, number of the target) of a block's oriented edges, sorted."""
        src, no = self.folder.load(f"out-{block}")
        return src.astype(np.int64), no

    def as_words(self, src: np.ndarray, no: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Keys (source, word) and the bits of each word of 64 numbers."""
        key = src * self.words + (no >> 6)
        first = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, dtype=np.int64)
        bit = np.left_shift(np.uint64(1), (no & 63).astype(np.uint64))
        return key[first], np.bitwise_or.reduceat(bit, first) if len(first) else np.zeros(0, dtype=np.uint64)

    def ids(self, block: int) -> np.ndarray:
        if block not in self.known:
            if sum(map(len, self.known.values())) > NAMES:
                self.known.clear()
            self.known[block] = self.folder.load(f"ids-{block}")[0]
        return self.known[block]

    def named(self, no: np.ndarray) -> np.ndarray:
        """The ids of vertex numbers."""
        out = np.empty(len(no), dtype=np.int64)
        of = np.searchsorted(self.base, no, side="right") - 1
        order = np.argsort(of, kind="stable")
        cut = np.searchsorted(of[order], np.arange(self.blocks + 1))
        for block in np.flatnonzero(np.diff(cut)).tolist():
            at = order[cut[block] : cut[block + 1]]
            out[at] = self.ids(block)[no[at] - self.base[block]]
        return out

    def met(self, block: int) -> Iterator[tuple]:
        """(target block, this block's src and no, edges, hit words and bits): for edges of `block`, the words in which the out-lists of both ends share numbers."""
        src, no = self.read(block)
        key, bits = self.as_words(src, no)
        sources = max(1, TABLE_WORDS // self.words)
        cut = np.arange(0, int(self.base[block + 1] - self.base[block]) + sources, sources)
        key_cut = np.searchsorted(key, cut * self.words)
        table = np.zeros(sources * self.words if len(key) else 0, dtype=np.uint64)
        for other in range(self.blocks if len(key) else 0):
            edges = np.flatnonzero((no >= self.base[other]) & (no < self.base[other + 1]))
            if not len(edges):
                continue
            (words, their_bits), (begin,) = self.folder.load(f"words-{other}"), self.folder.load(f"begin-{other}")
            d = no[edges] - self.base[other]
            size = begin[d + 1] - begin[d]
            edges, d, size = edges[size > 0], d[size > 0], size[size > 0]
            upto = np.concatenate([[0], np.cumsum(size)])
            row, shift = src[edges] * self.words, begin[d] - upto[:-1]
            stops = np.searchsorted(src[edges], cut)
            for c in np.flatnonzero(np.diff(stops)).tolist():
                spots, below = key[key_cut[c] : key_cut[c + 1]] - cut[c] * self.words, cut[c] * self.words
                table[spots] = bits[key_cut[c] : key_cut[c + 1]]
                first = int(stops[c])
                while first < stops[c + 1]:
                    last = min(int(stops[c + 1]), max(first + 1, int(np.searchsorted(upto, upto[first] + LOOKED_AT, side="right")) - 1))
                    at = np.repeat(shift[first:last], size[first:last]) + np.arange(upto[first], upto[last])
                    shared = table[np.repeat(row[first:last] - below, size[first:last]) + words[at]] & their_bits[at]
                    hit = np.flatnonzero(shared)
                    each = np.searchsorted(upto, hit + upto[first], side="right") - 1
                    yield other, (src, no), edges[each], words[at[hit]], shared[hit]
                    first = last
                table[spots] = 0

    def found(self, block: int) -> Iterator[tuple]:
        """The same with a row for each triangle: (target block, this block's src and no, edges, numbers of the third vertices)."""
        for other, own, edges, word, shared in self.met(block):
            for a in range(0, len(edges), LOOKED_AT // 4):
                some = np.ascontiguousarray(shared[a : a + LOOKED_AT // 4].astype("<u8"))
                row, bit = np.nonzero(np.unpackbits(some.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little"))
                yield other, own, edges[a:][row], word[a:][row] * 64 + bit

    def each(self, spark, run: Callable[[int], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
        """The rows that `run` gives for each block, a task for each."""

        def tasks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for block in batch.column("id").to_pylist():
                    yield from run(block)

        return spark.range(0, self.blocks, 1, max(1, self.blocks)).mapInArrow(tasks, schema)


def list_blocks(edges: DataFrame, per_block: int | None = None) -> Lists:
    """Writes edges (u, v) as out-lists of blocks, oriented by (degree, id): both directions of an edge are shuffled once, compressed, to the blocks of their sources, which so know the degrees."""
    spark = edges.sparkSession
    ensure_folder(spark)
    there = once(edges)
    kept = there.select(F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v"))
    blocks = max(1, -(-there.count() // (BLOCK_EDGES if per_block is None else per_block)))
    folder = Folder(fresh_uri(spark))

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def rows(held: list) -> pa.RecordBatch:
            u, v = (np.concatenate(x) for x in zip(*held, strict=True))
            src, dst = np.concatenate([u, v]), np.concatenate([v, u])
            of = (_mixed(src) % np.uint64(blocks)).astype(np.int64)
            order = np.lexsort((dst, src, of))
            src, dst, ends = src[order], dst[order], np.searchsorted(of[order], np.arange(blocks + 1))
            there = np.flatnonzero(np.diff(ends)).tolist()
            return pa.RecordBatch.from_pydict({"block": pa.array(there, pa.int64()), "data": pa.array([_packed(src[ends[b] : ends[b + 1]], dst[ends[b] : ends[b + 1]]) for b in there], pa.binary())})

        held, n = [], 0
        for batch in batches:
            held.append((batch.column("u").to_numpy(), batch.column("v").to_numpy()))
            n += batch.num_rows
            if n >= CUT_EDGES:
                yield rows(held)
                held, n = [], 0
        if n:
            yield rows(held)

    def gathered(group: pa.Table) -> pa.Table:
        block = group.column("block")[0].as_py()
        src, dst = (np.concatenate(x) for x in zip(*[_unpacked(x.as_py(), 2) for x in group.column("data")], strict=True))
        order = np.lexsort((dst, src))
        src, dst = src[order], dst[order]
        ids, degree = np.unique(src, return_counts=True)
        folder.save(f"ids-{block}", ids=ids, degree=degree)
        folder.save(f"near-{block}", dst=dst)
        return pa.table({"block": [block], "n": [len(ids)]})

    sizes = {r.block: r.n for r in kept.mapInArrow(cut, "block long, data binary").groupBy("block").applyInArrow(gathered, "block long, n long").collect()}
    base = np.concatenate([[0], np.cumsum([sizes.get(b, 0) for b in range(blocks)])]).astype(np.int64)
    lists = Lists(folder, base)

    def oriented(block: int) -> Iterator[pa.RecordBatch]:
        src, no = [np.zeros(0, dtype=np.int64)], [np.zeros(0, dtype=np.int64)]
        if block in sizes:
            (ids, degree), (dst,) = folder.load(f"ids-{block}"), folder.load(f"near-{block}")
            place = np.repeat(np.arange(len(ids)), degree)
            of = (_mixed(dst) % np.uint64(blocks)).astype(np.int64)
            for other in sizes:
                at = np.flatnonzero(of == other)
                theirs, their_degree = folder.load(f"ids-{other}")
                spot = np.searchsorted(theirs, dst[at])
                own = degree[place[at]]
                up = (own < their_degree[spot]) | ((own == their_degree[spot]) & (ids[place[at]] < dst[at]))
                src.append(place[at][up])
                no.append(spot[up] + base[other])
        else:
            folder.save(f"ids-{block}", ids=src[0], degree=src[0])
        src, no = np.concatenate(src), np.concatenate(no)
        order = np.lexsort((no, src))
        src, no = src[order], no[order]
        folder.save(f"out-{block}", src=src.astype(np.int32), no=no)
        key, bits = lists.as_words(src, no)
        folder.save(f"words-{block}", word=key % lists.words, bits=bits)
        folder.save(f"begin-{block}", begin=np.searchsorted(key // lists.words, np.arange(lists.base[block + 1] - lists.base[block] + 1)))
        yield pa.RecordBatch.from_pydict({"edges": pa.array([len(src)], pa.int64())})

    lists.edges = lists.each(spark, oriented, "edges long").agg(F.sum("edges")).first()[0]
    for block in sizes:
        folder.drop(f"near-{block}")
    return lists


def count_blocks(edges: DataFrame, per_block: int | None = None) -> DataFrame:
    """One row, `triangles`."""
    lists = list_blocks(edges, per_block)

    def run(block: int) -> Iterator[pa.RecordBatch]:
        n = sum(int(np.bitwise_count(shared).sum()) for *_, shared in lists.met(block))
        yield pa.RecordBatch.from_pydict({"n": pa.array([n], pa.int64())})

    return lists.each(edges.sparkSession, run, "n long").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("triangles"))


def block_triangles(edges: DataFrame, per_block: int | None = None) -> DataFrame:
    """(a, b, c) of every triangle, in the order of rank (degree, id)."""
    lists = list_blocks(edges, per_block)

    def run(block: int) -> Iterator[pa.RecordBatch]:
        for other, (src, no), edge, third in lists.found(block):
            # An edge's target and the third vertex come in the order of rank, as the target's own out-list has the third.
            columns = [lists.ids(block)[src[edge]], lists.ids(other)[no[edge] - lists.base[other]], lists.named(third)]
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in columns], names=["a", "b", "c"])

    return lists.each(edges.sparkSession, run, "a long, b long, c long")


def _summed(lists: Lists, spark, run: Callable[[int], Iterator[tuple[int, np.ndarray, np.ndarray]]], finish: Callable[[int, np.ndarray, np.ndarray], pa.Table], schema: str) -> DataFrame:
    """Sparse counts (block, places, numbers) that `run` gives for each block, shuffled compressed to the block they are about; finish(block, places, numbers) makes its rows."""

    def sent(block: int) -> Iterator[pa.RecordBatch]:
        none = np.zeros(0, dtype=np.int64)
        for to, place, n in [(block, none, none)]:  # each block gives its rows, counted or not
            yield pa.RecordBatch.from_pydict({"block": pa.array([to], pa.int64()), "data": pa.array([_packed(place, n)], pa.binary())})
        for to, place, n in run(block):
            yield pa.RecordBatch.from_pydict({"block": pa.array([to], pa.int64()), "data": pa.array([_packed(place, n)], pa.binary())})

    def got(group: pa.Table) -> pa.Table:
        place, n = (np.concatenate(x) for x in zip(*[_unpacked(x.as_py(), 2) for x in group.column("data")], strict=True))
        return finish(group.column("block")[0].as_py(), place, n)

    return lists.each(spark, sent, "block long, data binary").groupBy("block").applyInArrow(got, schema)


def _added(size: int, place: np.ndarray, n: np.ndarray) -> np.ndarray:
    out = np.zeros(size, dtype=np.int64)
    np.add.at(out, place, n)
    return out


def vertex_counts(edges: DataFrame, per_block: int | None = None) -> DataFrame:
    """(v, d, t): degree and triangles of every vertex that has an edge."""
    lists = list_blocks(edges, per_block)

    def run(block: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        held, n = [], 0

        def flushed() -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
            no, times = (np.concatenate(x) for x in zip(*held, strict=True))
            no, at = np.unique(no, return_inverse=True)
            total = _added(len(no), at, times)
            cut = np.searchsorted(no, lists.base)
            for k in np.flatnonzero(np.diff(cut)).tolist():
                yield k, no[cut[k] : cut[k + 1]] - lists.base[k], total[cut[k] : cut[k + 1]]

        for _, (src, no), edge, third in lists.found(block):
            for x in (src[edge] + lists.base[block], no[edge], third):
                held.append(np.unique(x, return_counts=True))
                n += len(held[-1][0])
            if n > NAMES:
                yield from flushed()
                held, n = [], 0
        if held:
            yield from flushed()

    def finish(block: int, place: np.ndarray, n: np.ndarray) -> pa.Table:
        ids, degree = lists.folder.load(f"ids-{block}")
        return pa.table({"v": ids, "d": degree, "t": _added(len(ids), place, n)})

    return _summed(lists, edges.sparkSession, run, finish, "v long, d long, t long")


def edge_counts(edges: DataFrame, per_block: int | None = None) -> DataFrame:
    """(u, v, support) of every edge: the triangles it is in."""
    lists = list_blocks(edges, per_block)
    top = int(lists.base[-1]) + 1

    def run(block: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        mine, key, at, theirs_key, theirs_count = None, None, None, None, None

        def sparse(to: int, counts: np.ndarray) -> tuple[int, np.ndarray, np.ndarray]:
            place = np.flatnonzero(counts)
            return to, place, counts[place]

        for other, (src, no), edge, third in lists.found(block):
            if mine is None:
                mine, key = np.zeros(len(src), dtype=np.int64), src * top + no
            if at != other:
                if at is not None:
                    yield sparse(at, theirs_count)
                theirs = lists.read(other)
                at, theirs_key, theirs_count = other, theirs[0] * top + theirs[1], np.zeros(len(theirs[0]), dtype=np.int64)
            mine += np.bincount(edge, minlength=len(mine))
            mine += np.bincount(np.searchsorted(key, src[edge] * top + third), minlength=len(mine))
            theirs_count += np.bincount(np.searchsorted(theirs_key, (no[edge] - lists.base[other]) * top + third), minlength=len(theirs_count))
        if at is not None:
            yield sparse(at, theirs_count)
            yield sparse(block, mine)

    def finish(block: int, place: np.ndarray, n: np.ndarray) -> pa.Table:
        src, no = lists.read(block)
        a, b = lists.ids(block)[src], lists.named(no)
        return pa.table({"u": np.minimum(a, b), "v": np.maximum(a, b), "support": _added(len(src), place, n)})

    return _summed(lists, edges.sparkSession, run, finish, "u long, v long, support long")


def slice_counts(edges: DataFrame, devices: int, split: str = "hash", per_block: int | None = None) -> DataFrame:
    """(slice, edges, triangles): oriented edges dealt over devices by a hash of their ends, by stride of the place in the array sorted by (src, dst), or by ranges of it.

    Places come from a running sum over the vertices in the order of ids, which each block reads back for its own; no edge is sorted beyond its block.
    """
    spark = edges.sparkSession
    lists = list_blocks(edges, per_block)

    def sizes(block: int) -> Iterator[pa.RecordBatch]:
        ids, n = lists.ids(block), np.bincount(lists.read(block)[0], minlength=len(lists.ids(block)))
        yield pa.RecordBatch.from_pydict({"block": pa.array(np.full(len(ids), block)), "v": pa.array(ids), "n": pa.array(n)})

    def kept(group: pa.Table) -> pa.Table:
        block = group.column("block")[0].as_py()
        lists.folder.save(f"before-{block}", before=group.column("before").to_numpy()[np.argsort(group.column("v").to_numpy())])
        return pa.table({"n": pa.array([group.num_rows], pa.int64())})

    runs = prep.prefix_sum(lists.each(spark, sizes, "block long, v long, n long"), "v", "n")
    runs.select("block", "v", "before").groupBy("block").applyInArrow(kept, "n long").agg(F.sum("n")).collect()
    total = lists.edges

    def sliced(block: int, src: np.ndarray, no: np.ndarray) -> np.ndarray:
        ends = lists.named(no)
        if split not in ("strided", "range"):
            return (_mixed(_mixed(lists.ids(block)[src]).view(np.int64) + ends) % np.uint64(devices)).astype(np.int64)
        order = np.lexsort((ends, src))
        place = np.empty(len(src), dtype=np.int64)
        place[order] = np.arange(len(src)) - np.searchsorted(src, src)
        place += lists.folder.load(f"before-{block}")[0][src]
        return place % devices if split == "strided" else np.minimum(place // max(total // devices, 1), devices - 1)

    def run(block: int) -> Iterator[pa.RecordBatch]:
        src, no = lists.read(block)
        if len(src):
            of, found = sliced(block, src, no), np.zeros(devices, dtype=np.int64)
            for _, _, edge, _, shared in lists.met(block):
                found += np.bincount(of[edge], weights=np.bitwise_count(shared), minlength=devices).astype(np.int64)
            n = np.bincount(of, minlength=devices)
            there = np.flatnonzero(n)
            yield pa.RecordBatch.from_pydict({"slice": pa.array(there, pa.int32()), "edges": pa.array(n[there]), "triangles": pa.array(found[there])})

    return lists.each(spark, run, "slice int, edges long, triangles long").groupBy("slice").agg(F.sum("edges").alias("edges"), F.sum("triangles").alias("triangles"))


def typed_counts(edges: DataFrame, types: DataFrame, per_block: int | None = None) -> DataFrame:
    """(ta, tb, tc, n) from a map (v, type): triangles by the sorted types of their corners; those with a corner that the map lacks are left out.

    Types become numbers in their order, one for each vertex in the files of the blocks, and each task adds up its triangles; none is moved. A task holds the numbers of all vertices.
    """
    spark = edges.sparkSession
    lists = list_blocks(edges, per_block)
    blocks = lists.blocks
    names = types.select("type").distinct().orderBy("type").toArrow().column("type").combine_chunks()
    code = next(k for k in (np.int8, np.int32) if len(names) <= np.iinfo(k).max)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            batch = batch.filter(pc.is_valid(batch.column("v")))
            v, kind = batch.column("v").to_numpy(), pc.index_in(batch.column("type"), value_set=names.cast(batch.column("type").type)).to_numpy(zero_copy_only=False)
            of = (_mixed(v) % np.uint64(blocks)).astype(np.int64)
            order = np.argsort(of, kind="stable")
            ends = np.searchsorted(of[order], np.arange(blocks + 1))
            there = np.flatnonzero(np.diff(ends)).tolist()
            data = [_packed(v[order[ends[b] : ends[b + 1]]], kind[order[ends[b] : ends[b + 1]]].astype(np.int64)) for b in there]
            yield pa.RecordBatch.from_pydict({"block": pa.array(there, pa.int64()), "data": pa.array(data, pa.binary())})

    def kept(group: pa.Table) -> pa.Table:
        block = group.column("block")[0].as_py()
        v, kind = (np.concatenate(x) for x in zip(*[_unpacked(x.as_py(), 2) for x in group.column("data")], strict=True))
        ids = lists.folder.load(f"ids-{block}")[0]
        spot = np.minimum(np.searchsorted(ids, v), max(len(ids) - 1, 0))
        here = ids[spot] == v if len(ids) else np.zeros(len(v), dtype=bool)
        if len(np.unique(v[here])) < int(here.sum()):
            raise ValueError("a vertex has several types")
        of = np.full(len(ids), -1, dtype=code)
        of[spot[here]] = kind[here]
        lists.folder.save(f"type-{block}", type=of)
        return pa.table({"n": pa.array([len(ids)], pa.int64())})

    def nothing(block: int) -> Iterator[pa.RecordBatch]:
        none = np.zeros(0, dtype=np.int64)
        yield pa.RecordBatch.from_pydict({"block": pa.array([block], pa.int64()), "data": pa.array([_packed(none, none)], pa.binary())})

    dealt = types.select(F.col("v").cast("long").alias("v"), "type").mapInArrow(cut, "block long, data binary")
    dealt.unionByName(lists.each(spark, nothing, "block long, data binary")).groupBy("block").applyInArrow(kept, "n long").agg(F.sum("n")).collect()

    def run(block: int) -> Iterator[pa.RecordBatch]:
        of = np.concatenate([lists.folder.load(f"type-{b}")[0] for b in range(blocks)])
        total: dict[int, int] = {}
        for _, (src, no), edge, third in lists.found(block):
            three = np.stack([of[src[edge] + lists.base[block]], of[no[edge]], of[third]]).astype(np.int64)
            three = np.sort(three[:, (three >= 0).all(axis=0)], axis=0)
            for key, n in zip(*np.unique((three[0] * len(names) + three[1]) * len(names) + three[2], return_counts=True), strict=True):
                total[int(key)] = total.get(int(key), 0) + int(n)
        key = np.array(list(total), dtype=np.int64)
        columns = [names.take(pa.array(x)) for x in (key // len(names) ** 2, key // len(names) % len(names), key % len(names))] if total else []
        if total:
            yield pa.RecordBatch.from_arrays([*columns, pa.array(list(total.values()), pa.int64())], names=["ta", "tb", "tc", "n"])

    kind = types.schema["type"].dataType.simpleString()
    return lists.each(spark, run, f"ta {kind}, tb {kind}, tc {kind}, n long").groupBy("ta", "tb", "tc").agg(F.sum("n").alias("n"))
