"""Near copies: an exact Jaccard join of word shingles by grouped prefixes."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.broadcast import Broadcast
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tricount.llm import textkit
from tricount.llm.common import Stages, unused
from tricount.llm.graph import components

#: Words of a shingle, and the least similarity of linked documents in hundredths.
WIDTH, PERCENT = 5, 80
#: Cells of the table of shingle counts (4 bytes each, broadcast): its size is fixed whatever the corpus holds.
CELLS = 1 << 20
#: Counts travel in so many pieces.
PIECES = 64
#: Bits of a filter that a scan applies before a join (a megabyte, broadcast).
MARKS = 1 << 23
#: Group parts of a bucket that meet in one task; a larger bucket is cut into chunks of this size.
TILE = 128
#: Nodes of a group part, and shingles of all of them together (a part holds one node at least).
PART, PART_SHINGLES = 16, 1 << 17


def _cell(h: np.ndarray) -> np.ndarray:
    return (h & np.uint64(CELLS - 1)).astype(np.int64)


def _count_pieces(docs: DataFrame, width: int) -> DataFrame:
    """How often shingles fall into each cell, over all documents, by piece of the table."""

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(CELLS, dtype=np.int64)
        for batch in batches:
            for _, _, data, offsets in textkit.texts(batch.column("text")):
                total += np.bincount(_cell(textkit.Words(data, offsets).shingles(width)[0]), minlength=CELLS)
        parts = np.minimum(total, 2**31 - 1).astype("<i4").reshape(PIECES, -1)
        yield pa.RecordBatch.from_arrays([pa.array(range(PIECES), pa.int32()), pa.array([x.tobytes() for x in parts], pa.binary())], names=["piece", "counts"])

    def summed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for piece, counts in zip(batch.column("piece").to_pylist(), batch.column("counts"), strict=True):
                sums[piece] = sums.get(piece, 0) + np.frombuffer(counts.as_buffer(), dtype="<i4").astype(np.int64)
        parts = [np.minimum(x, 2**31 - 1).astype("<i4").tobytes() for x in sums.values()]
        yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int32()), pa.array(parts, pa.binary())], names=["piece", "counts"])

    schema = "piece int, counts binary"
    return docs.select("text").mapInArrow(counted, schema).repartition(PIECES, "piece").mapInArrow(summed, schema)


def shingle_counts(docs: DataFrame, width: int = WIDTH) -> np.ndarray:
    """The table of counts: CELLS numbers, the sum over all documents."""
    rows = _count_pieces(docs, width).collect()
    table = np.zeros((PIECES, CELLS // PIECES), dtype=np.int32)
    for r in rows:
        table[r.piece] = np.frombuffer(r.counts, dtype="<i4")
    return table.reshape(-1)


def _mark(x: np.ndarray) -> np.ndarray:
    return (textkit.mix(x.astype(np.int64).view(np.uint64)) & np.uint64(MARKS - 1)).astype(np.int64)


def _marks(keys: DataFrame) -> Broadcast:
    """A filter of fixed size for one column of integers: whoever is not marked is not among them. It keeps most rows of a scan out of the join that follows."""

    def marked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits = np.zeros(MARKS, dtype=bool)
        for batch in batches:
            bits[_mark(batch.column(0).to_numpy())] = True
        parts = np.packbits(bits).reshape(PIECES, -1)
        yield pa.RecordBatch.from_arrays([pa.array(range(PIECES), pa.int32()), pa.array([x.tobytes() for x in parts], pa.binary())], names=["piece", "bits"])

    def joined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        either: dict[int, np.ndarray] = {}
        for batch in batches:
            for piece, bits in zip(batch.column("piece").to_pylist(), batch.column("bits"), strict=True):
                either[piece] = either.get(piece, 0) | np.frombuffer(bits.as_buffer(), dtype=np.uint8)
        yield pa.RecordBatch.from_arrays([pa.array(list(either), pa.int32()), pa.array([x.tobytes() for x in either.values()], pa.binary())], names=["piece", "bits"])

    schema = "piece int, bits binary"
    packed = np.zeros((PIECES, MARKS // 8 // PIECES), dtype=np.uint8)
    for r in keys.mapInArrow(marked, schema).repartition(PIECES, "piece").mapInArrow(joined, schema).collect():
        packed[r.piece] = np.frombuffer(r.bits, dtype=np.uint8)
    return keys.sparkSession.sparkContext.broadcast(packed.reshape(-1))


def _is_marked(marks: np.ndarray, x: np.ndarray) -> np.ndarray:
    at = _mark(x)
    return (marks[at >> 3] >> (7 - (at & 7)).astype(np.uint8) & 1).astype(bool)


def _marked_only(df: DataFrame, column: str, keys: DataFrame) -> DataFrame:
    """The rows, or elements of the list, that the filter of `keys` lets pass; a join on the column gives the same with these as with all."""
    marks = _marks(keys)

    def kept(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = batch.column(column)
            if pa.types.is_list(x.type):
                ok = _is_marked(marks.value, x.flatten().to_numpy())
                upto = np.concatenate([[0], np.cumsum(ok)])[x.offsets.to_numpy() - x.offsets[0].as_py()]
                left = pa.ListArray.from_arrays(pa.array(upto.astype(np.int32)), x.flatten().filter(pa.array(ok)))
                yield pa.RecordBatch.from_arrays([left if n == column else batch.column(n) for n in batch.schema.names], names=batch.schema.names)
            else:
                yield batch.filter(pa.array(_is_marked(marks.value, x.to_numpy())))

    return df.mapInArrow(kept, df.schema)


class Sets:
    """The shingle sets of a chunk of texts in one order shared by all documents: rarer cells first, then by hash."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, width: int, counts: np.ndarray | None) -> None:
        h, row = textkit.Words(data, offsets).shingles(width)
        order = np.lexsort((h, row) if counts is None else (h, counts[_cell(h)], row))
        h, row = h[order], row[order]
        new = np.ones(len(h), dtype=bool)
        new[1:] = (h[1:] != h[:-1]) | (row[1:] != row[:-1])
        self.h, self.row = h[new], row[new]
        self.n = np.bincount(self.row, minlength=len(offsets) - 1)
        self.first = np.concatenate([[0], np.cumsum(self.n)])

    def digest(self, salt: int, upto: np.ndarray | None = None) -> np.ndarray:
        """A 64-bit sum over each row's set, or over the part of it before `upto`."""
        x = textkit.mix(self.h ^ np.uint64(salt))
        if upto is not None:
            x = np.where(self.place() < upto[self.row], x, np.uint64(0))
        total = np.concatenate([np.zeros(1, dtype=np.uint64), np.cumsum(x)])
        return (total[self.first[1:]] - total[self.first[:-1]]).view(np.int64)

    def place(self) -> np.ndarray:
        return np.arange(len(self.h)) - self.first[self.row]


def _list(values: np.ndarray, sizes: np.ndarray) -> pa.Array:
    offsets = np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(values.view(np.int64)))


def _signed(docs: DataFrame, counts: Broadcast, width: int, percent: int) -> DataFrame:
    """Per document: set size, digests of the set and of its prefix, the prefix, and a parity bitmap of the set."""

    def signed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, data, offsets in textkit.texts(batch.column("text")):
                s = Sets(data, offsets, width, counts.value)
                upto = np.where(s.n > 0, s.n - -(-percent * s.n // 100) + 1, 0)
                bits = np.maximum(64, 1 << np.ceil(np.log2(np.maximum(2 * s.n, 1))).astype(np.int64))
                base = np.concatenate([[0], np.cumsum(bits)])
                cells = base[s.row] + (textkit.mix(s.h) >> np.uint64(7) & (bits[s.row] - 1).astype(np.uint64)).astype(np.int64)
                maps = np.packbits(np.bincount(cells, minlength=base[-1]).astype(np.uint8) & 1, bitorder="little")
                edges = pa.py_buffer((base // 8).astype(np.int32))
                yield pa.RecordBatch.from_arrays(
                    [
                        batch.column("doc_id").slice(a, b - a), pa.array(s.n.astype(np.int64)), pa.array(s.digest(11)), pa.array(s.digest(23)), pa.array(s.digest(37, upto)), pa.array(s.digest(53, upto)),
                        _list(s.h[s.place() < upto[s.row]], upto), pa.Array.from_buffers(pa.binary(), b - a, [None, edges, pa.py_buffer(maps)]),
                    ],
                    names=["doc_id", "n", "d1", "d2", "p1", "p2", "prefix", "bitmap"],
                )

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(signed, "doc_id long, n long, d1 long, d2 long, p1 long, p2 long, prefix array<long>, bitmap binary")


def _most_apart(nx: np.ndarray, ny: np.ndarray, percent: int) -> np.ndarray:
    """The largest symmetric difference with which sets of these sizes still link."""
    both = nx + ny
    return both - 2 * -(-percent * both // (100 + percent))


class Groups:
    """Group parts that meet in a tile, in the order of set sizes: their members' labels and parity bitmaps, and what the bitmaps of all members of a part have in common."""

    def __init__(self, gid: np.ndarray, n: np.ndarray, members: list[tuple[list, list, list]]) -> None:
        order = np.argsort(n, kind="stable")
        members = [members[k] for k in order]
        self.order, self.gid, self.n = order, gid[order], n[order]
        self.first = np.concatenate([[0], np.cumsum([len(m[0]) for m in members])])
        self.node = np.array([x for m in members for x in m[0]], dtype=np.int64)
        self.label = np.array([x for m in members for x in m[1]], dtype=np.int64)
        maps = [np.frombuffer(x, dtype="<u8") for m in members for x in m[2]]
        self.words = np.array([len(maps[k]) for k in self.first[:-1]])
        self.of_width, self.at = {}, np.zeros(len(maps), dtype=np.int64)
        self.known, self.value, self.place = {}, {}, np.zeros(len(members), dtype=np.int64)
        for w in np.unique(self.words):
            groups = np.flatnonzero(self.words == w)
            nodes = np.concatenate([np.arange(self.first[g], self.first[g + 1]) for g in groups])
            self.at[nodes], self.place[groups] = np.arange(len(nodes)), np.arange(len(groups))
            stack = np.stack([maps[k] for k in nodes])
            begins = np.concatenate([[0], np.cumsum(np.diff(self.first)[groups])[:-1]])
            every, some = np.bitwise_and.reduceat(stack, begins), np.bitwise_or.reduceat(stack, begins)
            self.of_width[w], self.value[w], self.known[w] = stack, every, ~(every ^ some)
        self.spread()

    def spread(self) -> None:
        """The smallest and the largest label of each part."""
        self.low, self.high = np.minimum.reduceat(self.label, self.first[:-1]), np.maximum.reduceat(self.label, self.first[:-1])

    def members(self, groups: np.ndarray) -> np.ndarray:
        return np.concatenate([np.arange(self.first[g], self.first[g + 1]) for g in groups])


def _folded(x: np.ndarray, words: int) -> np.ndarray:
    """Parity bitmaps brought to fewer words."""
    while x.shape[1] > words:
        half = x.shape[1] // 2
        x = x[:, :half] ^ x[:, half:]
    return x


def _folded_known(value: np.ndarray, known: np.ndarray, words: int) -> tuple[np.ndarray, np.ndarray]:
    """The same for bits that all members share: a folded bit is shared where both its halves are."""
    while value.shape[1] > words:
        half = value.shape[1] // 2
        value, known = value[:, :half] ^ value[:, half:], known[:, :half] & known[:, half:]
    return value, known


def _group_pairs(g: Groups, i: int, w: int, side: np.ndarray | None, same: bool, percent: int) -> np.ndarray:
    """Parts of bitmap width w, not smaller than part i, that may hold a set linked to one of i's: sizes, labels and the bits in which all members of one differ from all of the other decide."""
    js = np.flatnonzero(g.words == w)
    one = (g.low[js] == g.high[js]) & (g.low[i] == g.high[i]) & (g.low[js] == g.low[i])
    ok = (js > i) & (percent * g.n[js] <= 100 * g.n[i]) & ~one
    if side is not None:
        ok &= side[js] != side[i]
    if not same:
        ok &= g.gid[js] != g.gid[i]
    js = js[ok]
    if not len(js):
        return js
    at, mine = g.place[js], g.words[i]
    value, known = _folded_known(g.value[w][at], g.known[w][at], mine)
    apart = np.bitwise_count((value ^ g.value[mine][g.place[i]]) & known & g.known[mine][g.place[i]]).sum(axis=1, dtype=np.int64)
    return js[apart <= _most_apart(g.n[i], g.n[js], percent)]


def _near_pairs(g: Groups, side: np.ndarray | None, same: bool, forest: bool, percent: int) -> Iterator[tuple[int, np.ndarray]]:
    """(a, bs): members with different labels whose sizes and bitmaps don't exclude a link.

    Pairs of group parts are filtered first, and only members of pairs that are left are compared: a set differs from another by at least as many shingles as their parity bitmaps
    differ by bits. With `side`, only parts of different sides meet. With `same`, parts of one group meet, and the members of one part (unless there are sides). With `forest`, just enough pairs are given to join what all would connect.
    """
    for i in range(len(g.n)):
        met = [np.array([i])] if same and side is None and g.first[i + 1] - g.first[i] > 1 else []
        met += [_group_pairs(g, i, w, side, same, percent) for w in (g.words[i], 2 * g.words[i], 4 * g.words[i]) if w in g.of_width]
        for js in met:
            if not len(js):
                continue
            theirs = g.members(js)
            size = np.repeat(g.n[js], np.diff(g.first)[js])
            maps = _folded(g.of_width[g.words[js[0]]][g.at[theirs]], g.words[i])
            for a in range(g.first[i], g.first[i + 1]):
                ok = g.label[theirs] != g.label[a]
                if js[0] == i:
                    ok &= theirs > a
                ok[ok] = np.bitwise_count(maps[ok] ^ g.of_width[g.words[i]][g.at[a]]).sum(axis=1, dtype=np.int64) <= _most_apart(g.n[i], size[ok], percent)
                found = theirs[ok]
                if not len(found):
                    continue
                if forest:
                    _, firsts = np.unique(g.label[found], return_index=True)
                    found = found[firsts]
                    g.label[np.isin(g.label, g.label[found])] = g.label[a]
                    g.spread()
                yield a, found


def _candidates(rows: DataFrame, forest: bool, percent: int) -> DataFrame:
    """Pairs (a, b) of nodes that meet in a tile and may link. rows: tile columns b0, b1, x, y, then own (x or y), gid, n, nodes, labels, bitmaps of a group part.

    Buckets with b0 = 1 hold the parts of one group, whose members meet across parts and within; in others, parts of one group do not meet.
    """

    def compared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        open_key, held, out = None, [], []

        def close() -> None:
            if not held or (len(held) < 2 and not open_key[0]):
                return
            g = Groups(np.array([r[1] for r in held]), np.array([r[2] for r in held]), [r[3:] for r in held])
            side = np.array([r[0] for r in held])[g.order] if open_key[2] != open_key[3] else None
            for a, bs in _near_pairs(g, side, bool(open_key[0]), forest, percent):
                out.extend((min(g.node[a], g.node[b]), max(g.node[a], g.node[b])) for b in bs)

        def batch_out() -> pa.RecordBatch:
            pairs = np.array(sorted(set(out)), dtype=np.int64).reshape(-1, 2)
            out.clear()
            return pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], names=["a", "b"])

        for batch in batches:
            columns = [c.to_pylist() for c in batch.columns]
            for key, row in zip(zip(*columns[:4], strict=True), zip(*columns[4:], strict=True), strict=True):
                if key != open_key:
                    close()
                    open_key, held = key, []
                    if len(out) > 50_000:
                        yield batch_out()
                held.append(row)
        close()
        yield batch_out()

    tiled = rows.repartition("b0", "b1", "x", "y").sortWithinPartitions("b0", "b1", "x", "y")
    return tiled.select("b0", "b1", "x", "y", "own", "gid", "n", "nodes", "labels", "bitmaps").mapInArrow(compared, "a long, b long").distinct()


def _verified(docs: DataFrame, pairs: DataFrame, stages: Stages, width: int, percent: int) -> DataFrame:
    """The pairs whose whole shingle sets are similar enough."""
    ids = stages.write(pairs.select(F.explode(F.array("a", "b")).alias("wanted")).distinct())

    marks = _marks(ids)

    def listed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            batch = batch.filter(pa.array(_is_marked(marks.value, batch.column("doc_id").to_numpy())))
            for a, b, data, offsets in textkit.texts(batch.column("text")):
                s = Sets(data, offsets, width, None)
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(a, b - a), _list(s.h, s.n)], names=["doc_id", "items"])

    known = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").where("doc_id is not null")
    sets = stages.write(known.mapInArrow(listed, "doc_id long, items array<long>").join(ids, F.col("doc_id") == F.col("wanted"), "left_semi"))
    left = pairs.join(sets.toDF("a", "x"), "a").join(sets.toDF("b", "y"), "b")
    common = left.select("a", "b", F.size("x").alias("nx"), F.size("y").alias("ny"), F.size(F.array_intersect("x", "y")).alias("shared"))
    links = stages.write(common.where((100 + percent) * F.col("shared") >= percent * (F.col("nx") + F.col("ny"))).select("a", "b").distinct())
    stages.drop(ids, sets)
    return links


def _labelled(parts: DataFrame, labels: DataFrame | None) -> DataFrame:
    """(gid, part, n, labels, lo, hi): the labels of each part's members in their order, and the smallest and the largest; a node without a label is its own."""
    if labels is None:
        named = parts.select("gid", "part", "n", F.col("nodes").alias("labels"))
    else:
        told = parts.select("gid", "part", F.posexplode("nodes").alias("pos", "node")).join(labels, "node").groupBy("gid", "part").agg(F.map_from_entries(F.collect_list(F.struct("pos", "label"))).alias("new"))
        own = F.transform("nodes", lambda x, k: F.coalesce(F.col("new")[k], x))
        named = parts.select("gid", "part", "n", "nodes").join(told, ["gid", "part"], "left").select("gid", "part", "n", F.when(F.col("new").isNull(), F.col("nodes")).otherwise(own).alias("labels"))
    return named.withColumns({"lo": F.array_min("labels"), "hi": F.array_max("labels")})


def _chunk_id(band: Column, kind: Column, chunk: Column) -> Column:
    return F.shiftleft(band.cast("long") * 2 + kind, 32) + chunk


def _tiles(buckets: DataFrame, parts: DataFrame, labels: DataFrame | None, seed: int, stages: Stages, all_pairs: bool, large_only: bool, percent: int) -> DataFrame:
    """Rows of _candidates() for the buckets (b0, b1, gid) whose members hold different labels; with `large_only`, of more than TILE group parts.

    A bucket of at most TILE group parts is one tile. A larger one is cut into chunks by hash. Without `all_pairs` each chunk stays alone. With it chunks meet, but only those of
    neighbouring size bands (sets of others are too unlike in size to link) and only where not both hold nothing but the bucket's commonest label: so a bucket that is connected
    but for a few members copies its rows to the chunks of these few alone. Keys without bitmaps and all sums are written first, so that joins on a bucket read plain tables and large buckets can be split.
    """
    bucket = ["b0", "b1"]
    keyed = stages.write(buckets.join(_labelled(parts, labels), "gid"))
    sizes = keyed.groupBy(*bucket).agg(F.count(F.lit(1)).alias("m"), F.min("lo").alias("least"), F.max("hi").alias("most")).where("least <> most")
    sizes = stages.write((sizes.where(F.col("m") > TILE) if large_only else sizes).select(*bucket, "m"))
    placed = stages.write(keyed.join(sizes, bucket))
    maps = parts.select("gid", "part", "nodes", "bitmaps")
    chunk_of = lambda n: F.pmod(F.xxhash64("gid", "part", F.lit(seed)), F.ceil(F.col(n) / F.lit(TILE))).cast("long")
    columns = [*bucket, "x", "y", "own", "gid", "n", "nodes", "labels", "bitmaps"]
    if not all_pairs:
        return placed.withColumn("own", chunk_of("m")).withColumns({"x": F.col("own"), "y": F.col("own")}).join(maps, ["gid", "part"]).select(*columns)
    small = placed.where(F.col("m") <= TILE).withColumns({c: F.lit(0).cast("long") for c in ("own", "x", "y")}).join(maps, ["gid", "part"]).select(*columns)
    large = placed.where(F.col("m") > TILE)
    if large.isEmpty():
        return small
    band = F.floor(F.log(F.col("n").cast("double")) / F.lit(math.log(101 / percent)))  # a little wider than linked sizes are apart
    common = stages.write(large.where("lo = hi").groupBy(*bucket, "lo").agg(F.count(F.lit(1)).alias("k")).groupBy(*bucket).agg(F.max_by("lo", F.struct("k", "lo")).alias("common")))
    kind = F.when((F.col("lo") == F.col("hi")) & (F.col("lo") == F.col("common")), 0).otherwise(1)
    large = stages.write(large.join(common, bucket, "left").withColumns({"band": band, "kind": kind}))
    cells = large.groupBy(*bucket, "band", "kind").agg(F.count(F.lit(1)).alias("held"))
    near = cells.select(*bucket, F.explode(F.array(F.col("band") - 1, F.col("band"), F.col("band") + 1)).alias("band"), F.struct(F.col("band").alias("band"), "kind", F.ceil(F.col("held") / F.lit(TILE)).alias("chunks")).alias("other"))
    partners = cells.join(near, [*bucket, "band"]).where("kind = 1 or other.kind = 1").groupBy(*bucket, "band", "kind", "held").agg(F.collect_list("other").alias("others"))
    partners = stages.write(partners)
    theirs = F.flatten(F.transform("others", lambda o: F.transform(F.sequence(F.lit(0).cast("long"), o["chunks"] - 1), lambda c: _chunk_id(o["band"], o["kind"], c))))
    own = large.join(partners, [*bucket, "band", "kind"]).withColumn("own", _chunk_id(F.col("band"), F.col("kind"), chunk_of("held")))
    met = own.select(*bucket, "gid", "part", "n", "labels", "own", theirs.alias("theirs")).join(maps, ["gid", "part"])
    met = met.withColumn("other", F.explode("theirs")).withColumns({"x": F.least("own", "other"), "y": F.greatest("own", "other")})
    return small.unionByName(met.select(*columns))


def near_copies(docs: DataFrame, width: int = WIDTH, percent: int = PERCENT) -> DataFrame:
    """One row per document: doc_id, n_shingles (size of its set of word shingles), component_id.

    Documents link when |A and B| * 100 >= percent * |A or B|; component_id is the smallest doc_id reachable by links. Words are
    lower-cased in A-Z. With fewer than `width` words the whole sequence is the only shingle; without words the set is empty and links with nothing.

    1. Shingles are counted into a table of fixed size, which orders them from rare to common (any order gives the same links).
    2. Documents with equal sets become one node. Nodes with equal prefixes and sizes become one group; a group of many nodes is cut into parts of a few.
    3. Groups meet in a bucket for each shingle of their prefixes; buckets with the same groups are the same bucket, and buckets with the same smallest
       group are joined into one, which holds the same pairs and more, but each once. The parts of a group of several meet in a bucket of their own.
       In a bucket pairs of group parts are filtered by size and by the bits that all members of a part share; the pairs that are left expand to pairs of members,
       which their own bitmaps filter again, and whole sets verify. No pairs are made of what is known to be connected:
       one round (two, where a bucket is larger than a tile) proposes a forest for each tile, whose links are verified and joined to components, and a last one proposes every
       remaining pair across components. The number of rounds changes what is compared, never which documents are linked.
    4. Components of verified links are handed to all documents with the same set.

    Null and empty texts have n_shingles 0 and their own id as component. Rows that repeat an id are each given the component of their own
    text. A null id takes part in no link, and has the component of its equals. An empty table gives no rows. Other columns are ignored.
    """
    spark = docs.sparkSession
    stages = Stages(spark, "near")
    counts = spark.sparkContext.broadcast(shingle_counts(docs, width))
    signed = stages.write(_signed(docs, counts, width, percent))
    members = stages.write(signed.select("doc_id", "n", "d1", "d2"))
    known = signed.where("n > 0 and doc_id is not null")
    nodes = stages.write(known.groupBy("d1", "d2", "n").agg(F.min("doc_id").alias("node"), F.first("p1").alias("p1"), F.first("p2").alias("p2"), F.first("bitmap").alias("bitmap")))
    groups = stages.write(known.groupBy("n", "p1", "p2").agg(F.min("doc_id").alias("gid"), F.first("prefix").alias("prefix")))
    stages.drop(signed)
    grouped = stages.write(nodes.select("node", "n", "p1", "p2").join(groups.select("n", "p1", "p2", "gid"), ["n", "p1", "p2"]).select("node", "gid"))
    posted = groups.select("gid", F.explode("prefix").alias("token"))
    lists = posted.groupBy("token").agg(F.count(F.lit(1)).alias("groups"), F.bit_xor(F.xxhash64("gid")).alias("x1"), F.bit_xor(F.xxhash64("gid", F.lit(1))).alias("x2"), F.min("gid").alias("leader"))
    tokens = stages.write(lists.where("groups > 1").groupBy("groups", "x1", "x2").agg(F.min("token").alias("token"), F.min("leader").alias("leader")).select("token", "leader"))
    few = _marked_only(groups.select("gid", "prefix"), "prefix", tokens.select("token")).select("gid", F.explode("prefix").alias("token"))
    met = few.join(tokens, "token").select(F.lit(0).alias("b0"), F.col("leader").alias("b1"), "gid").distinct()
    several = stages.write(grouped.groupBy("gid").agg(F.count(F.lit(1)).alias("size")).where("size > 1"))
    buckets = stages.write(met.union(several.select(F.lit(1).alias("b0"), F.col("gid").alias("b1"), "gid")))
    stages.drop(groups, tokens)
    inside = _marked_only(grouped.select("gid", "node"), "gid", buckets.select("gid")).join(several, "gid", "left")
    maps = _marked_only(nodes.select("node", "n", "bitmap"), "node", inside.select("node"))
    cut = F.when(F.col("size").isNull(), 0).otherwise(F.pmod(F.xxhash64("node"), F.ceil(F.col("size") / F.greatest(F.lit(1), F.least(F.lit(PART), F.expr(f"{PART_SHINGLES} DIV n"))))))
    dealt = maps.join(inside, "node").select("gid", cut.cast("int").alias("part"), "n", F.struct("node", "bitmap").alias("member"))
    held = dealt.groupBy("gid", "part", "n").agg(F.collect_list("member").alias("members"))
    parts = stages.write(held.select("gid", "part", "n", F.col("members.node").alias("nodes"), F.col("members.bitmap").alias("bitmaps")))
    largest = buckets.join(parts.select("gid"), "gid").groupBy("b0", "b1").count().agg(F.max("count")).first()[0]
    turns = [1, 2, 3] if (largest or 0) > TILE else [1, 3]  # the second forest only reaches over chunks
    links = labels = None
    for turn in turns:
        pairs = stages.write(_candidates(_tiles(buckets, parts, labels, turn, stages, turn == 3, turn == 2, percent), turn < 3, percent))
        found = _verified(docs, pairs, stages, width, percent)
        links = found if links is None else links.union(found)
        if turn == 1 or not found.isEmpty():
            labels = components(links, stages)
    keys = nodes.select("d1", "d2", "n", "node").withColumnRenamed("n", "n0")
    keys = stages.write(keys.join(labels, "node", "left").select("d1", "d2", "n0", F.coalesce("label", "node").alias("root")))
    stages.keep_only(members, keys)
    same = (members.d1 == keys.d1) & (members.d2 == keys.d2) & (members.n == keys.n0)
    return members.join(keys, same, "left").select(
        "doc_id", F.col("n").alias("n_shingles"), F.when(F.col("n") > 0, F.col("root")).otherwise(F.col("doc_id")).alias("component_id")
    )


def one_of_each(docs: DataFrame) -> DataFrame:
    """The documents whose id is their component's, and those with a null id; all columns as they are."""
    name = unused(docs, "kept_id")
    kept = near_copies(docs).where("doc_id = component_id").select(F.col("doc_id").alias(name)).distinct()
    known = docs.where("doc_id is not null").join(kept, F.col("doc_id") == F.col(name), "left_semi")
    return known.unionByName(docs.where("doc_id is null"))
