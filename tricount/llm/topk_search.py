"""Exact top-k inner-product search by distributed histogram selection."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tricount.llm.common import Stages

#: Query vectors handled at once; they are broadcast, at 8 bytes a component.
QUERY_BLOCK = 4096
#: Cells of a histogram.
BINS = 1024
#: Candidate vectors scored at once, by all queries of a block.
TILE = 512


def quantised(column: Column | str, scale: int = 1024) -> Column:
    """floor(scale * x) of each component; null where the vector is null, or holds a null, NaN or infinite component."""
    v = F.col(column) if isinstance(column, str) else column
    v = F.transform(v, lambda x: x.cast("double"))
    bad = F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == F.lit(float("inf"))))
    return F.when(v.isNull() | bad, F.lit(None)).otherwise(F.transform(v, lambda x: F.floor(x * F.lit(float(scale)))))


def _matrix(column: pa.Array, width: int) -> np.ndarray:
    """Rows of a list column as float64, padded with zeros to `width`."""
    sizes = np.diff(column.offsets.to_numpy())
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    if len(sizes) and (sizes == width).all():
        return flat.reshape(-1, width)
    out = np.zeros((len(sizes), width))
    out[np.arange(width)[None, :] < sizes[:, None]] = flat
    return out


def _scores(batch: pa.RecordBatch, queries: np.ndarray, exact: bool) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(ids, scores as int64 with a row per query) for tiles of a batch. `exact`: every sum of products is below 2^53, so doubles hold it."""
    ids = batch.column("vec_id").to_numpy(zero_copy_only=False)
    vectors = _matrix(batch.column("v"), queries.shape[1])
    if not exact:
        queries, vectors = queries.astype(np.int64), vectors.astype(np.int64)
    for a in range(0, len(ids), TILE):
        yield ids[a : a + TILE], (queries @ vectors[a : a + TILE].T).astype(np.int64)


def top_k(vectors: DataFrame, k: int = 10, every: int = 100, id_col: str = "vec_id", vector_col: str = "embedding", scale: int = 1024, block: int = QUERY_BLOCK) -> DataFrame:
    """The k highest integer inner products of each query with all other vectors: query_id, rank, vec_id, score.

    Queries are the ids divisible by `every`; candidates are all rows except those with the query's own id. Ties go to the smaller id.
    For a block of queries, everything is scored, and histograms narrow down where each query's k-th highest score lies: a pass
    counts scores per cell of the query's present range, a task reporting only its highest cells that hold k scores together (lower ones
    cannot hold the k-th of all). The cell with the k-th score becomes the next range, until ranges are one score wide.
    A last pass keeps scores above that value, and of scores equal to it the k smallest ids of each task; ranks are then given.

    Vectors that are null or hold null or non-finite components take no part, nor do null ids. Shorter vectors count as padded by zeros; an empty one scores 0 with all.
    Every row is a candidate, so a repeated id comes once for each of its rows. A repeated query id asks with each of its different vectors, and its ranks are those
    of all these scores together. With fewer than k candidates all are returned; an empty table gives no rows. Sums must stay below 2^63 in size.

    Vectors are made integers once, in a written table; queries are dealt by hash into blocks of some `block`, and each block's rows are written, so a lost executor repeats no other block.
    """
    spark = vectors.sparkSession
    stages = Stages(spark, "top")
    usable = stages.write(vectors.select(F.col(id_col).cast("long").alias("vec_id"), quantised(vector_col, scale).alias("v")).where("vec_id is not null and v is not null"))
    queries = usable.where(F.col("vec_id") % every == 0).distinct()
    stats = usable.agg(F.max(F.size("v")).alias("width"), F.max(F.array_max(F.transform("v", F.abs))).alias("largest")).first()
    asked = queries.count()
    schema = "query_id long, rank int, vec_id long, score long"
    if not asked:
        stages.drop(usable)
        return spark.createDataFrame([], schema)
    bound = int(stats.width) * int(stats.largest or 0) ** 2
    exact = bound < 1 << 53
    blocks = -(-asked // block)
    dealt = stages.write(queries.withColumn("block", F.pmod(F.xxhash64("vec_id", "v"), F.lit(blocks)).cast("int")), "block")
    found = stages.folder()
    for number in range(blocks):
        ask = dealt.where(F.col("block") == number).select("vec_id", "v").collect()
        if ask:
            _block(usable, [r.vec_id for r in ask], [r.v for r in ask], int(stats.width), bound, exact, k).write.mode("append").parquet(found)
    stages.drop(usable, dealt)
    best = W.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    rows = spark.read.schema("query_id long, vec_id long, score long").parquet(found)
    return rows.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def _block(usable: DataFrame, ids: list[int], vectors: list[list[int]], width: int, bound: int, exact: bool, k: int) -> DataFrame:
    spark = usable.sparkSession
    matrix = np.zeros((len(ids), width))
    for row, v in zip(matrix, vectors, strict=True):
        row[: len(v)] = v
    names = np.array(ids, dtype=np.int64)
    shared = spark.sparkContext.broadcast((names, matrix))
    low = np.full(len(ids), -bound, dtype=np.int64)
    high = np.full(len(ids), bound + 1, dtype=np.int64)  # the range ends before it
    cell = np.full(len(ids), -(-(2 * bound + 1) // BINS), dtype=np.int64)  # width of a cell
    above = np.zeros(len(ids), dtype=np.int64)  # scores beyond the range
    settled = np.zeros(len(ids), dtype=bool)
    while not settled.all():
        told = _histogram(usable, shared, low, high, cell, settled, exact, k)
        for q, bins, counts in told:
            order = np.argsort(bins)[::-1]
            total = above[q] + np.cumsum(np.array(counts)[order])
            at = int(np.searchsorted(total, k))
            if at == len(total):  # fewer than k candidates in all: everything is wanted
                low[q], settled[q] = -bound, True
                above[q] = k
                continue
            above[q] = total[at - 1] if at else above[q]
            low[q] += int(bins[order[at]]) * int(cell[q])
            high[q] = min(high[q], low[q] + cell[q])
            settled[q] = cell[q] == 1
            cell[q] = max(1, -(-int(cell[q]) // BINS))
        settled[sorted(set(range(len(ids))) - {q for q, _, _ in told})] = True  # no candidate at all
    return _winners(usable, shared, low, exact, k)


def _histogram(usable, shared, low, high, cell, settled, exact, k) -> list[tuple[int, list[int], list[int]]]:
    """(query, cells, counts) of each unsettled query: scores in its range by cell, without cells that cannot hold the k-th."""

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, queries = shared.value
        ask = np.flatnonzero(~settled)
        seen = np.zeros((len(ask), BINS), dtype=np.int64)
        for batch in batches:
            for ids, s in _scores(batch, queries[ask], exact):
                at = (s - low[ask][:, None]) // cell[ask][:, None]
                ok = (at >= 0) & (s < high[ask][:, None]) & (ids[None, :] != names[ask][:, None])
                rows, cols = np.nonzero(ok)
                seen += np.bincount(rows * BINS + at[rows, cols], minlength=seen.size).reshape(seen.shape)
        higher = np.cumsum(seen[:, ::-1], axis=1)[:, ::-1] - seen
        rows, cols = np.nonzero((seen > 0) & (higher < k))
        for a in range(0, len(rows), 100_000):
            b = slice(a, a + 100_000)
            yield pa.RecordBatch.from_arrays([pa.array(ask[rows[b]]), pa.array(cols[b]), pa.array(seen[rows[b], cols[b]])], names=["q", "bin", "n"])

    cells = usable.mapInArrow(counted, "q long, bin long, n long").groupBy("q", "bin").agg(F.sum("n").alias("n"))
    # Of the summed cells too, only the highest that hold k together can matter.
    higher = F.coalesce(F.sum("n").over(W.partitionBy("q").orderBy(F.desc("bin")).rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    top = cells.withColumn("higher", higher).where(F.col("higher") < k)
    told = top.groupBy("q").agg(F.collect_list(F.struct("bin", "n")).alias("cells")).collect()
    return [(r.q, [c.bin for c in r.cells], [c.n for c in r.cells]) for r in told]


def _winners(usable, shared, low, exact, k) -> DataFrame:
    """The k best rows of each query of a block, given its k-th highest score; a query id with several vectors has k for each."""

    def kept(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, queries = shared.value
        have: list[list[np.ndarray]] = [[], [], []]  # query number, id, score

        def trimmed() -> list[np.ndarray]:
            q, v, s = (np.concatenate(x) if x else np.zeros(0, dtype=np.int64) for x in have)
            order = np.lexsort((v, -s, q))
            q, v, s = q[order], v[order], s[order]
            place = np.arange(len(q)) - np.searchsorted(q, q)
            return [x[place < k] for x in (q, v, s)]

        waiting = 0
        for batch in batches:
            for ids, s in _scores(batch, queries, exact):
                rows, cols = np.nonzero((s >= low[:, None]) & (ids[None, :] != names[:, None]))
                for to, x in zip(have, (rows, ids[cols], s[rows, cols]), strict=True):
                    to.append(x)
                waiting += len(rows)
                if waiting > 500_000:
                    have = [[x] for x in trimmed()]
                    waiting = 0
        q, v, s = trimmed()
        for a in range(0, len(q), 100_000):
            b = slice(a, a + 100_000)
            yield pa.RecordBatch.from_arrays([pa.array(names[q[b]]), pa.array(v[b]), pa.array(s[b])], names=["query_id", "vec_id", "score"])

    best = W.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    rows = usable.mapInArrow(kept, "query_id long, vec_id long, score long")
    return rows.withColumn("place", F.row_number().over(best)).where(F.col("place") <= k).drop("place")


SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(1024 * x::DOUBLE)) AS v FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), s AS (
  SELECT q.vec_id AS query_id, c.vec_id, CASE WHEN least(len(q.v), len(c.v)) = 0 THEN 0 ELSE list_inner_product(q.v, c.v) END::BIGINT AS score
  FROM (SELECT DISTINCT vec_id, v FROM v WHERE vec_id % 100 = 0) q JOIN v c ON q.vec_id <> c.vec_id
)
SELECT query_id, rank::INT AS rank, vec_id, score FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s) WHERE rank <= 10
"""
