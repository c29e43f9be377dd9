"""Triangles of an edge stream: windows, incremental totals, state with bounded memory, late and repeated rows."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from tricount.functions.lineage import ensure_folder, written
from tricount.operators.blocks import count_blocks

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def contacts(events: DataFrame) -> DataFrame:
    """(event_id, event_type, ts, u, v): an event's user and the one its `props.k` names, loops left out. ts becomes a timestamp, as watermarks need one."""
    other = F.get_json_object("props", "$.k").cast("long")
    pairs = events.select("event_id", "event_type", F.col("ts").cast("timestamp").alias("ts"), F.col("user_id").alias("a"), other.alias("b")).where("a <> b")
    return pairs.select("event_id", "event_type", "ts", F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v"))


def edge_stream(spark: SparkSession, folder: str, glob: str = "events.parquet", files_per_batch: int = 1) -> DataFrame:
    """The contacts of event files in a folder, as a stream."""
    raw = spark.readStream.schema(EVENTS).option("pathGlobFilter", glob).option("maxFilesPerTrigger", files_per_batch).parquet(folder)
    return contacts(raw)


def shared_folder(spark: SparkSession, name: str) -> str:
    """A fresh folder under spark.checkpoint.dir, or under the folder set on the context where that is unset."""
    ensure_folder(spark)
    return f"{spark.conf.get('spark.checkpoint.dir', None) or spark.sparkContext.getCheckpointDir()}/{name}-{uuid.uuid4().hex}"


def run_stream(df: DataFrame, folder: str, each: Callable[[DataFrame, int], None] | None = None, mode: str = "append", name: str = "q") -> StreamingQuery:
    """Runs a stream over what is there, then ends it. Rows go to parquet files in folder/out, or to `each`."""
    writer = df.writeStream.outputMode(mode).option("checkpointLocation", f"{folder}/{name}-checkpoint").trigger(availableNow=True)
    writer = writer.foreachBatch(each) if each else writer.format("parquet").option("path", f"{folder}/out")
    query = writer.start()
    query.awaitTermination()
    return query


def triangles_by_key(edges: DataFrame, keys: list[str]) -> DataFrame:
    """(keys, edges, triangles) of many graphs at once: unique (keys, u, v) rows, oriented by degree within each graph."""
    deg = edges.select(*keys, F.explode(F.array("u", "v")).alias("x")).groupBy(*keys, "x").agg(F.count(F.lit(1)).alias("d"))
    both = edges.join(deg.withColumnsRenamed({"x": "u", "d": "du"}), [*keys, "u"]).join(deg.withColumnsRenamed({"x": "v", "d": "dv"}), [*keys, "v"])
    up = F.struct("du", "u") < F.struct(F.col("dv"), F.col("v"))
    o = both.select(*keys, F.when(up, F.col("u")).otherwise(F.col("v")).alias("s"), F.when(up, F.col("v")).otherwise(F.col("u")).alias("d"))
    hop = o.withColumnsRenamed({"s": "a", "d": "b"}).join(o.withColumnsRenamed({"s": "b", "d": "c"}), [*keys, "b"])
    found = hop.join(o.withColumnsRenamed({"s": "a", "d": "c"}), [*keys, "a", "c"], "left_semi").groupBy(*keys).agg(F.count(F.lit(1)).alias("triangles"))
    sizes = edges.groupBy(*keys).agg(F.count(F.lit(1)).alias("edges"))
    return sizes.join(found, keys, "left").select(*keys, "edges", F.coalesce("triangles", F.lit(0)).alias("triangles"))


def stream_windows(stream: DataFrame, window: str = "1 day", slide: str | None = None, delay: str = "1 day") -> DataFrame:
    """Unique (start, u, v) rows of every window, as a stream; a row older than `delay` behind the newest is dropped."""
    span = F.window("ts", window, slide) if slide else F.window("ts", window)
    placed = stream.withWatermark("ts", delay).select(span.alias("w"), "u", "v")
    return placed.groupBy("w", "u", "v").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "u", "v")


def stream_triangles(stream: DataFrame, folder: str, window: str = "1 day", slide: str | None = None, delay: str = "1 day") -> DataFrame:
    """(start, edges, triangles) of each window: rows of closed windows are written by the stream, and counted window by window in one plan.

    Rows of windows still open at the end come with update mode, so that what is there is counted whole.
    """

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/windows/batch={number}")

    run_stream(stream_windows(stream, window, slide, delay), folder, keep, "update")
    rows = stream.sparkSession.read.parquet(f"{folder}/windows").select("start", "u", "v").distinct()
    return triangles_by_key(rows, ["start"])


def closed_windows(stream: DataFrame, folder: str, window: str = "6 hours", delay: str = "1 hour") -> DataFrame:
    """(start, edges, triangles) of the windows that the watermark has closed: each is written once, when it closes, and its state goes."""
    placed = stream_windows(stream, window, None, delay)
    run_stream(placed, folder, lambda batch, number: batch.write.mode("overwrite").parquet(f"{folder}/closed/batch={number}"))
    return triangles_by_key(stream.sparkSession.read.parquet(f"{folder}/closed").select("start", "u", "v"), ["start"])


def stream_sessions(stream: DataFrame, folder: str, gap: str = "30 minutes", delay: str = "1 hour") -> DataFrame:
    """(event_type, start, edges, triangles) of sessions that have ended: a session of a type ends after a gap without its events, and is written when the watermark has passed its end, which frees its state.

    A session's unique edges are gathered in its state.
    """
    held = stream.withWatermark("ts", delay).groupBy("event_type", F.session_window("ts", gap).alias("s")).agg(F.collect_set(F.struct("u", "v")).alias("e"))

    def keep(batch: DataFrame, number: int) -> None:
        batch.select("event_type", F.col("s.start").cast("timestamp_ntz").alias("start"), F.explode("e").alias("e")).select("event_type", "start", "e.*").write.mode("overwrite").parquet(f"{folder}/sessions/batch={number}")

    run_stream(held, folder, keep)
    ended = stream.sparkSession.read.parquet(f"{folder}/sessions").select("event_type", "start", "u", "v")
    return triangles_by_key(ended, ["event_type", "start"])


def new_triangles(old: DataFrame, new: DataFrame) -> DataFrame:
    """One row: the triangles with an edge of `new` in the union. Of the old edges only those at an end of a new one can close anything, so the others are left out first;
    what is left is counted with the new edges and without them, both by blocks of lists, so that no two-paths are shuffled."""
    touched = written(new.select(F.explode(F.array("u", "v")).alias("x")).distinct())
    by_u = old.join(touched, F.col("u") == F.col("x"), "left_semi")
    by_v = old.join(touched, F.col("v") == F.col("x"), "left_semi").join(touched, F.col("u") == F.col("x"), "left_anti")
    near = written(by_u.unionByName(by_v))
    after = count_blocks(near.unionByName(new)).select(F.col("triangles").alias("after"))
    return after.crossJoin(count_blocks(near)).select((F.col("after") - F.col("triangles")).alias("new_triangles"))  # one row each


def incremental_triangles(batch: DataFrame, batch_id: int, store: str) -> None:
    """Adds a batch of edges (u, v) to a store: batch=<id> under store/edges gets its unseen edges, and under store/counts the triangles they close.

    Only folders of earlier batches are read and only those of this batch written, so a batch that runs again leaves the same.
    """
    spark = batch.sparkSession
    fresh = batch.select("u", "v").distinct()
    old = None
    if batch_id:
        old = spark.read.parquet(f"{store}/edges").where(F.col("batch") < batch_id).select("u", "v")
        fresh = fresh.join(old, ["u", "v"], "left_anti")
    fresh.write.mode("overwrite").parquet(f"{store}/edges/batch={batch_id}")
    fresh = spark.read.parquet(f"{store}/edges/batch={batch_id}")
    delta = new_triangles(old if old is not None else fresh.limit(0), fresh)
    delta.coalesce(1).write.mode("overwrite").parquet(f"{store}/counts/batch={batch_id}")


def stream_incremental(stream: DataFrame, folder: str) -> DataFrame:
    """(batch, new_triangles) of a stream, kept up exactly."""
    run_stream(stream, folder, lambda batch, number: incremental_triangles(batch, number, folder))
    return stream.sparkSession.read.parquet(f"{folder}/counts").select(F.col("batch").cast("long").alias("batch"), "new_triangles")


def stream_wedges(left: DataFrame, right: DataFrame, within: str = "1 hour", delay: str = "1 hour") -> DataFrame:
    """(a, b, c, t1, t2): pairs of contacts that share their middle and follow each other within a time, as a stream-stream join with watermarks on both."""
    x = left.withWatermark("ts", delay).select(F.col("u").alias("a"), F.col("v").alias("b"), F.col("ts").alias("t1"))
    y = right.withWatermark("ts", delay).select(F.col("u").alias("b2"), F.col("v").alias("c"), F.col("ts").alias("t2"))
    return x.join(y, F.expr(f"b = b2 AND t2 >= t1 AND t2 <= t1 + INTERVAL {within}")).select("a", "b", "c", "t1", "t2")


def dedup_stream(stream: DataFrame, delay: str = "1 day") -> DataFrame:
    """A contact only once within the delay."""
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["u", "v"])


def late_report(query: StreamingQuery) -> list[tuple[int, int]]:
    """(batch, rows that came behind the watermark and were dropped) of a finished query."""
    return [(p["batchId"], sum(s["numRowsDroppedByWatermark"] for s in p["stateOperators"])) for p in query.recentProgress]


def stateful_triangles(stream: DataFrame, memory: int | None = 10_000, seed: int = 1) -> DataFrame:
    """(event_type, seen, held, kept, estimate) after each batch, from state of at most `memory` edges per event type, or of all edges where it is None.

    `held` edges are in memory, and `kept` triangles among them. With all edges `kept` is the exact number, at the price of state that grows with the graph of a type. With a limit, edges beyond it replace kept ones
    with the chance of an even sample, and counts are scaled by the chance that a triangle's three edges are kept; until the memory is full the estimate is the exact number. Streams of unique edges are expected (see dedup_stream).
    """

    def update(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        seen, edges = state.get if state.exists else (0, [])
        edges = [tuple(e) for e in edges]
        near: dict[int, set[int]] = {}
        for a, b in edges:
            near.setdefault(a, set()).add(b)
            near.setdefault(b, set()).add(a)
        for batch in batches:
            for a, b in zip(batch["u"].tolist(), batch["v"].tolist(), strict=True):
                if b in near.get(a, ()):
                    continue
                seen += 1
                if memory is not None and len(edges) >= memory:
                    slot = hash((seed, seen)) % seen
                    if slot >= memory:
                        continue
                    x, y = edges[slot]
                    near[x].discard(y)
                    near[y].discard(x)
                    edges[slot] = (a, b)
                else:
                    edges.append((a, b))
                near.setdefault(a, set()).add(b)
                near.setdefault(b, set()).add(a)
        kept = sum(len(near[a] & near[b]) for a, b in edges) // 3
        m = seen if memory is None else min(memory, seen)
        chance = m * (m - 1) * (m - 2) / (seen * (seen - 1) * (seen - 2)) if seen > m else 1.0
        state.update((seen, [list(e) for e in edges]))
        yield pd.DataFrame({"event_type": [key[0]], "seen": [seen], "held": [len(edges)], "kept": [kept], "estimate": [kept / chance]})

    return stream.groupBy("event_type").applyInPandasWithState(update, "event_type string, seen long, held long, kept long, estimate double", "seen long, edges array<array<long>>", "update", "NoTimeout")


def batch_windows(events: DataFrame, window: str, slide: str | None = None) -> DataFrame:
    """What stream_triangles() gives, from a table."""
    span = F.window("ts", window, slide) if slide else F.window("ts", window)
    rows = contacts(events).select(span.alias("w"), "u", "v").select(F.col("w.start").cast("timestamp_ntz").alias("start"), "u", "v").distinct()
    return triangles_by_key(rows, ["start"])


def growing_files(events: DataFrame, folder: str, files: int) -> str:
    """Writes events as so many files by time, oldest first, for streams that read a file per batch."""
    path = f"{folder}/in"
    cuts = events.approxQuantile("event_id", [k / files for k in range(1, files)], 0.0)
    bounds = [None, *cuts, None]
    for k in range(files):
        part = events
        if bounds[k] is not None:
            part = part.where(F.col("event_id") >= bounds[k])
        if bounds[k + 1] is not None:
            part = part.where(F.col("event_id") < bounds[k + 1])
        part.coalesce(1).write.mode("append").parquet(path)
    return path
