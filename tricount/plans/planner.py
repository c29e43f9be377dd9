"""Choosing a plan by measured sizes, timing plans, and the models that runs are held against."""

from __future__ import annotations

import itertools
import math
import statistics
import time
from collections.abc import Callable, Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tricount.functions.measures import pairs_of, travel_sums
from tricount.operators import prep
from tricount.operators.count import JOINED_LIMIT
from tricount.operators.split import REPLICATE_LIMIT

#: List elements for each 64-bit word from which on bit sets beat lists (measured: 5 times faster at 10 and more, 3 times slower at 1).
DENSE = 4


#: Rows that may name one target before it is split, and elements of a list before it is cut up.
SPLIT_OVER, SALT_OVER = 1 << 16, 1 << 16
#: Bytes of lists or words that edges may carry through joins, before compression.
MOVED_BYTES = 1 << 28


def plan_statistics(edges: DataFrame) -> dict[str, int]:
    """E, the longest list, the most edges into one vertex, the list elements that travel by join order, the oriented wedges, and the 64-bit words that lists fill as bit sets, from four actions."""
    o = prep.orient(edges)
    lists = o.groupBy("src").agg(F.count(F.lit(1)).alias("n"))
    size = lists.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("edges"), F.coalesce(F.max("n"), F.lit(0)).alias("max_out"), F.coalesce(F.sum(pairs_of(F.col("n"))), F.lit(0)).alias("wedges")).first()
    into = o.groupBy("dst").agg(F.count(F.lit(1)).alias("n")).agg(F.coalesce(F.max("n"), F.lit(0)).alias("max_in")).first()
    travel = travel_sums(o).first()
    words = o.select("src", F.expr("dst DIV 64")).distinct().count()
    return {"words": words, "edges": size.edges, "max_out": size.max_out, "max_in": into.max_in, "wedges": int(size.wedges), "src_first": travel.src_first, "dst_first": travel.dst_first}


def choose(edges: DataFrame, limit: int = REPLICATE_LIMIT, split_over: int = SPLIT_OVER, salt_over: int = SALT_OVER) -> tuple[str, dict]:
    """(method, options): two-paths in blocks of lists beyond JOINED_LIMIT edges, without measuring more, and where edges would carry over MOVED_BYTES through the joins of the form chosen otherwise; bit sets where lists are dense; lists cut up where one is longer than `salt_over`; else the grouped form where its lists can be broadcast or sources travel less, else lists
    joined at the target first. Vertices that more than `split_over` edges run into are split over tasks; then the grouped form stands for both join orders."""
    if edges.count() > JOINED_LIMIT:
        return "forward_paths", {}
    s = plan_statistics(edges)
    hubs = {"split_over": split_over} if s["max_in"] > split_over else {}
    if s["max_out"] > salt_over:
        return "forward_salted", {"salt_over": salt_over} | hubs
    dense = DENSE * s["words"] <= s["edges"] and not hubs
    # An edge carries its source's words as rows of 32 bytes, of which there are about as many as list elements over elements per word; or a list of 8 bytes an element.
    if (32 * s["src_first"] * s["words"] // max(s["edges"], 1) if dense else 8 * min(s["src_first"], s["dst_first"])) > MOVED_BYTES:
        return "forward_paths", {}
    if dense:
        return "forward_bitmap", {}
    if hubs or 8 * s["edges"] <= limit or s["src_first"] <= s["dst_first"]:
        return "forward_grouped", hubs
    return "forward_lists", {"first": "dst"}


def _below(node) -> list:
    """The operators under one of an executed plan, through adaptive stages."""
    kind = node.getClass().getSimpleName()
    if kind == "AdaptiveSparkPlanExec":
        return [node.executedPlan()]
    if kind.endswith("QueryStageExec"):
        return [node.plan()]
    children = node.children()
    return [children.apply(k) for k in range(children.size())]


def _metric(node, name: str) -> int | None:
    found = node.metrics().get(name)
    return int(found.get().value()) if found.isDefined() else None


def _rows_from(node) -> int:
    """Rows that an operator hands up: its own count, or that of the nearest one below it that counts."""
    for name in ("shuffleRecordsWritten", "numOutputRows"):
        if (n := _metric(node, name)) is not None:
            return n
    return _rows_from(_below(node)[0])


def _executed(df: DataFrame):
    run = df._jdf.queryExecution()
    run.toRdd().count()
    return run.executedPlan()


def plan_costs(df: DataFrame) -> dict[str, int]:
    """What a plan moved, from the metrics of its operators after it has run: rows and bytes through shuffles, rows that entered the topmost sort, bytes spilled, and the most memory of one operator."""
    out = dict.fromkeys(("shuffle_rows", "shuffle_bytes", "sorted_rows", "spill_bytes", "peak_bytes"), 0)
    seen, waiting, sorts = set(), [_executed(df)], []
    while waiting:
        node = waiting.pop(0)
        kind = node.getClass().getSimpleName()
        if kind == "ShuffleExchangeExec" and node.id() not in seen:
            seen.add(node.id())
            out["shuffle_rows"] += _metric(node, "shuffleRecordsWritten") or 0
            out["shuffle_bytes"] += _metric(node, "dataSize") or 0
        if kind == "SortExec":
            sorts.append(node)
        out["spill_bytes"] += _metric(node, "spillSize") or 0
        out["peak_bytes"] = max(out["peak_bytes"], _metric(node, "peakMemory") or 0)
        waiting += _below(node)
    out["sorted_rows"] = _rows_from(_below(sorts[0])[0]) if sorts else 0
    return out


def sorted_rows(edges: DataFrame) -> DataFrame:
    """(plan, rows): what enters the sort of the edge array when backward rows go after it, and before it."""
    rows = [(p, plan_costs(prep.preprocess(edges, p))["sorted_rows"]) for p in ("sort_first", "filter_first")]
    return edges.sparkSession.createDataFrame(rows, "plan string, rows long")


def subgraph_classes(edges: int, group_bytes: int, edge_bytes: int = 8) -> int:
    """The least number of classes with which three-class subgraphs of evenly spread edges stay within `group_bytes`."""
    return max(1, math.ceil(math.sqrt(6 * edges * edge_bytes / group_bytes)))


def amdahl(share: float, devices: int, copy: float = 0.0) -> float:
    """The highest speedup on `devices` when `share` of the run stays serial, and each further device costs `copy` of the run."""
    return 1 / (share + (1 - share) / devices + copy * (devices - 1))


def amdahl_share(speedup: float, devices: int) -> float:
    """The serial share that would explain a measured speedup."""
    return (devices / speedup - 1) / (devices - 1)


def amdahl_table(spark: SparkSession, shares: Iterable[int] = (8, 76), devices: Iterable[int] = (1, 2, 4)) -> DataFrame:
    """(share, devices, ceiling), shares in hundredths."""
    grid = spark.createDataFrame(list(itertools.product(shares, devices)), "share int, devices int")
    f = F.col("share") / F.lit(100.0)
    return grid.withColumn("ceiling", F.round(1 / (f + (1 - f) / F.col("devices")), 3))


def timed(run: Callable[[], DataFrame], reps: int = 5, warmup: int = 1) -> dict:
    """Wall-clock ms of an action that writes nowhere: mean, deviation, and whether the deviation is above 5 % of the mean. The session is started before."""
    out = []
    for k in range(warmup + reps):
        began = time.perf_counter()
        run().write.format("noop").mode("overwrite").save()
        if k >= warmup:
            out.append(1000 * (time.perf_counter() - began))
    mean, std = statistics.fmean(out), statistics.stdev(out) if len(out) > 1 else 0.0
    return {"ms": mean, "std": std, "noisy": std > 0.05 * mean, "reps": len(out)}


def speedup(runs: dict[str, dict], base: str) -> dict[str, float]:
    return {k: runs[base]["ms"] / r["ms"] for k, r in runs.items()}


def ablation(runs: dict[str, dict], with_option: str, without: str) -> float:
    """The gain of an option in per cent of the run without it."""
    return 100 * (runs[without]["ms"] - runs[with_option]["ms"]) / runs[without]["ms"]


def tune_grid(run: Callable[[int, int], DataFrame], partitions: Iterable[int], batches: Iterable[int], near: float = 0.05) -> list[dict]:
    """Times run(partitions, batch) over a grid; the points within `near` of the best are marked."""
    grid = [{"partitions": p, "batch": b} | timed(lambda p=p, b=b: run(p, b), reps=2) for p, b in itertools.product(partitions, batches)]
    best = min(g["ms"] for g in grid)
    return [g | {"optimal": g["ms"] <= (1 + near) * best} for g in grid]


def proportionality(runs: DataFrame) -> DataFrame:
    """How well ms follows each of edges, triangles and steps: slope and r2, one row for each (runs holds these columns)."""
    rows = [runs.agg(F.lit(x).alias("predictor"), F.regr_slope("ms", x).alias("slope"), F.regr_r2("ms", x).alias("r2")) for x in ("edges", "triangles", "steps")]
    return rows[0].unionByName(rows[1]).unionByName(rows[2])


def sql_functions(spark: SparkSession) -> None:
    """SQL functions and a table function for interactive use: triangles_at(src, nbrs_u, nbrs_v) gives a row for each shared neighbour."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="third bigint")
    class Shared:
        def eval(self, a: list, b: list):
            other = set(b or ())
            for x in a or ():
                if x in other:
                    yield (x,)

    spark.udtf.register("triangles_at", Shared)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION wedge_pairs(d BIGINT) RETURNS DECIMAL(38,0) RETURN CAST(d AS DECIMAL(19,0)) * (d - 1) / 2")


# The published run times in ms (graph, kind, one processor, older card, four older cards, newer card) and counts in millions (edges, triangles).
PUBLISHED = [
    ("internet", "real", 3459, 277, 306, 186, 22, 29),
    ("livejournal", "real", 13829, 951, 947, 540, 69, 178),
    ("orkut", "real", 82558, 9690, 7580, 2815, 234, 628),
    ("citeseer", "real", 4990, 578, 456, 329, 32, 872),
    ("dblp", "real", 4712, 446, 410, 239, 30, 442),
    ("kronecker_16", "synthetic", 2810, 179, 97, 82, 5, 119),
    ("kronecker_17", "synthetic", 6957, 476, 219, 219, 10, 288),
    ("kronecker_18", "synthetic", 17808, 1274, 499, 558, 21, 688),
    ("kronecker_19", "synthetic", 45947, 3434, 1304, 1443, 44, 1626),
    ("kronecker_20", "synthetic", 116811, 9308, 3296, 3942, 89, 3804),
    ("kronecker_21", "synthetic", 297426, 33150, 13624, 12009, 182, 8816),
    ("barabasi_albert", "synthetic", 5508, 327, 263, 155, 20, 3),
    ("watts_strogatz", "synthetic", 9627, 589, 576, 324, 50, 219),
]


def published_speedups(spark: SparkSession) -> DataFrame:
    """Speedups of the published times: older card and newer card over one processor, four older cards over one, and the rates of the newer card."""
    t = spark.createDataFrame(PUBLISHED, "graph string, kind string, cpu int, older int, older4 int, newer int, medges int, mtriangles int")
    return t.select(
        "graph", F.round(F.col("cpu") / F.col("older"), 2).alias("older_speedup"), F.round(F.col("older") / F.col("older4"), 2).alias("four_over_one"), F.round(F.col("cpu") / F.col("newer"), 2).alias("newer_speedup"),
        F.round(1000.0 * F.col("medges") / F.col("newer"), 1).alias("medges_s"), F.round(1000.0 * F.col("mtriangles") / F.col("newer"), 1).alias("mtriangles_s"),
    )
