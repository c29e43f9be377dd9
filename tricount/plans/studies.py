"""The published experiments on any graph: each study times its variants and gives run records.

    python -m tricount.plans.studies /root/testdata/sf0.01 [study ...]

A record holds study, graph, variant, phase, ms, std, edges, triangles, and `value`, the study's own measure where it has one.
"""

from __future__ import annotations

import json
import sys
from collections.abc import Callable, Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tricount.functions import measures
from tricount.operators import count, prep, split
from tricount.plans.planner import amdahl, amdahl_share, choose, plan_costs, proportionality, timed, tune_grid
from tricount.sources import generators as gen
from tricount.sources.loaders import load_graph

SCHEMA = "study string, graph string, variant string, phase string, ms double, std double, edges long, triangles long, value double"
#: Graphs that stand for the published ones, sparse to dense.
STAND_INS = ("bigram", "nextactor", "coactive", "cosupply_order", "copurchase")


class Graph:
    """Edges at rest with their number; studies start from them, so loading is not timed."""

    def __init__(self, name: str, edges: DataFrame, reps: int = 5) -> None:
        self.name, self.edges, self.reps = name, edges.persist(), reps
        self.n = self.edges.count()

    def record(self, study: str, variant: str, run: Callable[[], DataFrame], phase: str = "total", value: float | None = None) -> dict:
        out = run()
        triangles = out.agg(F.sum("triangles")).first()[0] if "triangles" in out.columns else None
        t = timed(run, self.reps, 0)
        return {"study": study, "graph": self.name, "variant": variant, "phase": phase, "ms": t["ms"], "std": t["std"], "edges": self.n, "triangles": triangles, "value": value}


def every_method(g: Graph) -> list[dict]:
    """The one-task baseline, the chosen plan and four slices over replicated lists; value is the speedup over the baseline."""
    method, options = choose(g.edges)
    out = [] if g.n > count.LOCAL_LIMIT else [g.record("all", "one task", lambda: count.forward_local(g.edges))]
    out.append(g.record("all", method, lambda: count.triangle_total(g.edges, method, **options)))
    out.append(g.record("all", "4 slices", lambda: split.count_replicated(g.edges, 4)))
    reuse, ms = measures.list_reuse(g.edges).first(), out[-2]["ms"]
    rates = {"reuse of a list": float(reuse.reuse or 0), "list megabytes a second": reuse.bytes / 1000 / ms}
    return [r | {"value": out[0]["ms"] / r["ms"]} for r in out] + [out[-2] | {"variant": k, "phase": "profile", "ms": None, "std": None, "value": v} for k, v in rates.items()]


def input_format(g: Graph) -> list[dict]:
    """Lists that are ready, an edge array, and the conversion of one into the other alone."""
    lists = prep.to_adjacency(prep.edge_array(g.edges)).persist()
    lists.count()
    out = [
        g.record("input", "neighbour lists", lambda: count.adjacency_input(lists)), g.record("input", "edge array", lambda: count.forward_grouped(g.edges)),
        *([] if g.n > count.LOCAL_LIMIT else [g.record("input", "neighbour lists, one task", lambda: count.forward_local_lists(lists)), g.record("input", "edge array, one task", lambda: count.forward_local(g.edges))]),
        g.record("input", "array to lists", lambda: prep.to_adjacency(prep.edge_array(g.edges)), "convert"), g.record("input", "lists to array", lambda: prep.to_edge_array(lists), "convert"),
    ]
    lists.unpersist()
    return out


def record_columns(g: Graph) -> list[dict]:
    """Pairs as one struct column against two columns, and what unzipping costs."""
    records = prep.zip_records(g.edges.toDF("src", "dst")).persist()
    records.count()
    as_edges = lambda: prep.unzip(records).toDF("u", "v")
    out = [
        g.record("unzip", "two columns", lambda: count.forward_grouped(g.edges)), g.record("unzip", "records", lambda: count.forward_grouped(as_edges())),
        g.record("unzip", "unzip alone", as_edges, "convert"),
    ]
    records.unpersist()
    return out


def sort_keys(g: Graph) -> list[dict]:
    """Sorting pairs against one packed key; ids that do not fit a packed key are refused by it."""
    array = prep.edge_array(g.edges)
    return [g.record("sort", f"{key} {layout}", lambda key=key, layout=layout: prep.sort_edges(array, key, layout, total=True), "sort") for key in ("pair", "packed") for layout in ("src_major", "dst_major")]


def list_reads(g: Graph) -> list[dict]:
    """List elements read by a merge that holds both heads, and by one that reads both anew; value is reads for each step."""
    r = measures.read_counters(g.edges).first()
    kernels = (("one read for each move", "merge", r.lazy_reads), ("both heads each step", "merge_eager", r.eager_reads))
    return [g.record("read", name, lambda k=k: count.forward_lists(g.edges, kernel=k), "count", n / max(r.steps, 1)) for name, k, n in kernels]


def list_cache(g: Graph) -> list[dict]:
    """Lists replicated to every executor against lists that are shuffled; value is how often a list is fetched."""
    reuse = measures.list_reuse(g.edges).first().reuse
    out = [g.record("cache", name, lambda limit=limit: split.count_replicated(g.edges, 1, limit=limit)) for name, limit in (("replicated", split.REPLICATE_LIMIT), ("shuffled", 0))]
    return [r | {"value": float(reuse or 0)} for r in out]


def _with_batches(g: Graph, partitions: int, batch: int) -> Callable[[], DataFrame]:
    """A merge count over so many partitions of lists and rows in an Arrow batch."""

    def run() -> DataFrame:
        g.edges.sparkSession.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(batch))
        return count.forward_lists(g.edges, kernel="merge", partitions=partitions)

    return run


def _keeping_batches(g: Graph, run: Callable[[], list[dict]]) -> list[dict]:
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = g.edges.sparkSession.conf.get(name)
    try:
        return run()
    finally:
        g.edges.sparkSession.conf.set(name, before)


def work_unit(g: Graph) -> list[dict]:
    """The unit that a kernel works on at once, halved and halved again."""
    return _keeping_batches(g, lambda: [g.record("warp", f"batch {b}", _with_batches(g, 8, b), "count") for b in (10_000, 5_000, 2_500)])


def launch_grid(g: Graph, partitions: Iterable[int] = (4, 8, 16), batches: Iterable[int] = (1_000, 10_000)) -> list[dict]:
    """Tasks over joined lists against rows of a batch; value is 1 for the best point and those near it."""
    grid = _keeping_batches(g, lambda: tune_grid(lambda p, b: _with_batches(g, p, b)(), partitions, batches))
    return [{"study": "grid", "graph": g.name, "variant": f"{r['partitions']} x {r['batch']}", "phase": "total", "ms": r["ms"], "std": r["std"], "edges": g.n, "triangles": None, "value": float(r["optimal"])} for r in grid]


def oversized(g: Graph) -> list[dict]:
    """Sorting everything before backward rows go, and after; value is the rows that entered the sort, counted while it ran. Further records give the bytes shuffled and spilled and the most memory of one operator."""
    out = []
    for plan in ("sort_first", "filter_first"):
        costs = plan_costs(prep.preprocess(g.edges, plan))
        timed_run = g.record("big", plan, lambda plan=plan: prep.preprocess(g.edges, plan), "prepare", float(costs["sorted_rows"]))
        out += [timed_run, *[timed_run | {"phase": name, "ms": None, "std": None, "value": float(costs[name])} for name in ("shuffle_bytes", "spill_bytes", "peak_bytes")]]
    return out


def without_gain(g: Graph) -> list[dict]:
    """Variants that brought nothing, beside the default."""
    variants = {"array_intersect": count.forward_lists, "several rows an edge": count.forward_exploded, "gallop": lambda e: count.forward_lists(e, kernel="gallop"), "salted": count.forward_salted}
    return [g.record("fail", k, lambda f=f: f(g.edges)) for k, f in variants.items()]


def devices(g: Graph, sizes: Iterable[int] = (1, 2, 4)) -> list[dict]:
    """Lists prepared once and kept, then counted by devices of equally many cores, one slice each; value is the speedup of preparation and counting over one device, of preparation its share with one device.

    Further records give the ceiling which that share allows, and the serial share that would explain the speedup of the most devices.
    """
    sizes = list(sizes)
    each = max(1, split.cores_of(g.edges.sparkSession) // max(sizes))
    before = g.record("multi", "preparation", lambda: prep.out_lists(prep.orient(g.edges)), "prepare")
    ready = split.Prepared(g.edges, each)
    runs = [(k, g.record("multi", f"{k} devices", lambda k=k: ready.count(k), "count")) for k in sizes]
    ready.drop()
    whole = {k: before["ms"] + r["ms"] for k, r in runs}
    share = before["ms"] / whole[sizes[0]]
    out = [before | {"value": share}]
    for k, r in runs:
        ceiling = {"variant": f"ceiling of {k} devices", "ms": None, "std": None, "value": amdahl(share, k)}
        out += [r | {"value": whole[sizes[0]] / whole[k]}, r | ceiling]
    k = sizes[-1]
    return [*out, before | {"variant": "serial share that explains the speedup", "ms": None, "std": None, "value": amdahl_share(whole[sizes[0]] / whole[k], k) if k > 1 else None}]


def vertex_order(g: Graph) -> list[dict]:
    """What ordering vertices by degree buys; value is the number of oriented wedges."""
    wedges = {r["order"]: float(r.wedges) for r in measures.order_ablation(g.edges).collect()}
    return [g.record("order", o, lambda o=o: count.forward_lists(g.edges, order=o), value=w) for o, w in wedges.items()]


def subgraphs(g: Graph, classes: Iterable[int] = (2, 3, 4, 6)) -> list[dict]:
    """Independent subgraphs; value is copies of edges for each edge."""
    out = []
    for rho in classes:
        copies = split.partition_costs(g.edges, rho).first().copies
        out.append(g.record("split", f"{rho} classes", lambda rho=rho: split.count_partitioned(g.edges, rho), value=copies / max(g.n, 1)))
    return out


def hub_block(g: Graph, sizes: Iterable[int] = (16, 64, 256)) -> list[dict]:
    """The highest degrees counted as a dense matrix, the rest by lists; value is the size of the block."""
    return [g.record("hub", f"{h} hubs", lambda h=h: count.hub_hybrid(g.edges, h), value=float(h)) for h in sizes]


#: Studies of one graph.
STUDIES = {
    "all": every_method, "input": input_format, "unzip": record_columns, "sort": sort_keys, "read": list_reads, "cache": list_cache, "warp": work_unit, "big": oversized,
    "fail": without_gain, "grid": launch_grid, "multi": devices, "order": vertex_order, "split": subgraphs, "hub": hub_block,
}


def kronecker(spark: SparkSession, scales: Iterable[int] = range(8, 14), reps: int = 5) -> list[dict]:
    """The scaling curve: preparation and the whole count over graphs that double; value is steps at most."""
    out = []
    for s in scales:
        g = Graph(f"rmat_{s}", gen.rmat(spark, s), reps)
        steps = float(measures.work_bound(g.edges).first().forward or 0)
        out += [g.record("kron", "forward", lambda g=g: count.forward_grouped(g.edges), value=steps), g.record("kron", "orient", lambda g=g: prep.orient(g.edges), "prepare", steps)]
        g.edges.unpersist()
    return out


def proportional(spark: SparkSession, runs: list[dict]) -> DataFrame:
    """(predictor, slope, r2): what the time that is left after preparation follows over the runs of the scaling curve."""
    before = {r["graph"]: r["ms"] for r in runs if r["phase"] == "prepare"}
    rows = [(r["ms"] - before[r["graph"]], float(r["edges"]), float(r["triangles"]), r["value"]) for r in runs if r["phase"] == "total"]
    return proportionality(spark.createDataFrame(rows, "ms double, edges double, triangles double, steps double"))


def run_records(spark: SparkSession, runs: list[dict]) -> DataFrame:
    names = [c.split()[0] for c in SCHEMA.split(", ")]
    return spark.createDataFrame([tuple(r[n] for n in names) for r in runs], SCHEMA)


def main(folder: str, *wanted: str) -> None:
    spark = SparkSession.builder.appName("studies").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    for name in wanted or ("kron", *STUDIES):
        if name == "kron":
            runs = kronecker(spark)
            print(json.dumps({"study": "proportion", "fits": [r.asDict() for r in proportional(spark, runs).collect()]}))
        else:
            runs = []
            generated = {"rmat_14": lambda: gen.rmat(spark, 14), "preferential": lambda: gen.preferential(spark, 20_000, 10), "small_world": lambda: gen.small_world(spark, 20_000, 50, 0.1)}
            for graph in (*STAND_INS, *generated) if name == "all" else ("copurchase",):
                g = Graph(graph, generated[graph]() if graph in generated else load_graph(spark, folder, graph))
                runs += STUDIES[name](g)
                g.edges.unpersist()
        for r in runs:
            print(json.dumps(r), flush=True)


if __name__ == "__main__":
    main(*sys.argv[1:])
