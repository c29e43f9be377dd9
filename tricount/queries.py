"""Every method, measure and workload on the given tables, each with the DuckDB SQL it must agree with."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tricount.functions import measures
from tricount.functions.lineage import once
from tricount.operators import count, listing, prep, split
from tricount.plans import planner
from tricount.sources import generators as gen
from tricount.sources.loaders import GRAPHS, coactive_triangles, copurchase, edges_from_projection, load_graph, table
from tricount.sources.rmat_source import drawn_for
from tricount.streaming import streams

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def add(name: str, query: Query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        SQL[name] = sql


def _shared(group: str, member: str, source: str = "lineitem") -> str:
    return f"SELECT DISTINCT a.{member} AS u, b.{member} AS v FROM {source} a JOIN {source} b USING ({group}) WHERE a.{member} < b.{member}"


def _pairs(select: str) -> str:
    """Unique unordered pairs of a query with the columns a and b."""
    return f"SELECT DISTINCT least(a, b) AS u, greatest(a, b) AS v FROM ({select}) WHERE a <> b"


EDGES = {
    "copurchase": _shared("l_orderkey", "l_partkey"),
    "cosupply_order": _shared("l_orderkey", "l_suppkey"),
    "cosupply_part": _shared("l_partkey", "l_suppkey"),
    "tripartite": _pairs(
        "SELECT unnest([3 * o_custkey, 3 * o_custkey, 3 * l_partkey + 1]) AS a, unnest([3 * l_partkey + 1, 3 * l_suppkey + 2, 3 * l_suppkey + 2]) AS b FROM lineitem JOIN orders ON l_orderkey = o_orderkey"
    ),
    "order_part": _pairs("SELECT 2 * l_orderkey AS a, 2 * l_partkey + 1 AS b FROM lineitem"),
    "coactive": _shared("event_type, hour", "user_id", "(SELECT DISTINCT event_type, date_trunc('hour', ts) AS hour, user_id FROM events)"),
    "nextactor": _pairs("SELECT user_id AS a, lead(user_id) OVER (ORDER BY ts, event_id) AS b FROM events"),
    "knn": _pairs(
        """SELECT a, b FROM (SELECT x.vec_id AS a, y.vec_id AS b, row_number() OVER (PARTITION BY x.vec_id ORDER BY list_inner_product(x.q, y.q) DESC, y.vec_id) AS r
        FROM (SELECT vec_id, list_transform(embedding, lambda e: floor(e::DOUBLE * 1048576)) AS q FROM embeddings) x
        JOIN (SELECT vec_id, list_transform(embedding, lambda e: floor(e::DOUBLE * 1048576)) AS q FROM embeddings) y ON x.vec_id <> y.vec_id) WHERE r <= 10"""
    ),
    "bigram": """SELECT least(x.id, y.id) AS u, greatest(x.id, y.id) AS v FROM (
        SELECT DISTINCT least(a, b) AS a, greatest(a, b) AS b FROM (
          SELECT unnest(w[1:len(w) - 1]) AS a, unnest(w[2:]) AS b FROM (SELECT regexp_extract_all(lower(text), '[a-z]+') AS w FROM documents) WHERE len(w) > 1) WHERE a <> b) p
        JOIN names x ON x.word = p.a JOIN names y ON y.word = p.b""",
    "nation_trade": _pairs("SELECT c_nationkey AS a, s_nationkey AS b FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey"),
    "bench_leak": """SELECT DISTINCT least(2 * d.key, 2 * b.key + 1) AS u, greatest(2 * d.key, 2 * b.key + 1) AS v FROM
        (SELECT DISTINCT key, array_to_string(w[i:i + 7], ' ') AS run FROM (SELECT key, w, unnest(range(1, len(w) - 6)) AS i FROM (SELECT doc_id AS key, regexp_extract_all(lower(text), '[a-z]+') AS w FROM documents) WHERE len(w) >= 8)) d JOIN
        (SELECT DISTINCT key, array_to_string(w[i:i + 7], ' ') AS run FROM (SELECT key, w, unnest(range(1, len(w) - 6)) AS i FROM (SELECT item_id AS key, regexp_extract_all(lower(text), '[a-z]+') AS w FROM benchmark) WHERE len(w) >= 8)) b USING (run)""",
    "pagelink": _shared("target", "page_id", "(SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href=\"(/[^\"/]*)\"', 1)) AS target FROM pages)"),
}
_NAMES = """names AS (SELECT word, row_number() OVER (ORDER BY word) - 1 AS id FROM (SELECT DISTINCT unnest([a, b]) AS word FROM (
    SELECT unnest(w[1:len(w) - 1]) AS a, unnest(w[2:]) AS b FROM (SELECT regexp_extract_all(lower(text), '[a-z]+') AS w FROM documents) WHERE len(w) > 1) WHERE a <> b)),"""


def _draw(*parts: str) -> str:
    text = " || '|' || ".join(f"({p})::VARCHAR" for p in parts)
    return f"('0x' || substr(md5({text}), 1, 8))::BIGINT"


def _rmat(scale: int, factor: int = 16, counter: str = "i", source: str | None = None) -> str:
    bits = ", ".join(f"(({_draw(counter, str(k), '42')} * 100) >> 32) AS r{k}" for k in range(scale))
    src = " + ".join(f"CASE WHEN r{k} >= 76 THEN {1 << k} ELSE 0 END" for k in range(scale))
    dst = " + ".join(f"CASE WHEN (r{k} >= 57 AND r{k} < 76) OR r{k} >= 95 THEN {1 << k} ELSE 0 END" for k in range(scale))
    return _pairs(f"SELECT ({src})::BIGINT AS a, ({dst})::BIGINT AS b FROM (SELECT {bits} FROM {source or f'range({factor << scale}) t(i)'})")


def _small_world(n: int | str, k: int, percent: int) -> str:
    links = f"SELECT i, j, CASE WHEN (({_draw('i', 'j', chr(39) + 'a' + chr(39), '42')} * 100) >> 32) < {percent} THEN {_draw('i', 'j', chr(39) + 'b' + chr(39), '42')} % {n} ELSE (i + j) % {n} END AS t FROM range({n}) x(i), range(1, {k // 2 + 1}) y(j)"
    return _pairs(f"SELECT i::BIGINT AS a, t::BIGINT AS b FROM ({links})")


def _preferential(n: int | str, k: int) -> str:
    c = k * (k + 1) // 2
    return f"""WITH RECURSIVE core AS (SELECT (row_number() OVER (ORDER BY a, b) - 1)::BIGINT AS edge, a::BIGINT AS src, b::BIGINT AS dst FROM range(1, {k + 1}) x(a), range({k}) y(b) WHERE b < a),
    fresh AS (SELECT ({c} + i)::BIGINT AS edge, ({k + 1} + i // {k})::BIGINT AS src, ({_draw('i', '42')} % (2 * ({c} + i // {k} * {k})))::BIGINT AS slot FROM range(({n} - {k + 1}) * {k}) t(i)),
    source AS (SELECT edge, src FROM core UNION ALL SELECT edge, src FROM fresh),
    walk AS (SELECT edge, slot FROM fresh UNION ALL SELECT w.edge, f.slot FROM walk w JOIN fresh f ON f.edge = w.slot // 2 WHERE w.slot % 2 = 1),
    hit AS (SELECT w.edge, s.src AS dst FROM walk w JOIN source s ON s.edge = w.slot // 2 WHERE w.slot % 2 = 0 UNION ALL SELECT w.edge, c.dst FROM walk w JOIN core c ON c.edge = w.slot // 2 WHERE w.slot % 2 = 1),
    every AS (SELECT src, dst FROM core UNION ALL SELECT f.src, h.dst FROM fresh f JOIN hit h USING (edge))
    SELECT DISTINCT least(src, dst) AS u, greatest(src, dst) AS v FROM every WHERE src <> dst"""


def on(graph: str, body: str, more: str = "") -> str:
    """SQL over CTEs: e (edges), g (edge array), d (degrees), o (oriented edges)."""
    edges = EDGES.get(graph, graph)
    return f"""WITH {_NAMES if graph == "bigram" else ""} e AS ({edges}), g AS (SELECT u AS src, v AS dst FROM e UNION ALL SELECT v, u FROM e),
    d AS (SELECT src AS v, count(*) AS deg FROM g GROUP BY src),
    o AS (SELECT CASE WHEN (x.deg, e.u) < (y.deg, e.v) THEN e.u ELSE e.v END AS src, CASE WHEN (x.deg, e.u) < (y.deg, e.v) THEN e.v ELSE e.u END AS dst FROM e JOIN d x ON x.v = e.u JOIN d y ON y.v = e.v),
    t AS (SELECT x.src AS a, x.dst AS b, y.dst AS c FROM o x JOIN o y ON y.src = x.dst JOIN o z ON z.src = x.src AND z.dst = y.dst){more} {body}"""


TOTAL = "SELECT count(*) AS triangles FROM t"


def _on(graph: str, f: Callable[[DataFrame], DataFrame]) -> Query:
    return lambda s, d: f(load_graph(s, d, graph))


MAIN = "copurchase"
SMALL = "nextactor"

# Loaders and counts of all graphs.
for _g in GRAPHS:
    add(f"edges_{_g}", partial(load_graph, name=_g), on(_g, "SELECT u, v FROM e"))
    add(f"tri_{_g}", coactive_triangles if _g == "coactive" else _on(_g, count.triangle_total), on(_g, TOTAL))

# Preparation.
_BROKEN = "SELECT l_partkey AS src, l_suppkey AS dst FROM lineitem"
add(
    "validate_edges", lambda s, d: prep.validate_edges(table(s, d, "lineitem").select(F.col("l_partkey").alias("src"), F.col("l_suppkey").alias("dst"))),
    f"""WITH p AS ({_BROKEN}), c AS (SELECT src, dst, count(*) AS n FROM p GROUP BY ALL)
    SELECT (SELECT count(*) FROM p WHERE src IS NULL OR dst IS NULL) AS nulls, coalesce((SELECT sum(n) FROM c WHERE src = dst), 0)::BIGINT AS loops,
    coalesce((SELECT sum(n - 1) FROM c), 0)::BIGINT AS repeats, (SELECT count(*) FROM c WHERE src <> dst AND NOT EXISTS (SELECT 1 FROM c r WHERE r.src = c.dst AND r.dst = c.src)) AS one_way""",
)
add("canonical_edges", lambda s, d: prep.canonical_edges(table(s, d, "lineitem"), "l_partkey", "l_suppkey"), _pairs("SELECT l_partkey AS a, l_suppkey AS b FROM lineitem"))
for _mode, _sql in (("max_id", "SELECT max(v) + 1 AS n FROM e"), ("distinct", "SELECT count(*) AS n FROM d")):
    add(f"vertex_count_{_mode.removesuffix('_id')}", _on(MAIN, partial(prep.vertex_count, mode=_mode)), on(MAIN, _sql))
add("degrees", _on(MAIN, prep.degrees), on(MAIN, "SELECT v, deg FROM d"))
_NODE = "SELECT v, (sum(deg) OVER (ORDER BY v) - deg)::BIGINT AS \"offset\", deg FROM d"
add("node_array", _on(MAIN, lambda e: prep.node_array(prep.edge_array(e))), on(MAIN, _NODE))
add("degrees_from_node", _on(MAIN, lambda e: prep.degrees_from_node(prep.node_array(prep.edge_array(e)))), on(MAIN, "SELECT v, deg FROM d"))
_FILL = """SELECT i AS v, (sum(n) OVER (ORDER BY i) - n)::BIGINT AS "offset", n AS deg FROM (SELECT i, count(o.src) AS n FROM range((SELECT max(greatest(src, dst)) + 1 FROM o)) r(i) LEFT JOIN o ON o.src = i GROUP BY i)"""
add("node_array_oriented", _on(MAIN, lambda e: prep.node_array(prep.orient(e), fill_isolated=True)), on(MAIN, _FILL))
add("backward_marks", _on(MAIN, prep.mark_backward), on(MAIN, "SELECT g.src, g.dst, (x.deg, g.src) > (y.deg, g.dst) AS backward FROM g JOIN d x ON x.v = g.src JOIN d y ON y.v = g.dst"))
for _name, _plan in (("oriented_edges", "sort_first"), ("oriented_edges_filter_first", "filter_first")):
    add(_name, _on(MAIN, partial(prep.preprocess, plan=_plan)), on(MAIN, "SELECT src, dst FROM o"))
add("sorted_rows", _on(MAIN, planner.sorted_rows), on(MAIN, "SELECT 'sort_first' AS plan, count(*) AS rows FROM g UNION ALL SELECT 'filter_first', count(*) FROM o"))
_packed = lambda e, layout: prep.orient(e).select(prep.pack_edge(F.col("src"), F.col("dst"), layout).alias("key"))
add("packed_keys", _on(MAIN, partial(_packed, layout="src_major")), on(MAIN, "SELECT (src << 32) | dst AS key FROM o"))
add("packed_keys_mirrored", _on(MAIN, partial(_packed, layout="dst_major")), on(MAIN, "SELECT (dst << 32) | src AS key FROM o"))
add("sorted_packed", _on(MAIN, lambda e: prep.sort_edges(prep.orient(e), key="packed")), on(MAIN, "SELECT src, dst FROM o"))
add("unzip_roundtrip", _on(MAIN, lambda e: prep.unzip(prep.zip_records(prep.orient(e)))), on(MAIN, "SELECT src, dst FROM o"))
add("out_lists_len", _on(MAIN, lambda e: prep.out_lists(prep.orient(e)).select("v", F.size("nbrs").cast("long").alias("n"))), on(MAIN, "SELECT src AS v, count(*) AS n FROM o GROUP BY src"))
add("adjacency_roundtrip", _on(MAIN, lambda e: prep.to_edge_array(prep.to_adjacency(prep.edge_array(e)))), on(MAIN, "SELECT src, dst FROM g"))
_WORDS = "SELECT DISTINCT unnest(regexp_extract_all(lower(text), '[a-z]+')) AS key FROM documents"
add(
    "dense_ids", lambda s, d: prep.dense_ids(table(s, d, "documents").select(F.explode(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0))).alias("w")), "w"),
    f"SELECT key, row_number() OVER (ORDER BY key) - 1 AS id FROM ({_WORDS})",
)
add("prefix_sum", _on(MAIN, lambda e: prep.prefix_sum(prep.degrees(e), "v", "deg")), on(MAIN, "SELECT v, deg, (sum(deg) OVER (ORDER BY v))::BIGINT AS running, (sum(deg) OVER (ORDER BY v) - deg)::BIGINT AS before FROM d"))

# Every method on one graph.
_METHODS: dict[str, Callable[[DataFrame], DataFrame]] = {
    "lists": count.forward_lists, "lists_src_first": partial(count.forward_lists, first="src"), "grouped": count.forward_grouped, "merge": partial(count.forward_lists, kernel="merge"),
    "merge_eager": partial(count.forward_lists, kernel="merge_eager"), "gallop": partial(count.forward_lists, kernel="gallop"), "sorted_run": partial(count.forward_lists, kernel="sorted_run"), "hubs_split": partial(count.forward_grouped, split_over=50), "salted_hubs_split": partial(count.forward_salted, salt_over=8, split_over=50), "bitmap": count.forward_bitmap, "exploded": count.forward_exploded,
    "paths": count.forward_paths, "wedges": count.forward_wedges, "edge_iterator": count.edge_iterator, "node_iterator": count.node_iterator, "brute": count.brute_force, "matrix": count.matrix,
    "hub_hybrid": count.hub_hybrid, "hub_degree": partial(count.hub_hybrid, degree_over=20), "salted": partial(count.forward_salted, salt_over=8), "partition_multiset": partial(split.count_partitioned, rho=4), "partition_weighted": partial(split.count_partitioned, rho=4, variant="weighted"),
    "replicated": lambda e: split.count_replicated(e, 4).agg(F.sum("triangles").alias("triangles")), "local": count.forward_local, "local_lists": lambda e: count.forward_local_lists(prep.to_adjacency(prep.edge_array(e))), "auto": partial(count.triangle_total, method="auto"),
    "adjacency_input": lambda e: count.adjacency_input(prep.to_adjacency(prep.edge_array(e))), "forward_dynamic": count.forward_dynamic,
    "id_order": partial(count.forward_grouped, order="id"), "random_order": partial(count.forward_grouped, order="random"),
}
for _name, _f in _METHODS.items():
    add(f"tri_{_name}", _on(MAIN, _f), on(MAIN, TOTAL))
add("tri_degeneracy", _on(SMALL, lambda e: count.forward_grouped(e, order="degeneracy")), on(SMALL, TOTAL))

# Generated graphs, drawn from the rows and keys of the given tables.
_KEY = "l_orderkey::VARCHAR || '-' || l_linenumber::VARCHAR"
for _scale in (8, 10, 12):
    add(f"tri_rmat_{_scale}", lambda s, d, k=_scale: count.forward_grouped(gen.rmat_from(table(s, d, "lineitem"), ["l_orderkey", "l_linenumber"], k)), on(_rmat(_scale, counter=_KEY, source="lineitem"), TOTAL))
add("edges_rmat_lineitem", lambda s, d: gen.rmat_from(table(s, d, "lineitem"), ["l_orderkey", "l_linenumber"], 10), _rmat(10, counter=_KEY, source="lineitem"))
_customers = lambda s, d: prep.dense_ids(table(s, d, "customer"), "c_custkey").select("id")
_COUNT = "(SELECT count(DISTINCT c_custkey) FROM customer)"
add("tri_ba", lambda s, d: count.forward_grouped(gen.preferential_of(_customers(s, d), 5)), on(_preferential(_COUNT, 5), TOTAL))
add("edges_rmat_source", lambda s, d: prep.canonical_edges(drawn_for(table(s, d, "orders").select("o_orderkey"), 8)), _rmat(8, counter="o_orderkey", source="orders"))


def _ring(s: SparkSession, d: str, beta: float) -> DataFrame:
    """Triangles of the small world of all customers in the order of their keys."""
    ids = _customers(s, d)
    return count.forward_grouped(gen.small_world_of(ids, ids.count(), 20, beta))


add("tri_ws0", partial(_ring, beta=0), on(_small_world(_COUNT, 20, 0), TOTAL))
add("tri_ws10", partial(_ring, beta=0.1), on(_small_world(_COUNT, 20, 10), TOTAL))
_lines_of = lambda s, d, column: table(s, d, "lineitem").select(F.col(column).cast("long"))
_OF = "(SELECT count(DISTINCT {0}::BIGINT) AS n FROM lineitem)"
add("tri_kron_power", lambda s, d: count.forward_grouped(gen.kron_power(gen.complete_graph(_lines_of(s, d, "l_linenumber")), 8, 3)), f"SELECT ((n * (n - 1) * (n - 2)) ** 3 / 6)::BIGINT AS triangles FROM {_OF.format('l_linenumber')}")
add("tri_clique", lambda s, d: count.forward_grouped(gen.complete_graph(_lines_of(s, d, "l_quantity"))), f"SELECT (n * (n - 1) * (n - 2) // 6)::BIGINT AS triangles FROM {_OF.format('l_quantity')}")
add("tri_bipartite", lambda s, d: count.forward_grouped(gen.complete_bipartite(_lines_of(s, d, "l_quantity"), _lines_of(s, d, "l_linenumber"))),
    on(_pairs("SELECT 2 * q AS a, 2 * l + 1 AS b FROM (SELECT DISTINCT l_quantity::BIGINT AS q FROM lineitem) x, (SELECT DISTINCT l_linenumber::BIGINT AS l FROM lineitem) y"), TOTAL))

# Workers and devices.
_NUMBERED = "row_number() OVER (ORDER BY o.src, o.dst) - 1"
add(
    "worker_counts_strided", _on(MAIN, partial(split.count_by_worker, workers=4)),
    on(MAIN, f"SELECT (n % 4)::INT AS worker, count(*) AS edges, sum(k)::BIGINT AS triangles FROM (SELECT {_NUMBERED} AS n, (SELECT count(*) FROM t WHERE t.a = o.src AND t.b = o.dst) AS k FROM o) GROUP BY 1"),
)
add(
    "device_slices_4", _on(MAIN, partial(split.count_replicated, devices=4, split="strided")),
    on(MAIN, f"SELECT (n % 4)::INT AS slice, count(*) AS edges, sum(k)::BIGINT AS triangles FROM (SELECT {_NUMBERED} AS n, src, dst, (SELECT count(*) FROM t WHERE t.a = o.src AND t.b = o.dst) AS k FROM o) GROUP BY 1"),
)

# Listing and support.
add("list_triangles", _on(SMALL, listing.list_triangles), on(SMALL, "SELECT a, b, c FROM t"))
_PER_V = "SELECT d.v, count(x.v) AS t FROM d LEFT JOIN (SELECT unnest([a, b, c]) AS v FROM t) x USING (v) GROUP BY d.v"
add("vertex_triangles", _on(MAIN, listing.vertex_triangles), on(MAIN, _PER_V))
_SIDES = "SELECT least(p, q) AS u, greatest(p, q) AS v FROM (SELECT unnest([a, a, b]) AS p, unnest([b, c, c]) AS q FROM t)"
_SUPPORT = f"SELECT e.u, e.v, count(x.u) AS support FROM e LEFT JOIN ({_SIDES}) x ON x.u = e.u AND x.v = e.v GROUP BY e.u, e.v"
add("edge_support", _on(MAIN, listing.edge_support), on(MAIN, _SUPPORT))
add("top_vertices", _on(MAIN, listing.top_vertices), on(MAIN, f"SELECT * FROM ({_PER_V}) ORDER BY t DESC, v LIMIT 10"))


def _truss(k: int, rounds: int) -> str:
    """Edges that are left after so many rounds of dropping those in fewer than k - 2 triangles."""
    steps = []
    for n in range(rounds):
        r = f"r{n}" if n else "e"
        steps.append(f"""r{n + 1} AS MATERIALIZED (SELECT e.u, e.v FROM {r} e JOIN (SELECT unnest([x.u, x.u, y.u]) AS u, unnest([x.v, y.v, y.v]) AS v FROM {r} x JOIN {r} y ON y.u = x.v JOIN {r} z ON z.u = x.u AND z.v = y.v) s
        ON (s.u = e.u AND s.v = e.v) GROUP BY e.u, e.v HAVING count(*) >= {k - 2})""")
    return ", " + ", ".join(steps)


_TRUSS_ROUNDS = 30  # enough at sf0.001 and sf0.01, where results were compared
add("truss_4", _on(SMALL, lambda e: listing.truss(e, 4)), on(SMALL, f"SELECT u, v FROM r{_TRUSS_ROUNDS}", _truss(4, _TRUSS_ROUNDS).replace("[x.u, x.u, y.u]", "[x.u, z.u, y.u]").replace("[x.v, y.v, y.v]", "[x.v, z.v, y.v]")))
add("vertices_without_triangle", _on("order_part", listing.vertices_without_triangle), on("order_part", "SELECT v FROM d WHERE v NOT IN (SELECT unnest([a, b, c]) FROM t)"))

# Measures.
_W = "(SELECT sum(deg * (deg - 1) // 2) FROM d)"
_TRANS = f"SELECT count(*) AS triangles, {_W}::BIGINT AS wedges, round(3.0::DOUBLE * count(*) / {_W}::DOUBLE, 6) AS transitivity FROM t"
add("transitivity", _on(MAIN, measures.transitivity), on(MAIN, _TRANS))
_LOCAL = f"SELECT v, deg AS d, t, CASE WHEN deg > 1 THEN round(2.0::DOUBLE * t / (deg::DOUBLE * (deg - 1)), 6) ELSE 0 END AS c FROM d JOIN ({_PER_V}) USING (v)"
add("local_clustering", _on(MAIN, measures.local_clustering), on(MAIN, _LOCAL))
add("average_clustering", _on(MAIN, measures.average_clustering), on(MAIN, f"SELECT count(*) AS n, round(avg(c), 6) AS clustering FROM ({_LOCAL})"))
add("clustering_by_degree", _on(MAIN, measures.clustering_by_degree), on(MAIN, f"SELECT (length(bin(d)) - 1)::INT AS log_degree, count(*) AS n, round(avg(c), 5) AS clustering FROM ({_LOCAL}) GROUP BY 1"))
_OUT = "(SELECT sum(n * (n - 1) // 2)::BIGINT FROM (SELECT count(*) AS n FROM {0} GROUP BY {1}))"
add("wedge_counts", _on("bigram", measures.wedge_counts), on("bigram", f"SELECT {_W}::BIGINT AS unoriented, {_OUT.format('e', 'u')} AS by_id, {_OUT.format('o', 'src')} AS by_degree"))
add("degree_stats", _on(MAIN, measures.degree_stats), on(MAIN, "SELECT count(*) AS n, max(deg) AS max_deg, round(avg(deg), 6) AS mean_deg, round(stddev_pop(deg), 6) AS std_deg FROM d"))
add("list_bound", _on("bigram", measures.list_bound), on("bigram", "SELECT max(n) AS max_out, (2 * sum(n))::BIGINT AS rows, max(n) * max(n) <= 2 * sum(n) AS ok FROM (SELECT count(*) AS n FROM o GROUP BY src)"))
_LEN = ", n AS (SELECT src, count(*) AS n FROM o GROUP BY src)"
add(
    "work_bound", _on(MAIN, measures.work_bound),
    on(MAIN, "SELECT (SELECT sum(x.n + coalesce(y.n, 0))::BIGINT FROM o JOIN n x ON x.src = o.src LEFT JOIN n y ON y.src = o.dst) AS forward, (SELECT sum(deg * deg)::BIGINT FROM d) AS edge_iterator", _LEN),
)
_HASH = _draw("v").replace("(v)::VARCHAR", "v::VARCHAR")
_RANDOM = f"SELECT CASE WHEN (x.h, e.u) < (y.h, e.v) THEN e.u ELSE e.v END AS src FROM e JOIN (SELECT v, {_HASH} AS h FROM d) x ON x.v = e.u JOIN (SELECT v, {_HASH} AS h FROM d) y ON y.v = e.v"
add(
    "order_ablation", _on(MAIN, measures.order_ablation),
    on(MAIN, " UNION ALL ".join(f"SELECT '{k}' AS \"order\", sum(n * (n - 1) // 2)::BIGINT AS wedges, max(n) AS max_out FROM (SELECT count(*) AS n FROM {q} GROUP BY {c})" for k, q, c in (("degree", "o", "src"), ("id", "e", "u"), ("random", f"({_RANDOM})", "src")))),
)
_MERGE = """, p AS (SELECT o.src, o.dst, least((SELECT max(dst) FROM o x WHERE x.src = o.src), (SELECT max(dst) FROM o x WHERE x.src = o.dst)) AS stop FROM o WHERE o.dst IN (SELECT src FROM o)),
    q AS (SELECT p.src, p.dst, (SELECT count(*) FROM o x WHERE x.src = p.src AND x.dst <= stop) AS ua, (SELECT count(*) FROM o x WHERE x.src = p.dst AND x.dst <= stop) AS ub,
    (SELECT count(*) FROM o x WHERE x.src = p.src) AS na, (SELECT count(*) FROM o x WHERE x.src = p.dst) AS nb FROM p)"""
_READS = """SELECT (SELECT count(*) FROM t) AS triangles, (sum(ua + ub) - (SELECT count(*) FROM t))::BIGINT AS steps, sum(ua + ub + (na > ua)::INT + (nb > ub)::INT)::BIGINT AS lazy_reads,
    (2 * (sum(ua + ub) - (SELECT count(*) FROM t)))::BIGINT AS eager_reads FROM q"""
add("read_counters", _on(SMALL, measures.read_counters), on(SMALL, _READS, _MERGE))
add(
    "list_reuse", _on(MAIN, measures.list_reuse),
    on(MAIN, """SELECT 2 * count(*) AS fetches, (SELECT count(*) FROM n) AS lists, round((2 * count(*))::DOUBLE / (SELECT count(*) FROM n), 6) AS reuse, (8 * coalesce(sum(x.n + y.n), 0))::BIGINT AS bytes
    FROM o JOIN n x ON x.v = o.src JOIN n y ON y.v = o.dst""", ", n AS (SELECT src AS v, count(*) AS n FROM o GROUP BY src)"),
)
add(
    "travel_sums", _on("bigram", lambda e: measures.travel_sums(prep.orient(e))),
    on("bigram", "SELECT sum(x.n)::BIGINT AS src_first, sum(coalesce(y.n, 0))::BIGINT AS dst_first FROM o JOIN n x ON x.src = o.src LEFT JOIN n y ON y.src = o.dst", _LEN),
)
_SUMMARY = "SELECT (SELECT count(*) FROM d) AS nodes, (SELECT count(*) FROM e) AS edges, 2 * (SELECT count(*) FROM e) AS edge_rows, (SELECT count(*) FROM t) AS triangles"
add("graph_summary", _on(MAIN, measures.graph_summary), on(MAIN, _SUMMARY))
add("triangle_edge_ratio", _on(MAIN, measures.triangle_edge_ratio), on(MAIN, "SELECT round((SELECT count(*) FROM t)::DOUBLE / (SELECT count(*) FROM e), 6) AS ratio"))
for _rho in (3, 6):
    for _variant in ("multiset", "weighted"):
        _c = f"(SELECT {_draw('u', '1')} % {_rho} AS cu, {_draw('v', '1')} % {_rho} AS cv FROM e)"
        _keys = {
            "multiset": f"SELECT list_sort([cu, cv, x]) AS key FROM {_c}, range({_rho}) r(x)",
            "weighted": f"SELECT [i, j, k] AS key FROM {_c}, range({_rho}) a(i), range({_rho}) b(j), range({_rho}) c(k) WHERE i > j AND j > k AND cu IN (i, j, k) AND cv IN (i, j, k)",
        }
        add(f"split_costs_{_variant}_{_rho}", _on(SMALL, partial(split.partition_costs, rho=_rho, variant=_variant)), on(SMALL, f"SELECT sum(n)::BIGINT AS copies, count(*) AS groups, max(n) AS largest FROM (SELECT count(*) AS n FROM ({_keys[_variant]}) GROUP BY key)"))

# Around the methods.
_types = lambda e: prep.degrees(e).select("v", F.element_at(F.array(F.lit("customer"), F.lit("part"), F.lit("supplier")), (F.col("v") % 3 + 1).cast("int")).alias("type"))
_TYPE = "['customer', 'part', 'supplier'][{0} % 3 + 1]"
_TYPED = f"SELECT k[1] AS ta, k[2] AS tb, k[3] AS tc, count(*) AS n FROM (SELECT list_sort([{', '.join(_TYPE.format(c) for c in 'abc')}]) AS k FROM t) GROUP BY ALL"
_typed = lambda e: listing.typed_triangles(e, _types(e))
add("typed_triangles", _on("tripartite", lambda e: _typed(once(e))), on("tripartite", _TYPED))


def _by_label(s: SparkSession, d: str, how: str) -> DataFrame:
    """Triangles of nearest vectors by whether all labels agree and by the lowest vertex's label, with subtotals."""
    labels = table(s, d, "embeddings").select(F.col("vec_id").alias("v"), "label")
    t = listing.list_triangles(load_graph(s, d, "knn"))
    for c in ("a", "b", "c"):
        t = t.join(labels.toDF(c, f"l{c}"), c)
    rows = t.select(F.expr("la = lb AND lb = lc").alias("same"), F.col("la").alias("label"))
    return getattr(rows, how)("same", "label").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().cast("long").alias("level"))


for _how in ("rollup", "cube"):
    add(
        f"typed_triangles_{_how}", partial(_by_label, how=_how),
        on("knn", f"SELECT same, label, count(*) AS n, grouping_id(same, label)::BIGINT AS level FROM (SELECT x.label = y.label AND y.label = z.label AS same, x.label FROM t JOIN embeddings x ON x.vec_id = a JOIN embeddings y ON y.vec_id = b JOIN embeddings z ON z.vec_id = c) GROUP BY {_how.upper()} (same, label)"),
    )


def _asof(s: SparkSession, d: str) -> DataFrame:
    """For every purchase event, the last other event type's event of its user before it: a union in time order, carried forward within the user."""
    e = table(s, d, "events").select("event_id", "user_id", "ts", "event_type")
    last = F.last(F.when(F.col("event_type") != "purchase", F.col("event_id")), ignorenulls=True).over(W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1))
    return e.withColumn("last_id", last).where("event_type = 'purchase'").select("event_id", "last_id")


add("asof_contact", _asof, "SELECT event_id, last_id FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type <> 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_id FROM events) WHERE event_type = 'purchase'")


def _interval(s: SparkSession, d: str) -> DataFrame:
    """Users with events of one type within 10 minutes: events fall into 10-minute cells, each looks into its own and the next cell, and the exact times decide."""
    e = table(s, d, "events").select("event_type", "ts", F.col("user_id").alias("x"), F.expr("unix_micros(CAST(ts AS TIMESTAMP)) DIV 600000000").alias("cell"))
    near = e.withColumn("cell", F.explode(F.array("cell", F.col("cell") + 1))).toDF("event_type", "t1", "a", "cell")
    met = near.join(e.toDF("event_type", "t2", "b", "cell"), ["event_type", "cell"]).where("t2 >= t1 AND t2 <= t1 + INTERVAL 10 MINUTES")
    return prep.canonical_edges(met, "a", "b")


add("coactive_interval", _interval, _pairs("SELECT x.user_id AS a, y.user_id AS b FROM events x JOIN events y ON x.event_type = y.event_type AND y.ts >= x.ts AND y.ts <= x.ts + INTERVAL 10 MINUTES"))
_HALF = "SELECT DISTINCT a.l_partkey AS u, b.l_partkey AS v FROM lineitem a JOIN lineitem b USING (l_orderkey) WHERE a.l_partkey < b.l_partkey AND {0} AND {1}"
_halves = lambda s, d: [copurchase(s, d, where=F.col("l_shipdate") < F.lit("1995-01-01")), copurchase(s, d, where=F.col("l_quantity") < 25)]
_H1 = _HALF.format("a.l_shipdate < '1995-01-01'", "b.l_shipdate < '1995-01-01'")
_H2 = _HALF.format("a.l_quantity < 25", "b.l_quantity < 25")
add("graph_intersect", lambda s, d: DataFrame.intersect(*_halves(s, d)), f"({_H1}) INTERSECT ({_H2})")
add("graph_except", lambda s, d: DataFrame.exceptAll(*_halves(s, d)), f"({_H1}) EXCEPT ({_H2})")


def _hub_rank(s: SparkSession, d: str) -> DataFrame:
    """Parts by degree within their brand: the three highest ranks."""
    deg = prep.degrees(copurchase(s, d)).join(table(s, d, "part").select(F.col("p_partkey").alias("v"), "p_brand"), "v")
    return deg.withColumn("rank", F.rank().over(W.partitionBy("p_brand").orderBy(F.desc("deg")))).where("rank <= 3")


add("hub_rank_window", _hub_rank, on(MAIN, "SELECT v, deg, p_brand, rank::INT AS rank FROM (SELECT v, deg, p_brand, rank() OVER (PARTITION BY p_brand ORDER BY deg DESC) AS rank FROM d JOIN part ON p_partkey = v) WHERE rank <= 3"))


def _json_edges(s: SparkSession, d: str) -> DataFrame:
    """Users whose events carry the same key in their JSON attributes on the same day."""
    e = table(s, d, "events").select(F.get_json_object("props", "$.k").cast("int").alias("k"), F.date_trunc("day", "ts").alias("day"), "user_id")
    return edges_from_projection(e, ["k", "day"], "user_id")


add("json_typed_edges", _json_edges, _shared("k, day", "user_id", "(SELECT DISTINCT (props->>'$.k')::INT AS k, date_trunc('day', ts) AS day, user_id FROM events)"))

# Streams, each against the same count over the whole table.
_CONTACTS = "SELECT event_id, event_type, ts, least(a, b) AS u, greatest(a, b) AS v FROM (SELECT event_id, event_type, ts, user_id AS a, (props->>'$.k')::BIGINT AS b FROM events) WHERE a <> b"


def _windows_sql(starts: str) -> str:
    return f"""WITH w AS (SELECT DISTINCT start, u, v FROM (SELECT {starts} AS start, u, v FROM ({_CONTACTS}))),
    t AS (SELECT x.start, count(*) AS n FROM w x JOIN w y ON y.start = x.start AND y.u = x.v JOIN w z ON z.start = x.start AND z.u = x.u AND z.v = y.v GROUP BY x.start)
    SELECT start, count(*) AS edges, coalesce(any_value(t.n), 0)::BIGINT AS triangles FROM w LEFT JOIN t USING (start) GROUP BY start"""


def _stream(run: Callable[[DataFrame, str], DataFrame], name: str, glob: str = "events.parquet") -> Query:
    def query(s: SparkSession, d: str) -> DataFrame:
        folder = streams.shared_folder(s, name)
        path = streams.growing_files(table(s, d, "events"), folder, 3)
        return run(streams.edge_stream(s, path, "*.parquet"), folder)

    return query


_QUARTERS = "time_bucket(INTERVAL 6 HOURS, ts) - to_hours(6 * unnest([0, 1, 2, 3]))"
add("stream_tumbling", _stream(lambda e, f: streams.stream_triangles(e, f, delay="60 days"), "tumbling"), _windows_sql("date_trunc('day', ts)::TIMESTAMP"))
add("stream_sliding", _stream(lambda e, f: streams.stream_triangles(e, f, "1 day", "6 hours", delay="60 days"), "sliding"), _windows_sql(_QUARTERS))
_SESSIONS = f"""WITH c AS ({_CONTACTS}), m AS (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY event_type ORDER BY ts) + INTERVAL 30 MINUTES THEN 0 ELSE 1 END AS new FROM c),
    n AS (SELECT *, sum(new) OVER (PARTITION BY event_type ORDER BY ts) AS s FROM m), i AS (SELECT *, min(ts) OVER (PARTITION BY event_type, s) AS start, max(ts) OVER (PARTITION BY event_type, s) AS stop FROM n),
    w AS (SELECT DISTINCT event_type, start, u, v FROM i WHERE stop + INTERVAL 30 MINUTES <= (SELECT max(ts) FROM c) - INTERVAL 1 HOUR),
    t AS (SELECT x.event_type, x.start, count(*) AS n FROM w x JOIN w y ON y.event_type = x.event_type AND y.start = x.start AND y.u = x.v JOIN w z ON z.event_type = x.event_type AND z.start = x.start AND z.u = x.u AND z.v = y.v GROUP BY ALL)
    SELECT event_type, start, count(*) AS edges, coalesce(any_value(t.n), 0)::BIGINT AS triangles FROM w LEFT JOIN t USING (event_type, start) GROUP BY event_type, start"""
add("stream_session", _stream(streams.stream_sessions, "session"), _SESSIONS)
_SIX = "time_bucket(INTERVAL 6 HOURS, ts)"
add("stream_closed_windows", _stream(streams.closed_windows, "closed"), f"SELECT * FROM ({_windows_sql(_SIX)}) WHERE start + INTERVAL 6 HOURS <= (SELECT max(ts) FROM ({_CONTACTS})) - INTERVAL 1 HOUR")
add(
    "stream_incremental", _stream(lambda e, f: streams.stream_incremental(e, f).agg(F.sum("new_triangles").alias("triangles")), "incremental"),
    f"WITH e AS (SELECT DISTINCT u, v FROM ({_CONTACTS})) SELECT count(*) AS triangles FROM e x JOIN e y ON y.u = x.v JOIN e z ON z.u = x.u AND z.v = y.v",
)


def _stateful(edges: DataFrame, folder: str) -> DataFrame:
    spark = edges.sparkSession
    streams.run_stream(streams.stateful_triangles(edges, memory=None), folder, lambda b, n: b.write.mode("overwrite").parquet(f"{folder}/state/batch={n}"), "update")
    seen = spark.read.parquet(f"{folder}/state")
    return seen.groupBy("event_type").agg(F.max("seen").alias("edges"), F.max_by("kept", "seen").alias("triangles"))


add(
    "stream_state", _stream(_stateful, "state"),
    f"""WITH e AS (SELECT DISTINCT event_type, u, v FROM ({_CONTACTS})), t AS (SELECT x.event_type, count(*) AS n FROM e x JOIN e y ON y.event_type = x.event_type AND y.u = x.v JOIN e z ON z.event_type = x.event_type AND z.u = x.u AND z.v = y.v GROUP BY 1)
    SELECT event_type, count(*) AS edges, coalesce(any_value(t.n), 0)::BIGINT AS triangles FROM e LEFT JOIN t USING (event_type) GROUP BY event_type""",
)


def _wedge_stream(edges: DataFrame, folder: str) -> DataFrame:
    streams.run_stream(streams.stream_wedges(edges, edges, delay="60 days"), folder, lambda b, n: b.write.mode("overwrite").parquet(f"{folder}/wedges/batch={n}"))
    found = edges.sparkSession.read.parquet(f"{folder}/wedges")
    return found.agg(F.count(F.lit(1)).alias("wedges"))


add("stream_wedges", _stream(_wedge_stream, "wedges"), f"WITH c AS ({_CONTACTS}) SELECT count(*) AS wedges FROM c x JOIN c y ON y.u = x.v AND y.ts >= x.ts AND y.ts <= x.ts + INTERVAL 1 HOUR")


def _late(s: SparkSession, d: str) -> DataFrame:
    """Rows dropped as late when the oldest events come last: counts of the stream's own report."""
    folder = streams.shared_folder(s, "late")
    events = table(s, d, "events")
    middle = events.approxQuantile("event_id", [0.5], 0.0)[0]
    for k, part in enumerate((events.where(F.col("event_id") >= middle), events.where(F.col("event_id") < middle))):
        part.coalesce(1).write.mode("append").parquet(f"{folder}/in{k}")
    out, dropped = 0, 0

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/rows/batch={number}")

    for k in (0, 1):
        for path in s.read.parquet(f"{folder}/in{k}").inputFiles():
            s.read.parquet(path).coalesce(1).write.mode("append").parquet(f"{folder}/all")
        query = streams.run_stream(streams.dedup_stream(streams.edge_stream(s, f"{folder}/all", "*.parquet"), "1 hour"), folder, keep)
        dropped += sum(n for _, n in streams.late_report(query))
    out = s.read.parquet(f"{folder}/rows").count()
    return s.createDataFrame([(out, dropped)], "kept long, dropped long")


add(
    "stream_late", _late,
    f"""WITH c AS ({_CONTACTS}), h AS (SELECT c.*, event_id >= (SELECT quantile_disc(event_id, 0.5) FROM events) AS first FROM c), w AS (SELECT max(ts) - INTERVAL 1 HOUR AS mark FROM h WHERE first)
    SELECT (SELECT count(DISTINCT (u, v)) FROM h WHERE first) AS kept, (SELECT count(*) FROM h, w WHERE NOT first AND ts <= mark) AS dropped""",
)


def _reservoir(s: SparkSession, d: str, memory: int = 500) -> DataFrame:
    """Edges seen and held by a state with room for fewer than there are; estimates are tested on their own, as SQL has no such sample."""
    folder = streams.shared_folder(s, "reservoir")
    edges = streams.contacts(table(s, d, "events")).select("event_type", "u", "v").distinct()
    edges.repartitionByRange(3, "u", "v").sortWithinPartitions("u", "v").write.parquet(f"{folder}/in")
    stream = s.readStream.schema(edges.schema).option("maxFilesPerTrigger", 1).parquet(f"{folder}/in")
    streams.run_stream(streams.stateful_triangles(stream, memory), folder, lambda b, n: b.write.mode("overwrite").parquet(f"{folder}/state/batch={n}"), "update")
    return s.read.parquet(f"{folder}/state").groupBy("event_type").agg(F.max("seen").alias("seen"), F.max("held").alias("held"))


add("stream_reservoir", _reservoir, f"SELECT event_type, count(*) AS seen, least(count(*), 500) AS held FROM (SELECT DISTINCT event_type, u, v FROM ({_CONTACTS})) GROUP BY 1")


def _sql_functions(s: SparkSession, d: str) -> DataFrame:
    """Neighbour pairs of vertices by the SQL function."""
    planner.sql_functions(s)
    prep.degrees(load_graph(s, d, SMALL)).createOrReplaceTempView("degrees_of_small")
    return s.sql("SELECT v, CAST(wedge_pairs(deg) AS BIGINT) AS wedges FROM degrees_of_small")


def _table_function(s: SparkSession, d: str) -> DataFrame:
    """Triangles by the table function, from both out-lists of every oriented edge."""
    planner.sql_functions(s)
    o = prep.orient(load_graph(s, d, SMALL))
    count.attach_lists(o, prep.out_lists(o)).createOrReplaceTempView("lists_of_small")
    return s.sql("SELECT src AS a, dst AS b, third AS c FROM lists_of_small, LATERAL triangles_at(nu, nv)")


add("sql_wedge_pairs", _sql_functions, on(SMALL, "SELECT v, (deg * (deg - 1) // 2)::BIGINT AS wedges FROM d"))
add("udtf_triangles", _table_function, on(SMALL, "SELECT a, b, c FROM t"))

# Samples.
_SIDES = "unnest([{'u': least(a, b), 'v': greatest(a, b)}, {'u': least(a, c), 'v': greatest(a, c)}, {'u': least(b, c), 'v': greatest(b, c)}]) AS side"


def _rated(method: str, share: int) -> str:
    """The estimate and its standard error, from kept and shared."""
    q, r = listing._chances(method, share)
    return f"round(kept * {1 / q!r}::DOUBLE, 6) AS estimate, round(sqrt(kept * {1 - q!r}::DOUBLE + shared * {2 * (1 - q / r)!r}::DOUBLE) * {1 / q!r}::DOUBLE, 6) AS std_error"


def _sampled(keep: str, method: str, share: int) -> str:
    """One sample's row: triangles of the edges that `keep` selects, and the pairs of them on one edge."""
    found = f"SELECT x.u AS a, x.v AS b, y.v AS c FROM ({keep}) x JOIN ({keep}) y ON y.u = x.v JOIN ({keep}) z ON z.u = x.u AND z.v = y.v"
    per_edge = f"SELECT count(*) AS s FROM (SELECT {_SIDES} FROM ({found})) GROUP BY side"
    return f"SELECT kept, shared, {_rated(method, share)} FROM (SELECT (coalesce(sum(s), 0) // 3)::BIGINT AS kept, coalesce(sum(s * (s - 1) // 2), 0)::BIGINT AS shared FROM ({per_edge}))"


def _seeds(drawn: str, method: str, share: int, seeds: int = 20) -> str:
    """A row for each seed: `drawn` says whether its sample has the edge (u, v)."""
    all_three = " AND ".join(drawn.format(u=f"least({x}, {y})", v=f"greatest({x}, {y})") for x, y in (("a", "b"), ("a", "c"), ("b", "c")))
    return f"""SELECT seed, kept, shared, estimate, std_error, round((estimate - total) / total, 6) AS rel_error, abs(estimate - total) <= 2 * std_error AS within FROM (
        SELECT seed, kept, shared, (SELECT count(*) FROM t) AS total, {_rated(method, share)} FROM (
            SELECT r.seed::INTEGER AS seed, (coalesce(sum(s), 0) // 3)::BIGINT AS kept, coalesce(sum(s * (s - 1) // 2), 0)::BIGINT AS shared FROM range(1, {seeds + 1}) r(seed) LEFT JOIN (
                SELECT seed, side, count(*) AS s FROM (SELECT seed, {_SIDES} FROM t, range(1, {seeds + 1}) q(seed) WHERE {all_three}) GROUP BY seed, side) k ON k.seed = r.seed GROUP BY r.seed))
        WHERE total > 0"""


_EDGE_SAMPLE = f"SELECT u, v FROM e WHERE {_draw('u', 'v', '1')} % 100 < 40"
_COLOUR_SAMPLE = f"SELECT u, v FROM e WHERE {_draw('u', '1')} % 3 = {_draw('v', '1')} % 3"
add("approx_edge_sample", _on(MAIN, lambda e: listing.approx_triangles(e, "edges", 40)), on(MAIN, _sampled(_EDGE_SAMPLE, "edges", 40)))
add("approx_colour", _on(MAIN, lambda e: listing.approx_triangles(e, "colours", 3)), on(MAIN, _sampled(_COLOUR_SAMPLE, "colours", 3)))
_WEDGE_SAMPLE = f"SELECT x.dst AS p, y.dst AS q FROM o x JOIN o y ON x.src = y.src AND x.dst < y.dst WHERE {_draw('x.src', 'x.dst', 'y.dst', '1')} % 100 < 30"
add("approx_wedge", _on(SMALL, lambda e: listing.approx_triangles(e, "wedges", 30)), on(SMALL, f"SELECT kept, shared, {_rated('wedges', 30)} FROM (SELECT count(*) AS kept, 0::BIGINT AS shared FROM ({_WEDGE_SAMPLE}) JOIN e ON e.u = p AND e.v = q)"))
add("approx_accuracy_edges", _on(SMALL, lambda e: listing.approx_accuracy(e, "edges", 40)), on(SMALL, _seeds(_draw("{u}", "{v}", "seed") + " % 100 < 40", "edges", 40)))
add("approx_accuracy_colours", _on(SMALL, lambda e: listing.approx_accuracy(e, "colours", 3)), on(SMALL, _seeds(_draw("{u}", "seed") + " % 3 = " + _draw("{v}", "seed") + " % 3", "colours", 3)))


def queries() -> dict[str, Query]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(SQL)


def entry(spark: SparkSession) -> DataFrame:
    """The flagship: nodes, edges and triangles of the co-purchase graph."""
    return measures.graph_summary(copurchase(spark, "/root/testdata/sf0.001"))

