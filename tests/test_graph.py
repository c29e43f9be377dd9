import itertools
import random
import re
import statistics
from math import comb
from pathlib import Path

import duckdb
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from pyspark.sql import functions as F

from tricount import queries as Q
from tricount.functions import kernels, measures
from tricount.operators import blocks, count, listing, prep, split
from tricount.plans import planner, studies
from tricount.sources import generators as gen
from tricount.sources import loaders
from tricount.sources.rmat_source import RmatSource, read_rmat
from tricount.sources.rmat_source import pairs as rmat_rows
from tricount.streaming import streams

SF = "/root/testdata/sf0.001"


def total(df):
    return df.first()[0]


def graph(spark, pairs):
    return prep.canonical_edges(spark.createDataFrame(pairs, "src long, dst long"))


def brute(pairs):
    edges = {(min(p), max(p)) for p in pairs if None not in p and p[0] != p[1]}
    near = {}
    for u, v in edges:
        near.setdefault(u, set()).add(v)
        near.setdefault(v, set()).add(u)
    return sum(len(near[u] & near[v]) for u, v in edges) // 3


@pytest.mark.parametrize(
    ("kind", "n", "m", "want"),
    [("complete", 9, 0, comb(9, 3)), ("cycle", 7, 0, 0), ("star", 9, 0, 0), ("path", 9, 0, 0), ("wheel", 6, 0, 6), ("bipartite", 5, 4, 0), ("cliques", 3, 5, 3 * comb(5, 3)), ("ring", 100, 10, 100 * 10 * 8 // 8), ("empty", 5, 0, 0)],
)
def test_closed_forms(spark, kind, n, m, want):
    assert total(count.forward_grouped(gen.fixture_graph(spark, kind, n, m))) == want


def test_all_methods_agree_and_ids_may_be_any(spark):
    rng = random.Random(4)
    pairs = [(rng.choice([-5, 0, 7, 2**40, *range(30)]), rng.randrange(30)) for _ in range(260)] + [(None, 3), (4, None), (6, 6)]
    e = graph(spark, pairs).persist()
    want = brute(pairs)
    for name, f in Q._METHODS.items():
        assert total(f(e)) == want, name
    for rho, variant in itertools.product((3, 5), ("multiset", "weighted")):
        assert total(split.count_partitioned(e, rho, variant)) == want
    for how in ("hash", "strided", "range"):
        rows = split.count_replicated(e, 3, how).collect()
        assert sum(r.triangles for r in rows) == want
        assert sum(r.triangles for r in split.count_replicated(e, 3, how, limit=0).collect()) == want
    assert sum(r.support for r in listing.edge_support(e).collect()) == 3 * want


def test_contract_checks_and_packing(spark):
    array = spark.createDataFrame([(1, 2), (2, 1), (1, 2), (3, 3), (4, 5), (None, 1)], "src long, dst long")
    assert prep.validate_edges(array).first().asDict() == {"nulls": 1, "loops": 1, "repeats": 1, "one_way": 1}
    with pytest.raises(ValueError):
        prep.canonical_edges(array, mode="strict")
    with pytest.raises(Exception, match="packed key"):
        prep.sort_edges(spark.createDataFrame([(1, 2**31)], "src long, dst long"), key="packed").collect()
    for layout in ("src_major", "dst_major"):
        rows = prep.sort_edges(spark.createDataFrame([(5, 1), (2, 9)], "src long, dst long"), "packed", layout).collect()
        assert sorted(map(tuple, rows)) == [(2, 9), (5, 1)]


def test_plans_give_the_same_rows_and_lists_stay_short(spark):
    e = gen.rmat(spark, 8).persist()
    assert sorted(prep.preprocess(e, "sort_first").collect()) == sorted(prep.preprocess(e, "filter_first").collect())
    assert total(count.forward_grouped(e)) == 10626
    assert measures.list_bound(e).first().ok
    r = measures.read_counters(e).first()
    assert r.lazy_reads <= r.eager_reads and r.steps <= measures.work_bound(e).first().forward


def test_hubs_are_split_and_the_default_plans(spark):
    star = [(0, k) for k in range(1, 3001)] + [(a, b) for a in range(3001, 3013) for b in range(3001, a)] + [(k, k + 1) for k in range(1, 3000, 2)]
    e = graph(spark, star).persist()
    want = brute(star)
    method, options = planner.choose(e, split_over=100)
    assert (method, options) == ("forward_grouped", {"split_over": 100}) and planner.plan_statistics(e)["max_in"] >= 1500
    split_up = count.forward_grouped(e, split_over=100)
    assert total(split_up) == total(count.triangle_total(e)) == total(count.forward_salted(e, 4, split_over=100)) == want
    plan = split_up._jdf.queryExecution().optimizedPlan().toString()
    assert "salt" in plan and "salt" not in count.forward_grouped(e)._jdf.queryExecution().optimizedPlan().toString()
    lists = prep.out_lists(prep.orient(e))
    rows = lists.select(studies.F.col("v").alias("src"), studies.F.explode("nbrs").alias("dst"))
    dealt = count.join_hubs(rows, lists.toDF("dst", "nv"), 100)
    assert dealt.groupBy("dst", "salt").count().agg({"count": "max"}).first()[0] <= 200
    assert planner.choose(e, salt_over=1)[0] == "forward_salted"


def test_sorting_first_sorts_both_directions(spark):
    e = gen.rmat(spark, 9).persist()
    n = e.count()
    assert {r.plan: r.rows for r in planner.sorted_rows(e).collect()} == {"sort_first": 2 * n, "filter_first": n}
    costs = planner.plan_costs(prep.preprocess(e, "sort_first"))
    assert costs["sorted_rows"] == 2 * n and costs["peak_bytes"] > 0


def test_subgraphs_fit_their_budget_and_devices_share_a_preparation(spark):
    e = gen.rmat(spark, 9).persist()
    want, n = total(count.forward_grouped(e)), e.count()
    for variant in ("multiset", "weighted"):
        assert total(split.count_partitioned(e, 3, variant, budget=n // 3)) == want
    with pytest.raises(ValueError, match="too many edges"):
        split.count_partitioned(gen.fixture_graph(spark, "star", 60), 3, budget=2)
    ready = split.Prepared(e, 2)
    for devices in (1, 2, 4):
        rows = ready.count(devices).collect()
        assert sum(r.triangles for r in rows) == want and sum(r.edges for r in rows) == n and len(rows) == devices
    ready.drop()
    lists = prep.to_adjacency(prep.edge_array(e))
    assert total(count.forward_local_lists(lists)) == want and total(count.forward_local_lists(lists.limit(0))) == 0


def test_nearest_vectors_of_odd_tables(spark):
    rows = [(k, [float(k % 7), float(k % 5), 1.0]) for k in range(40)] + [(50, [1.0]), (51, None), (52, [1.0, None, 2.0]), (53, [float("nan"), 1.0, 1.0]), (7, [9.0, 9.0, 9.0]), (None, [1.0, 1.0, 1.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    vectors = {}
    for k, v in rows:
        if k is not None and v and all(x is not None and x == x for x in v):
            vectors[k] = max(vectors.get(k, v), v)
    score = lambda a, b: sum(x * y for x, y in zip(vectors[a], vectors[b]))  # noqa: B905, E731
    want = set()
    for a in vectors:
        near = sorted((b for b in vectors if b != a), key=lambda b: (-score(a, b), b))[:3]
        want |= {(min(a, b), max(a, b)) for b in near}
    for block in (7, 4096):
        assert {tuple(r) for r in loaders.edges_from_vectors(df, 3, block=block).collect()} == want


def test_a_bounded_sample_estimates_without_bias(spark, tmp_path):
    pairs = [("a", u, v) for u, v in itertools.combinations(range(60), 2)]
    spark.createDataFrame(pairs, "event_type string, u long, v long").repartition(2).write.parquet(f"{tmp_path}/in")
    estimates = []
    for seed in range(6):
        stream = spark.readStream.schema("event_type string, u long, v long").parquet(f"{tmp_path}/in")
        Q.streams.run_stream(Q.streams.stateful_triangles(stream, 900, seed), f"{tmp_path}/{seed}", lambda b, n, seed=seed: b.write.mode("overwrite").parquet(f"{tmp_path}/out{seed}/batch={n}"), "update")
        last = spark.read.parquet(f"{tmp_path}/out{seed}").orderBy("seen", ascending=False).first()
        assert last.seen == comb(60, 2) and last.held == 900
        estimates.append(last.estimate)
    assert abs(sum(estimates) / len(estimates) - comb(60, 3)) < 0.15 * comb(60, 3)


@pytest.mark.parametrize(("method", "share"), [("edges", 50), ("colours", 2)])
def test_samples_are_as_far_off_as_they_say(spark, method, share):
    edges = gen.fixture_graph(spark, "complete", 30)
    rows = listing.approx_accuracy(edges, method, share, 60).collect()
    true = comb(30, 3)
    assert len(rows) == 60
    assert abs(sum(r.estimate for r in rows) / 60 - true) <= 3 * statistics.pstdev(r.estimate for r in rows) / 60**0.5 + 1e-9
    assert sum(r.within for r in rows) >= 0.8 * 60
    one = listing.approx_triangles(edges, method, share, rows[0].seed).first()
    assert (one.kept, one.shared, one.std_error) == (rows[0].kept, rows[0].shared, rows[0].std_error)
    assert listing.approx_accuracy(gen.fixture_graph(spark, "star", 5), method, share).collect() == []


def test_sums_and_ids_over_crowded_keys(spark):
    rows = [(k if k < 90 else 10**12 + k, k % 5) for k in range(100)] + [(-7, 3)]
    got = sorted(prep.prefix_sum(spark.createDataFrame(rows, "k long, x long").repartition(5), "k", "x").select("k", "x", "running", "before").collect())
    upto = list(itertools.accumulate(x for _, x in sorted(rows)))
    assert [(r.k, r.running, r.before) for r in got] == [(k, n, n - x) for (k, x), n in zip(sorted(rows), upto, strict=True)]
    words = [None, "", "é", *[f"customer{k}" for k in range(200)], "customer7"]
    ids = prep.dense_ids(spark.createDataFrame([(w,) for w in words], "w string").repartition(4), "w").collect()
    assert sorted((r.id, r.key) for r in ids) == list(enumerate(sorted({w for w in words if w is not None}, key=str.encode)))
    assert prep.dense_ids(spark.createDataFrame([], "w string"), "w").count() == 0
    array = spark.createDataFrame([(0, 3), (3, 0)], "src long, dst long")
    assert sorted(map(tuple, prep.node_array(array, fill_isolated=True).collect())) == [(0, 0, 1), (1, 1, 0), (2, 1, 0), (3, 1, 1)]
    assert prep.node_array(array.limit(0), fill_isolated=True).count() == 0


def test_generated_source_at_once_and_as_stream(spark):
    want = sorted(map(tuple, gen.rmat_pairs(gen.F.col("id"), spark.range(16 << 5), 5).collect()))
    assert sorted(map(tuple, read_rmat(spark, 5, partitions=3).collect())) == want
    stream = RmatSource({"scale": "5", "rowsPerBatch": "200"}).simpleStreamReader(None)
    at, rows = stream.initialOffset(), []
    while at["next"] < 16 << 5:
        found, at = stream.read(at)
        rows += found
    assert sorted(rows) == want


def test_edge_lists_survive_files_and_tables(spark, tmp_path):
    e = graph(spark, [(1, 2), (2, 3), (1, 3), (9, 1)])
    for fmt in ("csv", "parquet", "json", "orc"):
        loaders.write_edge_list(e, f"{tmp_path}/{fmt}", fmt)
        assert sorted(loaders.edges_from_file(spark, f"{tmp_path}/{fmt}", fmt).collect()) == sorted(e.collect())
    e.toDF("a", "b").createOrReplaceTempView("links")
    assert sorted(loaders.edges_from_table(spark, "links", "a", "b").collect()) == sorted(e.collect())


def test_studies_run_and_agree(spark):
    g = studies.Graph("k12", gen.fixture_graph(spark, "complete", 12), 1)
    runs = [r for f in studies.STUDIES.values() for r in f(g)]
    assert {r["study"] for r in runs} == set(studies.STUDIES)
    assert {r["triangles"] for r in runs} - {None} == {comb(12, 3)}
    curve = studies.kronecker(spark, (3, 4, 5), 1)
    assert studies.run_records(spark, runs + curve).count() == len(runs) + 6
    assert studies.proportional(spark, curve).count() == 3


def test_truss_and_clustering(spark):
    e = graph(spark, [(a, b) for a in range(5) for b in range(a)] + [(4, 9), (9, 10)])
    assert sorted(map(tuple, listing.truss(e, 5).collect())) == sorted((b, a) for a in range(5) for b in range(a))
    c = {r.v: r.c for r in measures.local_clustering(e).collect()}
    assert c[0] == 1.0 and c[10] == 0.0 and c[4] == 0.6


@settings(max_examples=60, deadline=None)
@given(st.lists(st.tuples(st.sets(st.integers(-9, 30)), st.sets(st.integers(-9, 30))), min_size=1, max_size=6))
def test_kernels(pairs):
    kind = pa.list_(pa.int64())
    a, b = pa.array([sorted(x) for x, _ in pairs], kind), pa.array([sorted(y) for _, y in pairs], kind)
    want = [len(x & y) for x, y in pairs]
    assert kernels.merge(a, b).tolist() == want and kernels.gallop(a, b).tolist() == want and kernels.sorted_run(a, b).tolist() == want
    shared, steps, lazy = kernels.walk(a, b)
    again, moves, eager = kernels.walk(a, b, eager=True)
    assert shared.tolist() == again.tolist() == want and steps.tolist() == moves.tolist() and eager.tolist() == (2 * steps).tolist()
    for (x, y), n, reads in zip(pairs, steps, lazy, strict=True):
        # Elements up to the end of the shorter range are passed, shared ones together; of a list that goes on, the next one has been read.
        stop = min(max(x), max(y)) if x and y else None
        passed = [sum(e <= stop for e in z) if x and y else 0 for z in (x, y)]
        assert n == sum(passed) - (len(x & y) if x and y else 0)
        assert reads == (sum(passed) + sum(p < len(z) for p, z in zip(passed, (x, y), strict=True)) if x and y else 0)


def test_models(spark):
    assert round(planner.amdahl(0.08, 4), 3) == 3.226 and round(planner.amdahl(0.76, 4), 2) == 1.22
    assert abs(planner.amdahl_share(planner.amdahl(0.3, 4), 4) - 0.3) < 1e-12
    assert total(count.forward_grouped(gen.kron_power(gen.fixture_graph(spark, "complete", 3), 3, 2))) == 6


@pytest.mark.parametrize("name", ["graph_summary", "list_triangles", "wedge_counts", "stream_incremental", "approx_colour", "approx_edge_sample", "approx_wedge", "approx_accuracy_edges", "approx_accuracy_colours", "tri_ba", "degrees_from_node", "sorted_rows", "truss_4", "split_costs_weighted_6", "stream_closed_windows", "stream_reservoir", "udtf_triangles", "edges_nation_trade"])
def test_queries_against_sql(spark, name):
    con = duckdb.connect()
    for t in ("lineitem", "orders", "events", "documents", "customer", "supplier"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    rel = con.sql(Q.SQL[name])
    names = sorted(rel.columns)
    df = Q.QUERIES[name](spark, SF)
    assert sorted(df.columns) == names
    assert sorted(map(tuple, df.select(*names).collect())) == sorted(rel.select(", ".join(f'"{c}"' for c in names)).fetchall())


def test_stream_state_is_exact_beyond_the_default_memory(spark, tmp_path):
    pairs = [("a", u, v) for u, v in itertools.combinations(range(150), 2)] + [("b", 1, 2), ("b", 2, 3), ("b", 1, 3)]
    schema = "event_type string, u long, v long"
    spark.createDataFrame(pairs, schema).repartition(3).write.parquet(f"{tmp_path}/in")
    edges = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    got = {r.event_type: (r.edges, r.triangles) for r in Q._stateful(edges, str(tmp_path)).collect()}
    assert got == {"a": (comb(150, 2), comb(150, 3)), "b": (3, 1)}


def test_blocks_of_lists_give_what_joins_give(spark):
    rng = random.Random(6)
    pairs = [(rng.choice([-5, 0, 2**40, *range(60)]), rng.randrange(60)) for _ in range(500)]
    e = graph(spark, pairs).persist()
    want = sorted(map(tuple, count.triangles_of(prep.orient(e)).collect()))
    for per_block in (40, 10**6):
        assert total(blocks.count_blocks(e, per_block)) == len(want)
        assert sorted(map(tuple, blocks.block_triangles(e, per_block).collect())) == want
        at, sides = {}, {}
        for t in want:
            for v in t:
                at[v] = at.get(v, 0) + 1
            for s in itertools.combinations(sorted(t), 2):
                sides[s] = sides.get(s, 0) + 1
        degree = {r.v: r.deg for r in prep.degrees(e).collect()}
        assert {tuple(r) for r in blocks.vertex_counts(e, per_block).collect()} == {(v, d, at.get(v, 0)) for v, d in degree.items()}
        assert {tuple(r) for r in blocks.edge_counts(e, per_block).collect()} == {(r.u, r.v, sides.get((r.u, r.v), 0)) for r in e.collect()}
    assert total(blocks.count_blocks(e.limit(0))) == 0 and blocks.vertex_counts(e.limit(0)).count() == 0


def test_two_paths_and_lists_are_not_shuffled_beyond_the_limit(spark, monkeypatch):
    e = gen.rmat(spark, 8).persist()
    monkeypatch.setattr(count, "JOINED_LIMIT", 100)
    monkeypatch.setattr(planner, "JOINED_LIMIT", 100)
    for f in (count.forward_grouped, count.forward_bitmap, count.edge_iterator, count.brute_force, count.forward_paths, count.triangle_total, lambda x: count.adjacency_input(prep.to_adjacency(prep.edge_array(x)))):
        out = f(e)
        assert total(out) == 10626
        assert "Join" not in out._jdf.queryExecution().optimizedPlan().toString()


def test_one_task_methods_take_any_number_of_edges(spark):
    e = gen.rmat(spark, 8).persist()
    lists = prep.to_adjacency(prep.edge_array(e))
    assert total(count.forward_local(e, limit=500)) == total(count.forward_dynamic(e, limit=500)) == total(count.forward_local_lists(lists, limit=500)) == 10626


def test_groups_that_share_pairs_make_them_unique_in_a_task(spark, monkeypatch):
    rng = random.Random(3)
    rows = [(rng.randrange(12) if rng.random() < 0.95 else None, rng.randrange(-9, 150) if rng.random() < 0.98 else None) for _ in range(2500)]
    df = spark.createDataFrame(rows, "g long, x long")
    groups = {}
    for g, x in rows:
        if g is not None and x is not None:
            groups.setdefault(g, set()).add(x)
    want = {p for xs in groups.values() for p in itertools.combinations(sorted(xs), 2)}
    for size, memory in ((2048, 1 << 26), (3, 1 << 26), (3, 1 << 9)):
        monkeypatch.setattr(loaders, "GROUP_TILE", size)
        monkeypatch.setattr(loaders, "PAIR_BYTES", memory)
        got = list(map(tuple, loaders.edges_from_projection(df, ["g"], "x").collect()))
        assert len(got) == len(want) and set(got) == want


def grouped_rows(rng, users, groups, copies):
    """(g, x): users in some of the groups, each with copies in the same ones, and who shares a group."""
    of = {x: [g for g in range(groups) if rng.random() < 0.3] for x in range(users)}
    rows = [(g, x + users * k) for x, gs in of.items() for k in range(copies if x % 3 else 1) for g in gs]
    return rows, {p for g in range(groups) for p in itertools.combinations(sorted({x for h, x in rows if h == g}), 2)}


def test_triangles_of_groups_are_counted_by_classes_of_members(spark, monkeypatch):
    rng = random.Random(5)
    for users, groups, copies in ((40, 6, 4), (90, 40, 1), (3, 1, 5), (1, 1, 1)):
        rows, pairs = grouped_rows(rng, users, groups, copies)
        df = spark.createDataFrame(rows + [(None, 1), (2, None), rows[0]] if rows else [(None, 1)], "g long, x long")
        for classes, sparse in ((2048, 1 << 40), (9, 1 << 40), (2048, 0)):
            monkeypatch.setattr(loaders, "MATRIX_CLASSES", classes)
            monkeypatch.setattr(loaders, "SPARSE", sparse)
            assert loaders.triangles_from_projection(df, ["g"], "x").collect() == [(brute(pairs),)]


def test_members_of_the_same_groups_are_paired_as_one(spark, monkeypatch):
    monkeypatch.setattr(loaders, "GROUP_TILE", 1)
    rng = random.Random(7)
    for (users, groups, copies), crossed, run, memory in (((40, 6, 4), 1 << 18, 256, 1 << 26), ((30, 8, 9), 20, 4, 1 << 9), ((1, 1, 12), 20, 5, 1 << 26), ((2, 2, 11), 20, 5, 1 << 26), ((60, 30, 1), 9, 2, 1 << 26)):
        for name, value in (("CROSSED", crossed), ("RUN", run), ("PAIR_BYTES", memory)):
            monkeypatch.setattr(loaders, name, value)
        rows, pairs = grouped_rows(rng, users, groups, copies)
        got = list(map(tuple, loaders.edges_from_projection(spark.createDataFrame(rows, "g long, x int"), ["g"], "x").collect()))
        assert len(got) == len(pairs) and set(got) == pairs


@pytest.mark.parametrize("name", ["edges_coactive", "json_typed_edges"])
def test_edges_of_copies_move_little(spark, tmp_path, name):
    rng = random.Random(8)
    rows = [(x + 20 * k, h) for x in range(20) for h in rng.sample(range(12), 6) for k in range(60)]
    con = duckdb.connect()
    con.register("r", pa.table({"user_id": [x for x, _ in rows], "h": [h for _, h in rows]}))
    made = "SELECT user_id, 'view' AS event_type, TIMESTAMP '2024-01-01' + INTERVAL 1 HOUR * h + INTERVAL 1 DAY * h AS ts, '{\"k\": ' || h || '}' AS props FROM r"
    con.sql(f"COPY ({made}) TO '{tmp_path}/events.parquet'")
    con.sql(f"CREATE VIEW events AS SELECT * FROM '{tmp_path}/events.parquet'")
    before = moved_bytes(spark)
    Q.QUERIES[name](spark, str(tmp_path)).write.parquet(f"{tmp_path}/out")
    moved = moved_bytes(spark) - before
    n = con.sql(Q.SQL[name]).aggregate("count(*)").fetchall()[0][0]
    assert n == 719_400 and moved < n // 6
    assert con.sql(f"SELECT * FROM '{tmp_path}/out/*.parquet' EXCEPT ({Q.SQL[name]})").fetchall() == [] and con.sql(f"SELECT count(*) FROM '{tmp_path}/out/*.parquet'").fetchall() == [(n,)]


def test_coactive_triangles_move_less_than_the_edges(spark, tmp_path):
    rng = random.Random(6)
    rows = [(x, h) for x in range(700) for h in rng.sample(range(12), 6)]
    con = duckdb.connect()
    con.register("r", pa.table({"user_id": [x for x, _ in rows], "h": [h for _, h in rows]}))
    con.sql(f"COPY (SELECT user_id, 'view' AS event_type, TIMESTAMP '2024-01-01' + INTERVAL 1 HOUR * h AS ts FROM r) TO '{tmp_path}/events.parquet'")
    con.sql(f"CREATE VIEW events AS SELECT * FROM '{tmp_path}/events.parquet'")
    folder = Path(spark.sparkContext.getCheckpointDir().removeprefix("file:"))
    held = lambda: moved_bytes(spark) + sum(p.stat().st_size for p in folder.rglob("*") if p.is_file())
    before = held()
    got = total(Q.QUERIES["tri_coactive"](spark, str(tmp_path)))
    moved = held() - before
    edges = con.sql(Q.SQL["edges_coactive"]).fetchall()
    assert got == con.sql(Q.SQL["tri_coactive"]).fetchall()[0][0]
    assert len(edges) > 200_000 and moved < len(edges)


@pytest.mark.parametrize("name", ["tri_rmat_8", "edges_rmat_source", "tri_ws0", "tri_ws10", "tri_kron_power", "tri_clique", "tri_bipartite", "tri_ba"])
def test_generated_graphs_read_a_table_and_agree_with_sql(spark, name):
    df = Q.QUERIES[name](spark, SF)
    con = duckdb.connect()
    for t in ("lineitem", "orders", "customer"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    rel = con.sql(Q.SQL[name])
    assert sorted(map(tuple, df.select(*rel.columns).collect())) == sorted(rel.fetchall())


def moved_bytes(spark):
    """Bytes that all stages so far have written for shuffles."""
    jvm = spark.sparkContext._jvm
    stages = spark.sparkContext._jsc.sc().statusStore().stageList(jvm.java.util.ArrayList(), False, False, spark.sparkContext._gateway.new_array(jvm.double, 0), jvm.java.util.ArrayList())
    return sum(stages.apply(k).shuffleWriteBytes() for k in range(stages.size()))


def test_block_lists_meet_in_small_tables(spark, monkeypatch):
    e = gen.rmat(spark, 8)
    monkeypatch.setattr(blocks, "TABLE_WORDS", 8)
    monkeypatch.setattr(blocks, "LOOKED_AT", 16)
    assert total(blocks.count_blocks(e, 300)) == total(count.forward_exploded(e))


def test_slices_beyond_the_limit_come_from_blocks(spark, monkeypatch):
    e = gen.rmat(spark, 8)
    want = {how: {r.slice: tuple(r) for r in split.count_replicated(e, 3, how).collect()} for how in ("strided", "range", "hash")}
    monkeypatch.setattr(count, "JOINED_LIMIT", 100)
    monkeypatch.setattr(blocks, "BLOCK_EDGES", 300)
    monkeypatch.setattr(split, "count_slices", None)
    for how in ("strided", "range"):
        assert {r.slice: tuple(r) for r in split.count_replicated(e, 3, how).collect()} == want[how]
    rows = split.count_replicated(e, 3, "hash").collect()
    assert [sum(r[k] for r in rows) for k in (1, 2)] == [sum(r[k] for r in want["hash"].values()) for k in (1, 2)]


def test_typed_triangles_are_added_up_where_they_are_found(spark, monkeypatch):
    monkeypatch.setattr(blocks, "BLOCK_EDGES", 300)
    e = gen.fixture_graph(spark, "complete", 40).persist()
    types = prep.degrees(e).where("v <> 7").select("v", F.expr("CASE WHEN v < 5 THEN NULL WHEN v % 2 = 0 THEN 'é' ELSE 'b' END").alias("type"))
    t = listing.list_triangles(e)
    for c in "abc":
        t = t.join(types.toDF(c, f"t{c}"), c)
    want = t.select(F.sort_array(F.array("ta", "tb", "tc")).alias("k")).groupBy("k").count().collect()
    before = moved_bytes(spark)
    found = listing.typed_triangles(e, types).collect()
    assert {(r.ta, r.tb, r.tc): r.n for r in found} == {tuple(r.k): r["count"] for r in want}
    assert moved_bytes(spark) - before < 60_000  # 9,880 triangles of three ids would be more


def test_new_triangles_without_two_paths(spark):
    """A star that gets its hub's second half: pairs of its edges were all made before."""
    star = spark.range(1, 3001).select(F.lit(0).cast("long").alias("u"), F.col("id").alias("v"))
    old, new = star.where("v <= 2000"), star.where("v > 2000").unionByName(spark.createDataFrame([(1, 2), (1, 2500), (2998, 2999)], "u long, v long"))
    before = moved_bytes(spark)
    assert total(streams.new_triangles(old, new)) == 3
    assert moved_bytes(spark) - before < 1_000_000


def test_subgraphs_share_one_copy_of_the_edges(spark):
    """With 20 classes an edge is in 20 subgraphs; what is shuffled must not grow with them."""
    e = gen.rmat(spark, 8).persist()
    e.count()
    for variant in ("multiset", "weighted"):
        before = moved_bytes(spark)
        assert total(split.count_partitioned(e, 20, variant)) == 10626
        assert moved_bytes(spark) - before < 150_000


def test_few_edges_with_long_lists_are_not_carried_through_joins(spark, monkeypatch):
    """Far fewer edges than JOINED_LIMIT, each of which would carry a list of 100 on average, as words or as ids (spread: no two in a word)."""
    e = gen.fixture_graph(spark, "complete", 300).persist()
    spread = e.select(F.col("u") * 64, F.col("v") * 64).toDF("u", "v").persist()
    assert planner.choose(e)[0] == "forward_bitmap" and planner.choose(spread)[0] in ("forward_grouped", "forward_lists")
    monkeypatch.setattr(planner, "MOVED_BYTES", 1 << 20)
    for edges in (e, spread):
        assert planner.choose(edges) == ("forward_paths", {})
        out = count.triangle_total(edges)
        assert total(out) == comb(300, 3) and "Join" not in out._jdf.queryExecution().optimizedPlan().toString()
    assert planner.choose(gen.fixture_graph(spark, "complete", 20))[0] == "forward_bitmap"


def test_pairs_of_words_are_shuffled_as_packed_numbers(spark, monkeypatch):
    rng = random.Random(5)
    names = ["".join(rng.choice("abcdefgh") for _ in range(rng.randrange(1, 9))) for _ in range(600)]
    texts = [None, "", "One", "a a a", "b", "solo solo"] + [" ".join(rng.choice(names).title() for _ in range(rng.randrange(0, 60))) + rng.choice(["", "\u00e9x", " 7"]) for _ in range(1500)]
    df = spark.createDataFrame([(t,) for t in texts], "text string").repartition(3).persist()
    lists = [re.findall("[a-z]+", (t or "").lower()) for t in texts]
    pairs = {tuple(sorted(p)) for w in lists for p in itertools.pairwise(w) if p[0] != p[1]}
    rank = {w: k for k, w in enumerate(sorted({w for p in pairs for w in p}))}
    want = {(rank[a], rank[b]) for a, b in pairs}
    df.count()
    before = moved_bytes(spark)
    got = list(map(tuple, loaders.edges_from_tokens(df, "text").collect()))
    assert len(got) == len(want) and set(got) == want
    assert moved_bytes(spark) - before < 6 * len(want)  # two words each would be more
    for small in ({"HELD_TOKENS": 300, "HELD_PAIRS": 500, "PART_PAIRS": 2000, "LISTED_WORDS": 90}, {"NAMED_WORDS": 100}):
        for name, value in small.items():
            monkeypatch.setattr(loaders, name, value)
        got = list(map(tuple, loaders.edges_from_tokens(df, "text").collect()))
        assert len(got) == len(want) and set(got) == want
    assert loaders.edges_from_tokens(df.limit(0), "text").count() == 0


def test_lists_of_many_bytes_are_not_carried_by_the_grouped_count(spark, monkeypatch):
    """Far fewer edges than JOINED_LIMIT, each of which carries a list of 100 on average."""
    e = gen.fixture_graph(spark, "complete", 300).persist()
    joins = lambda df: "Join" in df._jdf.queryExecution().optimizedPlan().toString()
    for order in ("degree", "id"):
        assert joins(count.forward_grouped(e, order=order))
    monkeypatch.setattr(count, "JOINED_BYTES", 1 << 20)
    for order in ("degree", "id"):
        out = count.forward_grouped(e, order=order)
        assert not joins(out) and total(out) == comb(300, 3)
    assert joins(count.forward_grouped(gen.fixture_graph(spark, "complete", 40)))
    assert total(count.forward_grouped(gen.fixture_graph(spark, "empty", 5), order="id")) == 0


def test_edges_that_carry_lists_are_not_broadcast(spark, tmp_path):
    """Their file is far below the size from which on Spark does not broadcast it."""
    gen.fixture_graph(spark, "complete", 400).coalesce(1).write.parquet(str(tmp_path / "e"))
    e = spark.read.parquet(str(tmp_path / "e"))
    e._is_written = True
    few = gen.fixture_graph(spark, "complete", 40)
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    for options in ({}, {"order": "random"}, {"split_over": 100}):
        out = count.forward_grouped(e, **options)
        left = plan(out).count("BroadcastHashJoin")
        assert total(out) == comb(400, 3) and left == (2 if options.get("split_over") else 0), options  # the table of hubs is small
    assert "BroadcastHashJoin" in plan(count.forward_grouped(few))


def test_each_draw_of_a_recursive_matrix_is_made_once(spark):
    keys = spark.range(300).select(F.col("id").alias("k"), (F.col("id") % 7).alias("line"))
    plan = gen.rmat_from(keys, ["k", "line"], 12)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("md5(") == 1  # in a function of the level
    for scale in (0, 1, 12, 31, 33, 62):
        got = gen.rmat_pairs(F.col("k"), keys, scale).collect()
        assert sorted(map(tuple, got)) == sorted(rmat_rows(range(300), scale, 42))


def test_many_pairs_of_groups_are_shuffled_packed(spark, monkeypatch):
    rng = random.Random(7)
    rows = [(g, m) for g in range(400) for m in rng.sample(range(-900, 900), 30)]
    rows += [(None, 1), (1, None), (500, 3), (501, 4), (501, 4)]

    def want(rows):
        groups = {}
        for g, m in rows:
            if None not in (g, m):
                groups.setdefault(g, set()).add(m)
        return {p for xs in groups.values() for p in itertools.combinations(sorted(xs), 2)}

    def moved(df):
        before = moved_bytes(spark)
        edges = loaders.edges_from_projection(df, ["g"], "m")
        got = list(map(tuple, edges.collect()))
        assert edges.schema["u"].dataType == edges.schema["v"].dataType == df.schema["m"].dataType
        assert len(got) == len(set(got)) and set(got) == want(map(tuple, df.collect()))
        return moved_bytes(spark) - before

    wide = [(g, m * (1 << 52)) for g, m in rows if m is not None]
    monkeypatch.setattr(loaders, "PAIR_BLOCKS", 1000)  # not the path of tiles
    shuffled = moved(spark.createDataFrame(rows, "g long, m long").repartition(3).persist())
    for name, value in {"PACKED_OVER": 0, "PART_PAIRS": 20_000}.items():
        monkeypatch.setattr(loaders, name, value)
    assert 2 * moved(spark.createDataFrame(rows, "g long, m long").repartition(3).persist()) < shuffled
    monkeypatch.setattr(loaders, "MADE_PAIRS", 1000)
    monkeypatch.setattr(loaders, "CELL_BITS", 3)
    for data, kind in ((rows, "int"), (wide, "long"), (rows[-3:], "long"), ([], "long")):
        moved(spark.createDataFrame(data, f"g long, m {kind}").repartition(3).persist())
    one_large = [(0, m) for m in range(300)] + [(g, g % 7 + k) for g in range(1, 60) for k in (0, 400)]
    monkeypatch.setattr(loaders, "SHARED", 0)
    moved(spark.createDataFrame(one_large, "g long, m long").repartition(3).persist())
