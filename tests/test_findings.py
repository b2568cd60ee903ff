"""What a review found on odd inputs and larger tables."""

import duckdb

import __spark_entry__ as entry


def both(spark, folder, name, **tables):
    """A query's rows and those of its SQL on Parquet tables given as DuckDB SQL."""
    con = duckdb.connect()
    for t, sql in tables.items():
        con.sql(f"copy ({sql}) to '{folder}/{t}.parquet' (format parquet)")
        con.sql(f"create view {t} as select * from read_parquet('{folder}/{t}.parquet')")
    got, want = entry.queries()[name](spark, str(folder)), con.sql(entry.oracle_sql()[name])
    return sorted(map(tuple, got.select(want.columns).collect()), key=str), sorted(want.fetchall(), key=str)


def test_vec_dot_in_the_precision_of_components(spark, tmp_path):
    """0.3195 * 1000 is 319.5 as a float and less as a double; nulls, empty vectors and missing ones follow the SQL."""
    rows = "values (0, [0.3195]::float[]), (1, [0.5, null]::float[]), (2, []::float[]), (3, null), (4, [-0.3195, 1.0]::float[])"
    got, want = both(spark, tmp_path, "vec_dot", embeddings=f"select vec_id::bigint as vec_id, embedding from ({rows}) t(vec_id, embedding)")
    assert got == want and dict(got)[0] == 320 * 320


def test_bound_equals_free_compares_whole_numbers(spark, monkeypatch):
    """One count for each cell whose least expansions differ or of which a run has none; equal quotients of other numbers are equal."""
    from cutline.plans import method_queries

    schema = "cell_id long, cutter int, step int, size long, small long, n long"
    free = [(i, 0, 0, 10 + i % 7, 605 + i, 1500) for i in range(50)]
    bound = [(i, 0, 0, 2 * s, 2 * m, n) if i % 2 else (i, 0, 0, s, m, n) for i, _, _, s, m, n in free]
    bound[7], bound[8] = (7, 0, 0, 1, 612, 1500), (99, 0, 0, 10, 605, 1500)
    monkeypatch.setattr(method_queries.graphs, "graph", lambda *a: None)
    monkeypatch.setattr(method_queries.cutters, "cuts", lambda g, name, bound=False, rows=(free, bound): spark.createDataFrame(rows[bound], schema))
    assert entry.queries()["bound_equals_free"](spark, "").first().differences == 3


def test_fronts_cover_cells_of_two_nodes(spark, tmp_path):
    """Two users that follow each other, apart from a ring of others, have a cut, too."""
    users = "list_concat([0, 1, 0, 1], [10, 11, 12, 13, 10, 11, 12, 13, 10, 11, 12, 13])"
    events = f"select i - 1 as event_id, timestamp '2024-01-01' + i * interval 1 minute as ts, ({users})[i]::bigint as user_id from range(1, 17) r(i)"
    got, want = both(spark, tmp_path, "landmark_front_users", events=events)
    assert got == want and got[0][2] == 6


SF = "/root/testdata/sf0.001"


def reads_a_table(spark, name):
    """Whether a query's rows come from a given table, and are those of its SQL."""
    con = duckdb.connect()
    for t in ("customer", "orders", "part"):
        con.sql(f"create view {t} as select * from read_parquet('{SF}/{t}.parquet')")
    got, want = entry.queries()[name](spark, SF), con.sql(entry.oracle_sql()[name])
    return any(f.startswith(f"file://{SF}/") for f in got.inputFiles()) and sorted(map(tuple, got.select(want.columns).collect())) == sorted(want.fetchall())


def test_bulk_limits_reads_a_table(spark):
    assert reads_a_table(spark, "bulk_limits")


def test_bulk_steps_reads_a_table(spark):
    assert reads_a_table(spark, "bulk_steps")


def test_choose_cut_reads_a_table(spark):
    assert reads_a_table(spark, "choose_cut")


def test_pareto_fixture_reads_a_table(spark):
    assert reads_a_table(spark, "pareto_fixture")


def test_cut_report_reads_a_table(spark):
    assert reads_a_table(spark, "cut_report")


def test_directions_8_reads_a_table(spark):
    assert reads_a_table(spark, "directions_8")


def test_front_time_reads_a_table(spark):
    assert reads_a_table(spark, "front_time")


def test_reach_rcte_reads_a_table(spark):
    assert reads_a_table(spark, "reach_rcte")


def test_complete_streams_are_files(spark, tmp_path):
    """Sessions come from the shared folder, not from a sink that holds all rows in the driver."""
    events = "select i as event_id, timestamp '2024-01-01' + (i * i) * interval 1 minute as ts, i % 3 as user_id, 0.5::double as value from range(60) r(i)"
    got, want = both(spark, tmp_path, "feed_session", events=events)
    assert got == want and entry.queries()["feed_session"](spark, str(tmp_path)).inputFiles()


def test_gabriel_memory_is_bounded():
    """3000 points in one group, some twice, are settled in little memory, and as the definition says."""
    import tracemalloc

    import numpy as np
    import pandas as pd

    from cutline.sources.graphs import _settle

    rng = np.random.default_rng(3)
    x, y = rng.integers(0, 10_000, (2, 3000))
    x[1500:1600], y[1500:1600] = x[:100], y[:100]
    group = pd.DataFrame({"node_id": np.arange(3000), "x": x, "y": y, "asks": np.arange(3000) < 10})
    tracemalloc.start()
    got = _settle(10_000, True)(group)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    want = {(i, b) for i in range(10) for b in range(3000) if b != i and not ((x - x[i]) * (x - x[b]) + (y - y[i]) * (y - y[b]) < 0).any()}
    assert got.settled.all() and len(got) == len(want) and set(zip(got.u, got.v, strict=True)) == want and peak < 32 << 20


def lattice_index(spark, wide):
    """A wide x wide lattice under an order of its nodes: edges, ranks, its index by one kernel."""
    import numpy as np

    from cutline.functions import index as kernel
    from cutline.model import Graph

    n = wide * wide
    edges = [(i, i + 1) for i in range(n) if i % wide < wide - 1] + [(i, i + wide) for i in range(n - wide)]
    rank = np.random.default_rng(3).permutation(n)
    g = Graph(spark.createDataFrame([(i, i % wide, i // wide) for i in range(n)], "node_id long, x long, y long"), spark.createDataFrame(edges, "u long, v long"))
    a, b = (rank[np.array([e[k] for e in edges])] for k in (0, 1))
    up = kernel.build(n, np.minimum(a, b), np.maximum(a, b))
    return g, spark.createDataFrame([(i, int(r)) for i, r in enumerate(rank)], "node_id long, rank long"), [(r, h) for r, x in enumerate(up) for h in x]


def test_index_rounds_are_blocks(spark, monkeypatch):
    """A round is a block of ranks, not a step of one rank, and gives the index of one kernel."""
    from cutline.operators import index

    g, ranks, want = lattice_index(spark, 9)
    rounds = []
    kept = index.kept
    monkeypatch.setattr(index, "kept", lambda df, *a: rounds.append(a) or kept(df, *a))
    got = index.build_index_rounds(index.oriented(g.edges, ranks), block_ranks=30)
    assert sorted(map(tuple, got.select("lo", "hi").collect())) == want
    assert len(rounds) == 1 + 3


def test_customize_rounds_are_blocks(spark, monkeypatch):
    """A round is a block of ranks, not a step along paths, and gives the weights of one kernel."""
    from pyspark.sql import functions as F

    from cutline.operators import index

    g, ranks, arcs = lattice_index(spark, 9)
    i = spark.createDataFrame(arcs, "lo long, hi long")
    metric = g.edges.withColumn("weight", 1 + (F.col("u") * 7 + F.col("v") * 3) % 17)
    want = sorted(map(tuple, index.customize(i, g, ranks, metric).collect()))
    rounds = []
    kept = index.kept
    monkeypatch.setattr(index, "kept", lambda df, *a: rounds.append(a) or kept(df, *a))
    assert sorted(map(tuple, index.customize_rounds(i, ranks, metric, block_ranks=30).collect())) == want
    assert len(rounds) == 1 + 3


def test_large_cells_are_ordered_by_several_tasks(spark, monkeypatch):
    """A cell that is not laned has its blocks ordered by tasks of their own, and the order stays the one that a single task gives."""
    from cutline.operators import cutters, dissect

    g, _, _ = lattice_index(spark, 12)
    rows = lambda: [r.node_id for r in dissect.cell_positions(g, cutters.config("SP4")).orderBy("path", "pos").collect()]
    whole = rows()
    jobs = []
    made = dissect._separated
    monkeypatch.setattr(dissect, "_separated", lambda n, e, s, lanes: jobs.append(lanes) or made(n, e, s, lanes))
    monkeypatch.setattr(dissect, "ALONE_NODES", 30)
    assert rows() == whole and len(jobs) > 1 and set(jobs) == {1}


def _grid(spark, w, h):
    """A lattice without some of its edges, as a graph of tables."""
    from cutline.model import Graph, kept

    at = [(i, 1000 * (i % w) + i % 7, 1000 * (i // w) + i % 5) for i in range(w * h)]
    edges = [(i, i + 1) for i in range(w * h) if i % w < w - 1] + [(i, i + w) for i in range(w * (h - 1)) if (i * 7) % 10 < 8 or i % w == 0]
    return Graph(kept(spark.createDataFrame(at, "node_id long, x long, y long")), kept(spark.createDataFrame(edges, "u long, v long")))


def test_growth_has_places_of_the_front_alone(spark, monkeypatch):
    """F4, F16: places of sides that have no cut of the front are not carried on; fronts are recounted with one row for each node, and a wrong size is seen."""
    from cutline.operators import cutters
    from cutline.plans.method_queries import front_checks

    g, splitter = _grid(spark, 13, 9), cutters.config("PP20")
    places, found = cutters.growth(g, splitter)
    side = lambda df: {(r.cell_id, r.cutter, r.grown) for r in df.select("cell_id", "cutter", "grown").distinct().collect()}
    assert side(places) == side(found) and places.count() == 117 * len(side(found))
    assert {(r.check_name, r.violations) for r in front_checks(g, splitter).collect()} == {(c, 0) for c in ("cut_recount", "block_recount", "front_strict", "cover")}
    wrong = found.withColumn("size", found["size"] + (found.step == 1).cast("long"))
    monkeypatch.setattr(cutters, "growth", lambda *a: (places, wrong))
    bad = {r.check_name: r.violations for r in front_checks(g, splitter).collect()}
    assert bad["cut_recount"] == 1 and bad["block_recount"] == 0 and bad["cover"] == 0


def test_brief_cutters_have_the_same_front(spark):
    """F4, F16: cutters that stop at the size of earlier halves leave the same front, for fewer units of flow."""
    import numpy as np
    from cutline.functions.order import Graph
    from cutline.operators import compiled, cutters
    from pyspark.sql import functions as F

    g = _grid(spark, 21, 16)
    e, n = np.array(g.edges.orderBy("u", "v").collect()), np.array(g.nodes.orderBy("node_id").collect())
    k = Graph(len(n), e[:, 0], e[:, 1], n[:, 1], n[:, 2])
    for name in ("PP20", "SP8"):
        asked = [(i, bytearray(compiled.packed(compiled.CUTS, k, cutters.config(name), logs=True, brief=bool(i)))) for i in (0, 1)]
        table = spark.createDataFrame(asked, "i int, request binary").select("i", F.expr(f"{compiled.registered(spark)}(request)").alias("answer"))
        full, brief = (compiled.read_cuts(bytes(r.answer), k.n) for r in table.orderBy("i").collect())
        assert [(c.cutter, c.size, c.small, c.side) for c in full[0]] == [(c.cutter, c.size, c.small, c.side) for c in brief[0]] and brief[2] < full[2]


def test_blocks_are_tiles_and_searches_cross_few(spark, monkeypatch):
    """r03 F1: blocks are tiles and not strips, so that a search over a lattice takes a few rounds; a phase pushes a unit for each root that has a way, and the flow is the one of a task."""
    import numpy as np
    from cutline.functions.flow import Net
    from cutline.functions.flow import max_flow as task_flow
    from cutline.operators import flow, graph, table_cutter
    from pyspark.sql import functions as F

    g = _grid(spark, 20, 20)
    _, places = graph.blocked(g, 30)
    spread = places.join(g.nodes, "node_id").groupBy("block").agg((F.max("y") - F.min("y")).alias("h")).agg(F.max("h").alias("h"), F.count("*").alias("n")).first()
    high = g.nodes.agg((F.max("y") - F.min("y")).alias("h")).first().h
    assert spread.n > 15 and spread.h < 0.6 * high
    ids = lambda low, top: g.nodes.filter((F.col("x") >= low) & (F.col("x") < top)).select("node_id")
    searched = []
    found = flow.BlockNet.reach
    monkeypatch.setattr(flow.BlockNet, "reach", lambda self, *a, **b: searched.append(1) or found(self, *a, **b))
    s, t = ids(0, 1000), ids(19_000, 30_000)
    net = flow.BlockNet.of(g, table_cutter.undirected(g), 30)
    units, _ = net.augment(s, t)
    u, v = np.array(g.edges.collect()).T
    assert units == task_flow(Net.undirected(400, u, v), list(range(0, 400, 20)), list(range(19, 400, 20))) and len(searched) <= 4
    assert all(r.violations == 0 for r in flow.flow_violations(net.state(), table_cutter.undirected(g), s, t).collect())


def test_order_grid_equals_the_python_kernels(spark, monkeypatch):
    """r03 F2, F3, F4: orders of the grid come from the compiled kernel or level by level, indexes from the compiled kernel; both are those of the Python kernels, and so are distances."""
    import numpy as np
    from cutline.functions import index, order
    from cutline.operators import compiled, dissect
    from cutline.plans import workloads
    from pyspark.sql import functions as F

    monkeypatch.setattr(dissect, "PYTHON_NODES", 30)
    g = _grid(spark, 13, 9)
    e, at = np.array(g.edges.orderBy("u", "v").collect()), np.array(g.nodes.orderBy("node_id").collect())
    k = order.Graph(117, e[:, 0], e[:, 1], at[:, 1], at[:, 2])
    weights = (e[:, 0] * 7 + e[:, 1] * 3) % 17 + 1
    want, requests = {}, []
    configs = {n: workloads.order_splitter(n) for n in ("SP4", "QM", "PP3")}
    for name, (splitter, prep) in configs.items():
        rank = np.empty(117, np.int64)
        rank[order.full_order(k, splitter, prep)] = np.arange(117)
        lo, hi = np.minimum(rank[k.u], rank[k.v]), np.maximum(rank[k.u], rank[k.v])
        up = index.build(117, lo, hi)
        w = index.Weights(up).attach([*lo, *hi], [*hi, *lo], [*weights, *weights]).customize("upper")
        ask = np.random.default_rng(1).integers(0, 117, (300, 2))
        want[name] = index.measures(up) | {"distances": sum(w.tree_query(index.parents(up), *p) for p in ask.tolist())}
        requests.append((name, bytearray(compiled.packed_index(117, lo, hi, weights, 2, ask))))
    answers = spark.createDataFrame(requests, "name string, request binary").select("name", F.expr(f"{compiled.registered(spark)}(request)").alias("answer")).collect()
    for r in answers:
        got, took = compiled.read_index(bytes(r.answer))
        assert {m: got[m] for m in want[r.name]} == want[r.name] and len(took) == 2
    for nodes in (workloads.GRID_NODES, 0):
        monkeypatch.setattr(workloads, "GRID_NODES", nodes)
        rows = {r.config: r for r in workloads.order_grid(g, configs).collect()}
        assert all(rows[c][m] == x for c in want for m, x in want[c].items() if m != "distances") and all(r.order_s > 0 and r.custom_s > 0 and r.query_us > 0 for r in rows.values())


def test_rows_with_lists_or_paths_are_not_broadcast(spark, monkeypatch):
    """r03 F5, F6, F7: files of such rows are far smaller than the rows, so joins with them are shuffled whatever the files' size; else the driver takes whole node tables."""
    from cutline.operators import cutters
    from cutline.plans import method_queries

    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    g, plans, kept = _grid(spark, 13, 9), {}, method_queries.kept
    monkeypatch.setattr(method_queries, "kept", lambda df, label="state": plans.setdefault(label, plan(df)) and kept(df, label))
    assert all(r.violations == 0 for r in method_queries.front_checks(g, cutters.config("PP3")).collect())
    assert plans["recount"].count("SortMergeJoin") >= 2
    monkeypatch.setattr(method_queries.graphs, "graph", lambda *a: g)
    found = entry.queries()["nd_apart_cust"](spark, "")
    assert plan(found).count("SortMergeJoin") >= 2 and "BroadcastHashJoin" not in plan(found)
    assert tuple(found.first())[:2] == (0, 0)
