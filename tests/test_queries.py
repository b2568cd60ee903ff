"""Queries on the smallest tables against DuckDB."""

import os

import duckdb
import pandas as pd
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
NAMES = (
    "edges_part", "edges_cust", "edges_emb", "degree_hist", "induced_sub", "components_part", "bfs_part", "balance_table", "sweep_emb", "bands_emb", "stcut_value", "reach_target", "sp4_front", "pp3_front",
    "bandflow_cuts", "pierce_trace_nat", "bulk_steps", "pareto_fixture", "choose_cut", "best_eps_nat", "split_graph", "node_sep", "nd_perm_part", "nd_levels_cust", "nd_apart_cust", "chain_edges_part", "bridges", "clique_cells_region", "component_rounds_talk", "candidates_nat", "pierce_choice", "avoid_augmenting", "bulk_limits", "bound_equals_free",
    "bandflow_first_nat", "cut_report", "flow_levels_nat", "table_cutter_nat", "wide_equals_local", "handpicked_cut", "ml_cuts", "ml_recount", "path_weights_supp", "custom_rounds_supp", "dist_rounds_supp", "dist_witness_supp",
    "witness_arcs_supp", "custom_directed_supp", "dist_directed_supp", "w3_cuts", "feed_ttl", "feed_join", "feed_late_rows", "feed_customized", "tree_cells", "path_tree_depth", "chains_part", "index_arcs_supp",
    "etree_supp", "search_space_supp", "custom_w_supp", "dist_supp", "dist_labels_supp", "qm_cut", "range_grid", "asof_weight", "feed_tumbling", "udtf_steps", "w4_grid",
)


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"create view {t} as select * from read_parquet('{SF}/{t}.parquet')")
    return con


def rows(df: pd.DataFrame) -> list:
    def plain(v):
        if v is None or v is pd.NA or v != v:
            return None
        v = v.item() if hasattr(v, "item") else v
        return int(v) if isinstance(v, float) and v == int(v) else v

    return sorted((tuple(plain(v) for v in r) for r in df[sorted(df.columns)].itertuples(index=False)), key=str)


@pytest.mark.skipif(not os.path.isdir(SF), reason="no tables")
@pytest.mark.parametrize("name", NAMES)
def test_query(spark, duck, name):
    got, want = entry.queries()[name](spark, SF).toPandas(), duck.sql(entry.oracle_sql()[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)


def test_entry(spark):
    assert entry.entry(spark).count() > 0


def test_wide_plans(spark):
    """Tables of nodes are numbered without a window over one partition."""
    from cutline.operators.geometry import global_rank

    df = spark.range(1000).selectExpr("(id * 7919) % 1000 as a")
    got = [(r.a, r.n) for r in global_rank(df, ["a"], "n").collect()]
    assert sorted(got) == [(i, i) for i in range(1000)]
    assert "SinglePartition" not in global_rank(df, ["a"], "n")._jdf.queryExecution().executedPlan().toString()


def test_dimacs_round_trip(spark, tmp_path):
    from cutline.register import register
    from cutline.sources import dimacs

    arcs = spark.createDataFrame([(i, i + 1, 3 * i + 1) for i in range(50)], "src long, dst long, weight long")
    dimacs.write_arcs(arcs, str(tmp_path / "g"))
    want = sorted(map(tuple, arcs.collect()))
    assert sorted(map(tuple, dimacs.read_arcs(spark, str(tmp_path / "g")).collect())) == want
    register(spark)
    assert sorted(map(tuple, spark.read.format("dimacs").option("range", "40").load(str(tmp_path / "g")).collect())) == want
    assert spark.sql("select count(*) as n from sweep_directions(8)").first().n == 8


def test_index_folders_and_formats(spark, tmp_path):
    from cutline import schema
    from cutline.sources import tables

    edges = spark.createDataFrame([(i, i + 1) for i in range(40)], "u long, v long")
    for kind in tables.FORMATS:
        for _ in range(2):  # a repeated run replaces its own folder
            path = tables.write_run(edges, str(tmp_path / kind), "r1", kind)
        assert sorted(map(tuple, tables.read_table(spark, path, schema.EDGES, kind).collect())) == [(i, i + 1) for i in range(40)]
    with pytest.raises(TypeError):
        tables.read_table(spark, str(tmp_path / "parquet" / "run=r1"), schema.PAIRS)
    with pytest.raises(ValueError):
        tables.read_table(spark, "x", schema.EDGES, "text")
    index = spark.createDataFrame([(i, i + 1, False) for i in range(300)], "lo long, hi long, is_shortcut boolean")
    back = spark.read.parquet(tables.write_index(index, str(tmp_path / "index"), "a", 8))
    assert back.filter("lo < 20").count() == 20 and back.select("bucket").distinct().count() == 8


def test_dimacs_problem_line(spark, tmp_path):
    from cutline.sources import dimacs

    arcs = spark.createDataFrame([(1, 2, 3), (2, 3, 1)], "src long, dst long, weight long")
    dimacs.write_arcs(arcs, str(tmp_path / "g"))
    assert dimacs.check_problem(spark, str(tmp_path / "g")) == (3, 2)
    (tmp_path / "bad.gr").write_text("c x\np sp 3 5\na 1 2 3\n")
    (tmp_path / "none.gr").write_text("a 1 2 3\n")
    for name in ("bad.gr", "none.gr"):
        with pytest.raises(ValueError):
            dimacs.check_problem(spark, str(tmp_path / name))


def _lattice(spark, w, h):
    from cutline.model import Graph, kept

    e = [(i, i + 1) for i in range(w * h) if i % w < w - 1] + [(i, i + w) for i in range(w * (h - 1))]
    nodes = spark.createDataFrame([(i, 1000 * (i % w) + 37 * i % 100, 1000 * (i // w) + 53 * i % 100) for i in range(w * h)], "node_id long, x long, y long")
    return Graph(kept(nodes), kept(spark.createDataFrame(e, "u long, v long"))), e


def test_components_join_forests_of_many_tasks(spark, monkeypatch):
    """Edges that no two tasks see alike: components come from forests of small pieces and the rounds between them."""
    import random

    from cutline.functions.order import component_labels
    from cutline.model import Graph
    from cutline.operators import graph as ops
    import numpy as np

    monkeypatch.setattr(ops, "TASK_EDGES", 20)
    r = random.Random(3)
    e = [(i, i + 1) for i in range(0, 300) if i % 40] + [(r.randrange(300, 500), r.randrange(300, 500)) for _ in range(120)]
    e = [x for x in e if x[0] != x[1]]
    edges = spark.createDataFrame(e, "u long, v long").repartition(9)
    nodes = spark.range(520).withColumnRenamed("id", "node_id")
    want = component_labels(520, *np.array(e).T)
    for run in (ops.components, ops.component_rounds):
        got = {x.node_id: x.component_id for x in run(Graph(nodes, edges)).collect()}
        assert [got[i] for i in range(520)] == want.tolist()
    forest = ops.forest(edges).collect()
    assert forest and all(x.u > x.v for x in forest)


def test_hops_cross_blocks(spark):
    from cutline.operators import graph as ops

    g, _ = _lattice(spark, 9, 7)
    seeds = spark.createDataFrame([(0,), (40,)], "node_id long")
    want = {i: min(i % 9 + i // 9, abs(i % 9 - 4) + abs(i // 9 - 4)) for i in range(63)}
    for size in (1000, 15):
        assert {r.node_id: r.dist for r in ops.hop_dist(g, seeds, size).collect()} == want


def test_selection_narrows_brackets(spark, monkeypatch):
    import random

    from cutline.operators import geometry

    monkeypatch.setattr(geometry, "WHOLE", 10)
    monkeypatch.setattr(geometry, "BUCKETS", 4)
    r = random.Random(5)
    values = {c: [r.choice([r.randrange(-(10**15), 10**15), 7, 7]) for _ in range(200)] for c in range(3)} | {3: [4] * 50}
    df = spark.createDataFrame([(c, v) for c, own in values.items() for v in own], "c long, value long")
    for take in (1, 20, 50):
        want = spark.createDataFrame([(c, take) for c in values], "c long, take long")
        got = {x.c: (x.value, x.before) for x in geometry.nth(df, ["c"], want).collect()}
        for c, own in values.items():
            v = sorted(own)[take - 1]
            assert got[c] == (v, sum(x < v for x in own))
    nodes = spark.createDataFrame([(i, 0, i % 7 * 10, i % 3) for i in range(60)], "node_id long, cell_id long, x long, y long")
    found = {(x.k, x.node_id): x.term for x in geometry.bands(nodes, 2, 0.1).collect()}
    for k, (c, s) in enumerate(geometry.directions(2)):
        order = sorted(range(60), key=lambda i: (i % 7 * 10 * c + i % 3 * s, i))
        assert {n: t for (q, n), t in found.items() if q == k} == {n: 1 for n in order[:6]} | {n: 2 for n in order[-6:]}


def test_block_flow_equals_task_flow(spark):
    """Several sources and targets, flow pushed forward and backward, blocks of a few edges."""
    import numpy as np

    from cutline.functions.flow import Net, max_flow
    from cutline.operators import flow, table_cutter

    g, e = _lattice(spark, 6, 5)
    u, v = np.array(e).T
    ids = lambda x: spark.createDataFrame([(i,) for i in x], "node_id long")
    for s, t, forward in (([0, 6, 12], [29, 23], True), ([14], [0, 5, 24, 29], False)):
        net = Net.undirected(30, u, v)
        value = max_flow(net, s, t)
        blocks = flow.BlockNet.of(g, table_cutter.undirected(g), 12)
        assert blocks.places.select("block").distinct().count() > 1
        units, _ = blocks.augment(ids(s if forward else t), ids(t if forward else s), forward)
        assert units == value
        assert all(x.violations == 0 for x in flow.flow_violations(blocks.state(), table_cutter.undirected(g), ids(s), ids(t)).collect())
        for seeds, way in ((s, True), (t, False)):
            marks = net.reach(seeds, way)[0]
            assert {x.node_id for x in blocks.reach(ids(seeds), way)[0].collect()} == {i for i in range(30) if marks[i]}
