"""Cases of the second review of the engine."""

import duckdb
import pytest

from graphevents import catalog, keyed, kg, tree
from graphevents.catalog import base
from graphevents.sources import notes


@pytest.mark.parametrize("name", ["dec_regulation", "dec_nested", "tree_prune_t2"])
def test_a_query_reads_the_tables_itself(spark, sf, name):
    """Nothing that another query derived stands in for the tables."""
    df = spark.range(1)
    base._KEPT.update({(spark.sparkContext.applicationId, sf, k): df for k in ("lines", "edges", "terminals", "gold_events")})
    assert catalog.queries()[name](spark, sf).count() > 0


def test_a_grid_of_two_vocabularies(spark, sf):
    df = catalog.queries()["op_join_cross_grid"](spark, sf)
    assert {x.rsplit("/", 1)[-1] for x in df.inputFiles()} == {"orders.parquet", "lineitem.parquet"}
    want = duckdb.sql(catalog.oracle_sql()["op_join_cross_grid"].replace("FROM orders", f"FROM '{sf}/orders.parquet'").replace("FROM lineitem", f"FROM '{sf}/lineitem.parquet'")).fetchall()
    assert sorted(r["cell"] for r in df.collect()) == sorted(x for (x,) in want) and len(want) > 3


def test_trees_that_join_brands(spark, sf, tmp_path):
    """A table of three parts, by hand: two brands share a name, the third meets them by the head only."""
    rows = [("b1", "red nut"), ("b2", "red nut"), ("b3", "old nut")]
    spark.createDataFrame(rows, "p_brand string, p_name string").write.parquet(f"{tmp_path}/part.parquet")
    got = {r["mode"]: r["cost"] for r in catalog.queries()["tree_exact_steiner"](spark, str(tmp_path)).collect()}
    assert got == {"exact": 5, "bfs": 5, "voronoi": 5, "closure": 6}
    whole = {r["mode"]: r["cost"] for r in catalog.queries()["tree_exact_steiner"](spark, sf).collect()}
    assert whole["exact"] >= 5 and all(whole["exact"] <= whole[m] <= 2 * whole["exact"] for m in ("voronoi", "closure"))


def test_events_and_scores_need_no_shuffle_beyond_the_lines(spark, sf):
    """Decoding and matching stay in a sentence's row: the lines meet their orders by the only shuffles of a large table, and nothing is kept."""
    base.forget()
    df = catalog.queries()["dec_full"](spark, sf)
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") <= 2 and plan.count("SortMergeJoin") <= 1 and not base._KEPT
    plan = catalog.queries()["score_approx_all"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("hashpartitioning(l_orderkey") <= 1 and plan.count("parquet") > 0 and not base._KEPT


def test_pruning_makes_no_network(spark, sf):
    """Only the terminals are kept on disk, and the nodes are those of the network."""
    base.forget()
    w, found = base.Work(spark, sf), {t: {r["node"] for r in catalog.queries()[f"tree_prune_t{t}"](spark, sf).collect()} for t in (1, 3, 35)}
    assert {k[2] for k in base._KEPT} <= {"codes"}
    for t, got in found.items():
        assert got == {r["node"] for r in tree.kept_nodes(tree.undirected(w.edges), w.terminals, t).collect()}


def test_pruning_counts_neighbours_of_what_no_sentence_names(spark, tmp_path):
    """Lines without a part or an order give no sentence, but their keys are nodes with terminal neighbours; nulls are none."""
    tables = {
        "region": ("r_regionkey int", [(0,)]), "nation": ("n_nationkey int, n_regionkey int", [(0, 0)]),
        "customer": ("c_custkey long, c_name string, c_mktsegment string, c_nationkey int", [(1, "c", "FURNITURE", 0), (2, "d", "FURNITURE", 0)]),
        "supplier": ("s_suppkey long, s_name string, s_nationkey int", [(1, "s", 0), (2, "t", 0)]),
        "part": ("p_partkey long, p_name string, p_brand string", [(1, "red nut", "b"), (2, "red nut", None)]),
        "orders": ("o_orderkey long, o_custkey long", [(1, 1), (2, 1), (2, 2), (3, None)]),
        "lineitem": (
            "l_orderkey long, l_linenumber int, l_partkey long, l_suppkey long, l_extendedprice double, l_shipdate date, l_returnflag string",
            [(o, n, p, s, 1.0, None, "R") for n, (o, p, s) in enumerate([(1, 1, 1), (1, 1, 1), (2, 2, 2), (9, 7, 1), (9, 7, 2), (9, 1, 8), (None, 1, 8), (3, None, 1), (3, 2, None)])],
        ),
    }
    for name, (schema, rows) in tables.items():
        spark.createDataFrame(rows, schema).write.parquet(f"{tmp_path}/{name}.parquet")
    sf, edges = str(tmp_path), kg.concept_edges(spark, str(tmp_path)).filter("src is not null and dst is not null")
    rows = notes.lines(spark, sf)
    codes, terminals = notes.terminal_codes(rows), notes.terminals(rows)
    assert sorted(r["n"] for r in codes.select(notes.name_of(codes["code"]).alias("n")).collect()) == sorted(r["node"] for r in terminals.collect())
    for t in (1, 2, 3, 4):
        got = [r["node"] for r in tree.kept_of_tables(spark, sf, codes, t).collect()]
        assert sorted(got) == sorted(r["node"] for r in tree.kept_nodes(tree.undirected(edges), terminals, t).collect()), t
        assert ("P:7" in got) == (t <= 2) and ("S:8" in got) == (t <= 1)
    cells = sorted(map(tuple, tree.cells_of_tables(spark, sf, codes).collect()))
    assert cells == sorted(map(tuple, tree.voronoi_cells(edges, terminals).select("node", "owner", "dist").collect()))
    assert max(d for _, _, d in cells) > 1


def test_cells_make_no_network(spark, sf):
    base.forget()
    w, got = base.Work(spark, sf), sorted(map(tuple, catalog.queries()["tree_voronoi_owner"](spark, sf).collect()))
    assert {k[2] for k in base._KEPT} <= {"codes"}
    assert got == sorted(map(tuple, tree.voronoi_cells(w.edges, w.terminals).select("node", "owner", "dist").collect()))


def test_forest_from_keys_makes_no_network(spark, sf):
    """Nothing is kept, and the forest is the one over the network: one large tree, terminals beside it, orders, nations and brands."""
    base.forget()
    got = sorted(map(tuple, catalog.queries()["tree_bfs_parents"](spark, sf).collect()), key=repr)
    levels = sorted(map(tuple, catalog.queries()["tree_bfs_levels"](spark, sf).collect()))
    assert not base._KEPT
    assert got == sorted(map(tuple, base.Work(spark, sf).forest.select("node", "parent", "depth", "root").collect()), key=repr)
    assert levels == [(d, sum(r[2] == d for r in got)) for d in range(len(levels))] and {n[0] for n, *_ in got} >= set("CSPONB")


def test_keys_in_the_order_of_their_names():
    import numpy as np

    keys = np.array([0, 1, 10, 100, 9, 99, 12, 2, 10**17, 10**18 - 1, 5 * 10**17, 123456789], np.int64)
    assert [str(k) for k in keys[np.lexsort((keys, keyed.padded(keys)))]] == sorted(map(str, keys))


@pytest.mark.parametrize("name", ["tree_sentence_tree_dfs", "tree_sentence_tree_broadcast", "sg_type_nodes", "sg_without_types"])
def test_sentences_find_their_trees_in_their_own_rows(spark, sf, name, monkeypatch):
    """With a threshold that leaves one tree, nothing is kept, the lines meet their orders by the only large shuffle, and the rows are those of the other form."""
    from graphevents.catalog import graphs

    monkeypatch.setattr(graphs, "THRESHOLD", 3)
    monkeypatch.setattr(base.Work.pruned, "__defaults__", (3,))
    assert keyed.paths_of_tables(spark, sf, 3) is not None
    base.forget()
    df = catalog.queries()[name](spark, sf)
    assert df._jdf.queryExecution().executedPlan().toString().count("Exchange hashpartitioning") <= 2 and not base._KEPT
    got = sorted(map(repr, df.select(*sorted(df.columns)).collect()))
    monkeypatch.setattr(keyed, "paths_of_tables", lambda *_: None)
    base.forget()
    other = catalog.queries()[name](spark, sf)
    assert got == sorted(map(repr, other.select(*sorted(other.columns)).collect())) and len(got) > 5_000
    base.forget()


def test_systems_without_a_graph_keep_nothing(spark, sf, monkeypatch):
    """Their rows come from the lines alone, are those of the graph systems but for the graph, and lead to the same scores."""
    from graphevents import examples, workloads
    from graphevents.model import Config, Extractor

    base.forget()
    monkeypatch.setattr(examples, "graphs", lambda *_, **__: 1 / 0)
    got = examples.plain_rows(spark, sf)
    assert workloads.run_system(spark, sf, "text_only", 2)[0] == "text_only" and not base._KEPT
    monkeypatch.undo()
    whole = examples.rows(spark, sf)
    names = ["sent_id", "split", "forms", "triggers", "entities", "arguments"]
    assert [f.dataType.simpleString() for f in got.schema] == [f.dataType.simpleString() for f in whole.schema]
    assert got.select(*names).orderBy("sent_id").collect() == whole.select(*names).orderBy("sent_id").collect()
    c = workloads.baselines.make_ablation("no_graph", Config(seed=0, patience=2))
    params = [workloads.Trainer(r, c, Extractor(c)).fit(epochs=2, sample=300, dev_sample=100) for r in (got, whole)]
    scores = [workloads.scored(workloads.Trainer(r, c, Extractor(c)), p) for r, p in zip((got, whole), params, strict=True)]
    assert scores[0] == pytest.approx(scores[1])
