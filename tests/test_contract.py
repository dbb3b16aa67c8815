"""Registered queries against their SQL on the smallest tables, and the plans they should have."""

import math
import os

import duckdb
import pandas as pd
import pytest

import __spark_entry__ as entry
from graphevents import catalog
from graphevents.plans import choose_dictionary, physical

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
CHOSEN = ["kg_concept_edges", "kg_type_network", "kg_relsets", "ground_matches_longest", "ground_disambiguated", "ground_benchmark_phrases", "tree_prune_t10", "tree_bfs_parents", "tree_sentence_tree", "tree_voronoi_links", "sg_edges_merged", "gnn_edge_softmax_layer2", "gnn_edge_conv_matrix", "gnn_node_attention_fixed", "dec_full", "score_by_group_rollup", "score_confusion", "op_join_as_of", "op_join_range", "op_agg_pivot", "stream_tumbling"]


def shown(v):
    if v is None or v is pd.NaT or v is pd.NA or (isinstance(v, float) and math.isnan(v)):
        return None
    if isinstance(v, pd.Timestamp):
        return str(v)
    v = v.item() if hasattr(v, "item") else v
    return (int(v) if float(v).is_integer() else round(v, 6)) if isinstance(v, (float, bool)) else v


def rows(df):
    df = df[sorted(df.columns)]
    return list(df.columns), sorted((tuple(map(shown, r)) for r in df.itertuples(index=False)), key=repr)


@pytest.fixture(scope="module")
def duck(sf):
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", CHOSEN)
def test_query_equals_sql(spark, sf, duck, name):
    assert rows(catalog.queries()[name](spark, sf).toPandas()) == rows(duck.sql(catalog.oracle_sql()[name]).df())


def test_entry(spark):
    df = entry.entry(spark)
    assert df.columns == ["g", "n", "dim", "x"] and df.count() > 0


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_plans(spark, sf):
    plan = physical(catalog.queries()["ground_matches_all"](spark, sf))
    assert "CartesianProduct" not in plan
    plan = physical(catalog.queries()["op_pushed_filter"](spark, sf))
    assert "PushedFilters: [IsNotNull(l_shipdate)" in plan and "l_extendedprice" not in plan.split("ReadSchema")[1].split("\n")[0]


def test_choices(spark, sf):
    assert choose_dictionary(spark.range(10)).form == "trie"
    assert choose_dictionary(spark.range(10), limit=1).form == "join"


def test_the_core_does_not_import_the_corpus_operators():
    top = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    for folder, _, files in os.walk(os.path.join(top, "graphevents")):
        if "llm" not in folder.split(os.sep):
            for f in files:
                if f.endswith(".py"):
                    text = open(os.path.join(folder, f)).read()
                    assert "graphevents.llm" not in text and "from .llm" not in text and "from ..llm" not in text
