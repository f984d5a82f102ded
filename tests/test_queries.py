"""Registered queries against their SQL on the smallest tables, and edge files in and out."""

import duckdb
import pytest

import __spark_entry__ as entry
from grove.operators.graph import Forest
from grove.plans import catalog
from grove.session import table
from grove.sources import io

NAMES = [
    "root_and_depth", "forest_edges_F1", "forest_edges_F6", "forest_edges_F9", "graph_edges_G2", "sampled_component_report", "shatter_round", "priority_round", "bit_reduction_round", "budget_round_F4",
    "clique_gather_G1", "rooting_cert_F8", "tree_mis_clique_F2", "small_subtree_lemma", "rel_range_join", "rel_as_of_join", "rel_rollup", "udtf_tree_paths", "stream_chain_edges", "predicted_rounds",
]


def rows(cols, got):
    order = sorted(range(len(cols)), key=lambda i: cols[i])
    return sorted([tuple(None if x is None else float(x) if isinstance(x, (int, float)) and not isinstance(x, bool) else str(x) for x in (r[i] for i in order)) for r in got], key=str)


@pytest.mark.parametrize("name", NAMES)
def test_against_sql(spark, sf, name):
    con = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    c = con.execute(catalog.oracle_sql()[name])
    cols = [x[0] for x in c.description]
    df = catalog.queries()[name](spark, sf)
    assert sorted(df.columns) == sorted(cols)
    assert rows(df.columns, df.collect()) == rows(cols, c.fetchall())


def test_every_sql_has_its_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("fmt", ["parquet", "csv", "tsv", "json", "orc", "text"])
def test_edge_files(spark, tmp_path, fmt):
    e = spark.createDataFrame([(1, 2), (2, 3)], "src long, dst long")
    io.write_edges(e, str(tmp_path / fmt), fmt)
    assert sorted(map(tuple, io.read_edges(spark, str(tmp_path / fmt), fmt).collect())) == [(1, 2), (2, 3)]


def test_labels_by_bucket(spark, tmp_path, sf):
    from grove.operators.graph import component_labels

    g = Forest.of(table(spark, sf, "orders").selectExpr("o_orderkey as src", "o_custkey + 1000000 as dst").limit(50))
    io.write_labels(component_labels(g), str(tmp_path / "labels"), buckets=4)
    assert spark.read.parquet(str(tmp_path / "labels")).count() == g.nodes.count()
