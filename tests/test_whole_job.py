"""Whole tables and every size: no id subset, no refusal."""

import numpy as np
import pandas as pd
import pytest

from grove.operators import extras
from grove.operators.graph import Forest
from grove.plans import catalog
from grove.session import table
from grove.sources import forests


def test_upkeep_holds_every_event(spark, sf):
    e = pd.read_parquet(f"{sf}/events.parquet")
    got = catalog.queries()["stream_set_upkeep"](spark, sf).first()
    assert len(e) > 200
    assert got.asDict() == {"n_nodes": len(e), "n_edges": len(e) - e.user_id.nunique(), "inside_edges": 0, "undominated": 0}


def test_vectors_beyond_the_old_cap(spark, tmp_path):
    rng = np.random.default_rng(3)
    x = rng.integers(-3, 4, (5200, 3)).astype(np.float32)  # many ties
    x[:, 0] += 0.5
    pd.DataFrame({"vec_id": np.arange(5200), "embedding": list(x)}).to_parquet(tmp_path / "embeddings.parquet")
    got = {r.v: r.parent for r in forests.nearest_earlier_tree(spark, f"file://{tmp_path}").collect()}
    y = x.astype(float)
    n = np.sqrt(y[:, 0] ** 2 + y[:, 1] ** 2 + y[:, 2] ** 2)
    assert len(got) == 5200 and got[0] == 0
    for a in range(1, 5200):
        cos = (y[a, 0] * y[:a, 0] + y[a, 1] * y[:a, 1] + y[a, 2] * y[:a, 2]) / (n[a] * n[:a])
        assert got[a] == int(cos.argmax()), a
    one = forests.vector_neighbours(spark, f"file://{tmp_path}").where("src = 4000").toPandas().dst.tolist()
    cos = (y[4000] @ y.T) / (n[4000] * n)
    assert len(one) == 5 and 4000 not in one and cos[one].min() > np.sort(np.delete(cos, 4000))[-6] - 1e-12


def test_line_graph_of_many_short_paths(spark):
    e = spark.createDataFrame([(i, i + 1) for i in range(50)], "src long, dst long")
    assert extras.line_graph(Forest.of(e), most=10)[1].edges.count() == 98
    star = spark.createDataFrame([(0, i) for i in range(1, 30)], "src long, dst long")
    with pytest.raises(ValueError):
        extras.line_graph(Forest.of(star), most=10, per_edge=2)


def test_every_leaf_and_hub(spark, sf):
    p = pd.read_parquet(f"{sf}/part.parquet")
    hubs = (-p.p_brand.str.extract("([0-9]+)")[0].astype(int)).value_counts()
    want = {(int(v), 1, True) for v in p.p_partkey} | {(int(v), int(n), n == 1) for v, n in hubs.items() if n == 1 or n >= 5}
    assert {tuple(r) for r in catalog.queries()["rel_filter_predicates"](spark, sf).collect()} == want
