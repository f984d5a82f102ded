"""Worked examples, exact baselines and invariants of the tree methods."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from grove import cost
from grove.functions.coins import coin
from grove.operators import baselines as bl
from grove.operators import extras as ex
from grove.operators import rooting
from grove.operators.clique import TooManyPairs, clique_gather, completion_round
from grove.operators.degree import conquer_step, neighbour_independence, reduce_degree, sample_nodes
from grove.operators.gather import binned, colocate, gather, inspace_gather, pack_components
from grove.operators.graph import Forest, component_labels, induced, is_forest, max_degree, require_forest
from grove.operators.labels import contract_labels, flood_labels, minset_labels
from grove.operators.ledger import RoundLedger
from grove.operators.local import Arrays, greedy, larger_class, maximum, per_task
from grove.operators.pointers import jump_to_root
from grove.operators.rooting import budget_round, growth_rounds, root_forest, tree_edges
from grove.operators.shatter import shatter
from grove.operators.verify import certify_mis
from grove.params import TreeMisParams
from grove.plans import catalog
from grove.plans.tree_mis import tree_mis, with_hub_cleanup
from grove.plans.workloads import path_forest
from grove.sources.forests import forest_of


def graph(spark, edges, nodes=()):
    e = spark.createDataFrame(list(edges) or [(0, 0)], "src long, dst long")
    n = spark.createDataFrame([(v,) for v in nodes] or [(0,)], "v long")
    return Forest.of(e if edges else e.limit(0), n if nodes else n.limit(0))


def path(spark, n):
    return graph(spark, [(i, i + 1) for i in range(n - 1)], range(n))


def random_tree(n, seed):
    r = random.Random(seed)
    return [(i, r.randrange(i)) for i in range(1, n)]


def certified(g, s):
    c = certify_mis(g, s).first()
    return c.inside_edges == 0 and c.undominated == 0


def test_dirty_edges(spark):
    g = graph(spark, [(1, 2), (2, 1), (1, 1), (2, 3), (2, 3), (9, 9)], [7])
    assert sorted(r.v for r in g.nodes.collect()) == [1, 2, 3, 7, 9]
    assert sorted(map(tuple, g.edges.collect())) == [(1, 2), (2, 1), (2, 3), (3, 2)]


def test_coin_is_the_fixed_one(spark):
    got = [r.c for r in spark.range(3).select(coin("id", 7, 1).alias("c")).collect()]
    assert got == [4031354885014499, 1880813299708690, 1993193191362718]


@pytest.mark.parametrize("d", [1, 2, 3, 4, 5, 9, 17])
def test_clique_rounds_exact(spark, d):
    ledger = RoundLedger()
    labels = clique_gather(path(spark, d + 1), ledger)
    assert ledger.rounds() == max(0, (d - 1).bit_length()) + 1
    assert ledger.copies() <= (d + 1) ** 3
    assert {r.leader for r in labels.collect()} == {0}


def test_completion_squares_a_path(spark):
    g = path(spark, 9)
    added = {tuple(sorted((r.src, r.dst))) for r in completion_round(g.edges, g.edges).collect()}
    assert added == {(i, i + 2) for i in range(7)}


def test_labels_agree_on_a_cyclic_graph(spark):
    edges = [(1, 2), (2, 3), (3, 4), (4, 1), (10, 11), (-5, 20)]
    g = graph(spark, edges, [99])
    want = {1: 1, 2: 1, 3: 1, 4: 1, 10: 10, 11: 10, -5: -5, 20: -5, 99: 99}
    for run in (clique_gather, flood_labels, minset_labels, contract_labels, component_labels):
        assert dict(map(tuple, run(g).select("v", "leader").collect())) == want, run
    with pytest.raises(ValueError):
        require_forest(g)


def test_star_rounds_beyond_one_block(spark):
    from grove.operators.components import star_components

    e = spark.createDataFrame(random_tree(60, 3), "src long, dst long")
    got = star_components(e, block=7).collect()
    assert len(got) == 60 and {r.leader for r in got} == {0}


@pytest.mark.parametrize("n,budget,seed", [(1, 8, 0), (2, 8, 0), (3, 1000, 1), (10, 4, 2), (25, 64, 3), (25, 2, 4), (40, 1000, 5)])
def test_rooting_bruteforce(spark, n, budget, seed):
    edges = random_tree(n, seed)
    g = graph(spark, edges, range(n)).cut()
    parents = {r.v: r.parent for r in root_forest(g, budget).collect()}
    assert set(parents) == set(range(n))
    roots = [v for v, p in parents.items() if v == p]
    assert len(roots) == 1
    assert {tuple(sorted((v, p))) for v, p in parents.items() if v != p} == {tuple(sorted(e)) for e in edges}


def test_six_node_star_and_pair(spark):
    star = graph(spark, [(0, i) for i in range(1, 6)])
    parents = {r.v: r.parent for r in root_forest(star.cut(), 1000).collect()}
    assert [v for v, p in parents.items() if v == p] == [5]
    pair = {r.v: r.parent for r in root_forest(graph(spark, [(3, 8)]).cut(), 8).collect()}
    assert pair[8] == 8 and pair[3] == 8


def test_cubic_tree_first_phase(spark):
    edges = [(k, (k - 1) // 2) for k in range(1, 120)]
    ledger = RoundLedger()
    root_forest(graph(spark, edges).cut(), 2, ledger=ledger, strict_budget=True)
    assert ledger.rows[0][6] == 120 and ledger.rows[1][6] == 29 and ledger.rows[1][7] == 8
    assert all(r[6] * r[7] <= 240 for r in ledger.rows)


def test_budget_round_pays_or_waits(spark):
    g = graph(spark, [(0, 1), (0, 2), (0, 3), (3, 4)])
    new, spent = budget_round(tree_edges(g.edges), g.nodes.withColumn("left", F.lit(2).cast("long")))
    assert {(r.x, r.n) for r in spent.collect()} == {(3, 1)}
    assert {tuple(r) for r in new.collect()} == {(0, 4, 3, 3), (4, 0, 3, 3)}


def test_pointer_rounds_and_cycle(spark):
    ledger = RoundLedger()
    got = {r.v: (r.root, r.depth) for r in jump_to_root(path_forest(spark, (16,)), ledger).collect()}
    assert got[16] == (0, 16) and ledger.rounds() == 4
    with pytest.raises(ValueError):
        jump_to_root(spark.createDataFrame([(1, 2), (2, 1)], "v long, parent long"), max_rounds=6)


def test_gather_ways_agree(spark):
    g = graph(spark, random_tree(15, 8) + [(100 + a, 100 + b) for a, b in random_tree(6, 9)], [500]).cut()
    want = sorted(map(tuple, component_labels(g).collect()))
    for how in ("clique", "inspace", "label", "auto"):
        assert sorted(map(tuple, gather(g, how).select("v", "leader").collect())) == want


def test_neighbour_independence(spark):
    g = graph(spark, random_tree(80, 4)).cut()
    r = neighbour_independence(g, sample_nodes(g.nodes, 3, 1.0, 7))
    assert r.where("sampled_neighbours <> components").count() == 0


@pytest.mark.parametrize("how", ["clique", "inspace"])
def test_conquer_step(spark, how):
    g = graph(spark, random_tree(60, 5)).cut()
    p = TreeMisParams(gather=how)
    chosen, rest, row = conquer_step(g, p, 0, max_degree(g))
    assert induced(g, chosen).edges.count() == 0
    sampled = sample_nodes(g.nodes, max_degree(g), p.sampling_exponent(), p.seed, 0)
    assert sampled.join(rest.nodes, "v", "left_semi").count() == 0 and row["delta_after"] <= max_degree(g)


@pytest.mark.parametrize("edges,nodes", [([], [1]), ([], [1, 2]), ([(0, 1)], []), ([(0, i) for i in range(1, 30)], []), (random_tree(50, 6), [900])])
def test_tree_mis(spark, edges, nodes):
    g = graph(spark, edges, nodes)
    for how in ("clique", "inspace"):
        assert certified(g, tree_mis(g, gather=how, hub_cleanup=False))


def test_empty_graph(spark):
    g = graph(spark, [])
    assert tree_mis(g).count() == 0 and bl.priority_mis(g).count() == 0 and component_labels(g).count() == 0


def test_hub_passes(spark):
    g = graph(spark, [(0, i) for i in range(1, 40)] + [(39, i) for i in range(40, 70)]).cut()
    out, left = with_hub_cleanup(g, TreeMisParams(mem_exp=0.5, gather="label"))
    n = g.nodes.count()
    assert certified(g, out) and left[0] <= 2 * (n - 1) / TreeMisParams().hub_degree(n) and left[-1] == 0


def test_partitioning_does_not_matter(spark):
    edges = random_tree(40, 11)
    a = graph(spark, edges)
    b = Forest(a.nodes.repartition(7), a.edges.repartition(3))
    get = lambda g: sorted(r.v for r in tree_mis(g, gather="clique").collect())
    assert get(a) == get(b)


def test_baselines(spark):
    edges = random_tree(40, 12)
    g = graph(spark, edges).cut()
    parents = spark.createDataFrame([(0, 0), *edges], "v long, parent long")
    for run in (bl.solo_mis, bl.priority_mis, bl.marking_mis, bl.tree_local_mis, bl.prefix_greedy_mis, bl.ball_gather_mis, lambda g: bl.rooted_mis(g, parents)):
        assert certified(g, run(g)), run
    colours = {r.v: r.c for r in bl.rooted_three_colour(parents).collect()}
    assert set(colours.values()) <= {0, 1, 2} and all(colours[a] != colours[b] for a, b in edges)


def test_balls_are_the_desire_process(spark):
    g = graph(spark, random_tree(60, 17)).cut()
    direct, _ = shatter(g, 60)
    for rounds in (1, 2):
        assert {r.v for r in bl.ball_gather_mis(g, rounds).collect()} == {r.v for r in direct.collect()}
    with pytest.raises(ValueError):
        bl.ball_gather_mis(g, 1, most_pairs=10)
    with pytest.raises(ValueError):
        bl.prefix_greedy_mis(g, most_rows=5)


def test_fixed_order_is_sequential_greedy(spark):
    edges = random_tree(30, 13)
    g = graph(spark, edges)
    order = {r.v: r.c for r in g.nodes.select("v", coin("v", 7, "priority0").alias("c")).collect()}
    want = bl.sequential_greedy(list(range(30)), edges, order)
    assert {r.v for r in bl.priority_mis(g, fresh=False).collect()} == want
    rank = {r.v: r.c for r in g.nodes.select("v", coin("v", 7, "rank").alias("c")).collect()}
    assert {r.v for r in bl.prefix_greedy_mis(g).collect()} == bl.sequential_greedy(list(range(30)), edges, rank)


def test_local_solvers():
    for seed in range(6):
        edges = np.array(random_tree(30, seed))
        t = Arrays(np.arange(30), np.concatenate([edges[:, 0], edges[:, 1]]), np.concatenate([edges[:, 1], edges[:, 0]]))
        best = maximum(t)
        for s in (greedy(t), larger_class(t), best):
            assert not (s[t.src] & s[t.dst]).any()
            assert s.sum() <= best.sum()
        near = [set() for _ in range(30)]
        for a, b in edges:
            near[a].add(b), near[b].add(a)
        take, skip = [1] * 30, [0] * 30
        for v in range(29, 0, -1):
            p = [a for a, b in zip(edges[:, 1], edges[:, 0], strict=True) if b == v][0]
            take[p] += skip[v]
            skip[p] += max(take[v], skip[v])
        assert best.sum() == max(take[0], skip[0])


def test_packing_holds_capacity(spark):
    sizes = spark.createDataFrame([(i, 1 + i * 7 % 50) for i in range(300)], "leader long, size long")
    loads = pack_components(sizes, 50).groupBy("bin").agg(F.sum("size").alias("s"))
    assert loads.where("s > 50").count() == 0 and loads.agg(F.sum("s")).first()[0] == sizes.agg(F.sum("size")).first()[0]
    with pytest.raises(ValueError):
        pack_components(sizes, 10)


def test_extras(spark):
    g = graph(spark, [(0, 1), (1, 2), (2, 3), (3, 0), (3, 4)]).cut()
    m = ex.maximal_matching(g).collect()
    ends = [v for r in m for v in (r.src, r.dst)]
    assert len(ends) == len(set(ends)) and all(r.src in ends or r.dst in ends for r in g.edges.collect())
    c = {r.v: r.c for r in ex.degree_colouring(g).collect()}
    assert all(c[r.src] != c[r.dst] for r in g.edges.collect()) and max(c.values()) <= 3
    e = ex.edge_colouring(g).collect()
    assert len(e) == 5 and max(r.c for r in e) <= 4
    p = spark.createDataFrame([(0, 0), *random_tree(20, 14)], "v long, parent long")
    assert ex.diameters(p, None).count() == 1


def test_reduction_reaches_floor(spark):
    edges = [(k, (k - 1) // 20) for k in range(1, 300)]
    _, rest, trace = reduce_degree(graph(spark, edges).cut(), TreeMisParams(gather="label", degree_floor=4))
    assert max_degree(rest) <= 4 and all(a <= b for _, b, a, *_ in trace)


def test_inspace_equals_clique(spark):
    g = graph(spark, random_tree(20, 21)).cut()
    assert sorted(map(tuple, inspace_gather(g, 8).select("v", "leader").collect())) == sorted(map(tuple, clique_gather(g).collect()))


def test_bins_bound_a_task(spark):
    """One giant component and many small ones: a task's nodes are bounded but for the giant."""
    small = [(10_000 + 10 * i, 10_000 + 10 * i + 1) for i in range(300)]
    g = graph(spark, [(i, i + 1) for i in range(500)] + small).cut()
    labels = component_labels(g)
    bins = binned(labels, 64).groupBy("bin").agg(F.count("*").alias("n"), F.countDistinct("leader").alias("k")).collect()
    assert sorted(r.n for r in bins)[-1] == 501 and all(r.n <= 64 for r in bins if r.n != 501) and sum(r.k for r in bins) == 301
    seen = per_task(g, labels, lambda t: {"v": t.ids, "n": np.full(len(t.ids), len(t.ids))}, "v long, n long", capacity=64).toPandas()
    assert len(seen) == 501 + 600 and sorted(seen.n.unique())[-1] == 501 and (seen.n[seen.v >= 10_000] <= 64).all()
    with pytest.raises(ValueError):
        binned(labels, 64, strict=True)
    lay = colocate(g.nodes, labels, capacity=64).select("leader", "bin", F.input_file_name().alias("f")).groupBy("bin").agg(F.countDistinct("f").alias("files")).agg(F.max("files")).first()[0]
    assert lay == 1


def test_rooting_of_a_large_forest_under_adaptive_plans(spark):
    """60,000 nodes read by several tasks, the session's own settings: one root a tree, pointers along edges."""
    g = catalog.forest(spark, "/root/testdata/sf0.01", "F4")
    g = Forest(g.nodes.repartition(7), g.edges.repartition(9))
    assert g.nodes.count() > 50_000
    got = catalog.rooting_certificate(g, root_forest(g, 27, diameter=32)).first()
    assert got.pointed == got.n_nodes and got.roots == got.trees and got.edges_used == got.n_nodes - got.trees


def test_split_rows_are_noticed():
    src, dst, back = np.array([1, 1]), np.array([2, 4]), np.array([1, 3])
    with pytest.raises(RuntimeError):
        rooting._pairs_of(src, dst, back)


def test_auto_gives_completion_up(spark):
    star = graph(spark, [(0, i) for i in range(1, 60)]).cut()
    assert {r.leader for r in gather(star, "auto", most_pairs=100).collect()} == {0}
    with pytest.raises(TooManyPairs):
        clique_gather(star, most_pairs=100)


def test_ledger_measures(spark):
    g = graph(spark, [(i, i + 1) for i in range(40)]).cut()
    ledger = RoundLedger(machines=8)
    with ledger.measuring():
        jump_to_root(spark.createDataFrame([(0, 0)] + [(i + 1, i) for i in range(40)], "v long, parent long"), ledger)
    assert ledger.exchanges() >= ledger.rounds() and 41 / 8 <= ledger.max_load() <= 41 and ledger.busiest <= 2 * 41
    assert g.nodes.count() == 41


def test_cost_model(spark):
    assert cost.mpc_plan("inspace", 10**6)[2:] == (1000, 1000, 10**6)
    assert growth_rounds(10) == 5 and is_forest(path(spark, 4))
