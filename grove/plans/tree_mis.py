"""A maximal independent set of a forest, end to end.

Hub clean-up, degree reduction, shattering, and a local finish of what is left. Every
part returns an independent set of what it was given and removes it with its
neighbours, so their union is independent, and the finish makes it maximal.
"""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame

from grove.operators.degree import reduce_degree
from grove.operators.gather import gather
from grove.operators.graph import Forest, induced, max_degree, remove_closed, split_by_degree
from grove.operators.ledger import RoundLedger
from grove.operators.local import solve_components
from grove.operators.shatter import shatter
from grove.params import TreeMisParams
from grove.session import Parts, cut, drop_cut


def finish(g: Forest, how: str = "auto", local: str = "greedy", diameter: int = 16, ledger: RoundLedger | None = None) -> DataFrame:
    """(v): gather what is left and solve each component in its task."""
    labels = cut(gather(g, how, diameter, ledger=ledger), "labels")
    if ledger is not None:
        ledger.record("finish", rounds=1, live=0)
    return cut(solve_components(g, labels, local), "finish")


def _core(g: Forest, params: TreeMisParams, ledger: RoundLedger | None) -> DataFrame:
    first, g, _ = reduce_degree(g, params, ledger)
    second, g = shatter(g, params.rounds_for(max_degree(g)), params.seed, ledger)
    found = first.unionByName(second)
    return cut(found.unionByName(finish(g, params.gather, params.local, params.diameter, ledger)) if g.nodes.limit(1).count() else found, "mis")


def with_hub_cleanup(g: Forest, params: TreeMisParams, ledger: RoundLedger | None = None) -> tuple[DataFrame, list[int]]:
    """(set, hubs left after each pass): solve the nodes below the hub degree, remove the set
    with its neighbours, and go on with what survives, which was hubs only."""
    n, parts, left, old = g.nodes.count(), Parts(g.nodes.sparkSession, "passes", "v long"), [], []
    for _ in range(64):
        live = g.nodes.count()
        if live == 0:
            break
        low, _ = split_by_degree(g, params.hub_degree(n))
        sub = induced(g, low).cut()
        if sub.nodes.count() == 0:
            raise RuntimeError("no node is below the hub degree; the graph is not a forest")
        new = parts.add(_core(sub, params, ledger))
        g = remove_closed(g, new).cut()
        drop_cut(sub.nodes, sub.edges, *old)
        old = [g.nodes, g.edges]
        left.append(g.nodes.count())
        if ledger is not None:
            ledger.record("hub_pass", rounds=1, live=left[-1])
    return parts.frame(), left


def tree_mis(g: Forest, params: TreeMisParams | None = None, ledger: RoundLedger | None = None, **options) -> DataFrame:
    """(v): a maximal independent set. ``gather`` is clique, inspace or auto; hub clean-up runs by
    itself when the maximum degree reaches n^(mem_exp / 2) and ``hub_cleanup`` is not set."""
    params = replace(params or TreeMisParams(), **options)
    g = g.cut()
    n, deg = g.nodes.count(), max_degree(g)
    hubs = params.hub_cleanup if params.hub_cleanup is not None else deg >= params.hub_degree(n) and deg > params.floor_for(n)
    if hubs:
        return with_hub_cleanup(g, params, ledger)[0]
    return _core(g, params, ledger)
