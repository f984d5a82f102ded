"""Experiment workloads: the claims about rounds, memory and degrees, put to the test on the given tables.

The reference reports no measurements. A workload measures (subject, measure, value) and
draws claims (subject, claim, holds) from it; its query returns the claims, whose SQL is
that all of them hold. ``measures`` gives the figures behind them:

    python -m grove.plans.workloads /root/testdata/sf0.01 w2_degree_decay_F6
"""

from __future__ import annotations

import math
import sys
from collections.abc import Callable
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from grove import cost
from grove.operators import baselines as bl
from grove.operators.clique import TooManyPairs, clique_gather
from grove.operators.degree import neighbour_independence, reduce_degree, sample_nodes
from grove.operators.extras import diameters, tree_max_independent_set
from grove.operators.gather import binned, pack_components
from grove.operators.graph import Forest, component_labels, degrees, induced, max_degree
from grove.operators.labels import contract_labels, flood_labels, minset_labels
from grove.operators.ledger import RoundLedger
from grove.operators.pointers import jump_to_root
from grove.operators.rooting import root_forest
from grove.operators.shatter import leftover_sizes, shatter
from grove.operators.verify import certify_mis
from grove.params import TreeMisParams
from grove.plans.tree_mis import finish, tree_mis, with_hub_cleanup
from grove.session import cut, table
from grove.sources import forests as fs

MACHINES = 16
PARENTS = fs.FORESTS | {"F7(2)": lambda s, d: fs.ary_tree(s, d, 2), "F7(300)": lambda s, d: fs.ary_tree(s, d, 300)}


@dataclass
class Findings:
    """What a workload measured and what follows from it."""

    measures: list[tuple[str, str, float]] = field(default_factory=list)
    claims: list[tuple[str, str, bool]] = field(default_factory=list)

    def saw(self, subject: str, **values: float) -> None:
        self.measures += [(subject, k, float(v or 0)) for k, v in values.items()]

    def claim(self, subject: str, text: str, holds: bool) -> None:
        self.claims.append((subject, text, bool(holds)))


#: name -> (run(spark, folder) -> Findings, the claims that it makes)
WORKLOADS: dict[str, tuple[Callable[[SparkSession, str], Findings], list[tuple[str, str]]]] = {}


def workload(name: str, claims: list[tuple[str, str]], **given):
    def keep(run):
        WORKLOADS[name] = (lambda s, d: run(s, d, **given), claims)
        return run

    return keep


def query(name: str) -> Callable[[SparkSession, str], DataFrame]:
    return lambda s, d: s.createDataFrame([(name, *c) for c in WORKLOADS[name][0](s, d).claims], "workload string, subject string, claim string, holds boolean")


def sql(name: str) -> str:
    rows = ", ".join(f"('{name}', '{a}', '{b}', true)" for a, b in WORKLOADS[name][1])
    return f"select * from (values {rows}) t(workload, subject, claim, holds)"


def measures(s: SparkSession, d: str, name: str) -> DataFrame:
    return s.createDataFrame(WORKLOADS[name][0](s, d).measures, "subject string, measure string, value double")


def forest(s: SparkSession, d: str, f: str) -> Forest:
    return fs.forest_of(PARENTS[f](s, d)).cut()


MIS, LOAD = "maximal independent set", "no machine over its bound"


def _solved(out: Findings, subject: str, g: Forest, run: Callable[[Forest, RoundLedger], DataFrame]) -> RoundLedger:
    ledger = RoundLedger(machines=MACHINES)
    with ledger.measuring():
        got = cut(run(g, ledger), "set")
    c = certify_mis(g, got).first()
    out.saw(subject, rounds=ledger.rounds(), exchanges=ledger.exchanges(), copies=ledger.copies(), largest_load=ledger.max_load(), rows_moved=sum(r[4] for r in ledger.rows), size=got.count())
    out.claim(subject, MIS, c.inside_edges == 0 and c.undominated == 0)
    return ledger


def w1_tree(s: SparkSession, d: str, f: str) -> Findings:
    """Both variants of the solver; no logical machine may hold more than its bound."""
    out, g = Findings(), forest(s, d, f)
    n, deg = g.nodes.count(), max_degree(g)
    for how in ("clique", "inspace"):
        # a sampled component's edges are what gathering holds beside the graph's own
        ledger = _solved(out, f"{f} {how}", g, lambda g, led, how=how: tree_mis(g, ledger=led, gather=how, diameter=8))
        out.claim(f"{f} {how}", LOAD, ledger.max_load() <= cost.load_bound(2 * n, MACHINES, deg))
    return out


def w1_baselines(s: SparkSession, d: str, f: str) -> Findings:
    out, g = Findings(), forest(s, d, f)
    runs = {"solo": lambda g, led: bl.solo_mis(g), "priority": lambda g, led: bl.priority_mis(g, ledger=led), "tree local": lambda g, led: bl.tree_local_mis(g, ledger=led), "prefix": lambda g, led: bl.prefix_greedy_mis(g, ledger=led)}
    if f in ("F5", "F7"):  # balls of a tree with hubs hold most of it
        runs["ball"] = lambda g, led: bl.ball_gather_mis(g, 1, ledger=led)
    for name, run in runs.items():
        _solved(out, f"{f} {name}", g, run)
    return out


for _f in ("F1", "F2", "F5", "F6", "F7"):
    workload(f"w1_tree_{_f}", [(f"{_f} {h}", c) for h in ("clique", "inspace") for c in (MIS, LOAD)], f=_f)(w1_tree)
    workload(f"w1_baselines_{_f}", [(f"{_f} {m}", MIS) for m in ("solo", "priority", "tree local", "prefix", *(["ball"] if _f in ("F5", "F7") else []))], f=_f)(w1_baselines)

DECAYS = (0.25, 0.5, 1.0)


def w2_degree_decay(s: SparkSession, d: str, f: str) -> Findings:
    out, g = Findings(), forest(s, d, f)
    for decay in DECAYS:
        p = TreeMisParams(decay=decay)
        trace = reduce_degree(g, p)[2]
        for step, before, after, sampled, largest, live in trace:
            out.saw(f"{f} decay {decay} step {step}", delta_before=before, delta_after=after, predicted=before ** (1 / (1 + decay)), sampled=sampled, max_component=largest, live=live)
        out.claim(f"{f} decay {decay}", "the degree never rises", all(t[2] <= t[1] for t in trace))
        out.claim(f"{f} decay {decay}", "the degree ends at the floor", not trace or trace[-1][2] <= p.floor_for(g.nodes.count()))
    return out


for _f in ("F2", "F6", "F7(300)"):
    workload(f"w2_degree_decay_{_f}", [(f"{_f} decay {x}", c) for x in DECAYS for c in ("the degree never rises", "the degree ends at the floor")], f=_f)(w2_degree_decay)


@workload("w3_independence", [(f, "sampled neighbours lie in different components") for f in ("F2", "F6")])
def w3_independence(s: SparkSession, d: str) -> Findings:
    out = Findings()
    for f in ("F2", "F6"):
        g = forest(s, d, f)
        r = neighbour_independence(g, sample_nodes(g.nodes, 50, 1.0, 7)).agg(F.count("*").alias("n"), F.sum((F.col("sampled_neighbours") != F.col("components")).cast("int")).alias("bad"), F.max("components").alias("most")).first()
        out.saw(f, nodes=r.n, dependent=r.bad, most_components=r.most)
        out.claim(f, "sampled neighbours lie in different components", not r.bad)
    return out


def path_forest(s: SparkSession, lengths: tuple[int, ...]) -> DataFrame:
    """Parents of one path for each number of edges."""
    base = s.createDataFrame([(i * 1_000_000, n) for i, n in enumerate(lengths)], "o long, n int")
    return base.select("o", F.explode(F.sequence(F.lit(0), F.col("n"))).alias("k")).select((F.col("o") + F.col("k")).alias("v"), (F.col("o") + F.greatest(F.lit(0), F.col("k") - 1)).alias("parent"))


def _rounds(d: int) -> int:
    return max(0, (d - 1).bit_length()) + 1


@workload("w4_gather_rounds", [(x, c) for x in ("path 1", "path 2", "path 5", "path 33", "F8", "F3") for c in ("ceil(log2 d) + 1 rounds", "copies within the cubes")])
def w4_gather_rounds(s: SparkSession, d: str) -> Findings:
    out = Findings()
    for name, parents in [*((f"path {n}", path_forest(s, (n,))) for n in (1, 2, 5, 33)), ("F8", fs.turn_paths(s, d)), ("F3", fs.event_chains(s, d))]:
        p, ledger = cut(parents, "parents"), RoundLedger()
        labels = cut(clique_gather(fs.forest_of(p), ledger), "labels")
        far = diameters(p, None).agg(F.max("diameter")).first()[0]
        k3 = labels.groupBy("leader").count().agg(F.sum(F.pow("count", F.lit(3)))).first()[0]
        out.saw(name, diameter=far, rounds=ledger.rounds(), copies=ledger.copies(), k3=k3)
        out.claim(name, "ceil(log2 d) + 1 rounds", ledger.rounds() == _rounds(far))
        out.claim(name, "copies within the cubes", ledger.copies() <= k3)
    return out


@workload("w5_copies", [(x, c) for x in ("F3", "F8", "F1 sampled") for c in ("completion within the cubes", "in space within the budget", "in space copies no more than completion")])
def w5_copies(s: SparkSession, d: str) -> Findings:
    """Copies of completion against rooting in space on the same forest."""
    out, f1 = Findings(), forest(s, d, "F1")
    for name, g in (("F3", forest(s, d, "F3")), ("F8", forest(s, d, "F8")), ("F1 sampled", induced(f1, sample_nodes(f1.nodes, 4, 1.0, 7)).cut())):
        a, b = RoundLedger(), RoundLedger()
        labels = cut(clique_gather(g, a), "labels")
        root_forest(g, 4, ledger=b)
        k3 = labels.groupBy("leader").count().agg(F.sum(F.pow("count", F.lit(3)))).first()[0]
        out.saw(name, completion_copies=a.copies(), k3=k3, completion_rounds=a.rounds(), in_space_copies=b.copies(), in_space_rounds=b.rounds())
        out.claim(name, "completion within the cubes", a.copies() <= k3)
        out.claim(name, "in space within the budget", all(r[8] <= r[6] * r[7] for r in b.rows))
        out.claim(name, "in space copies no more than completion", b.copies() <= a.copies())
    return out


PHASES = ("live nodes times budget never above the start", "copies within live nodes times budget", "every phase removes nodes")
SHARE = "every phase removes sqrt(B) / (d + sqrt(B)) of the nodes"


def w6_phases(s: SparkSession, d: str, f: str, budget: int | None) -> Findings:
    """One budget of rooting, the cubed diameter if none is given. Completing single trees of n nodes makes n^2 rows,
    so F5 and F7(2), where the in-space condition n d^3 = O(n) fails, have no cubed diameter."""
    p = cut(PARENTS[f](s, d), "parents")
    g, out = fs.forest_of(p).cut(), Findings()
    n0, far = g.nodes.count(), diameters(p, g).agg(F.max("diameter")).first()[0] or 0
    b, ledger = budget or max(2, far**3), RoundLedger()
    root_forest(g, b, far, ledger)
    name = f"{f} budget {budget or 'cubed diameter'}"
    for i, r in enumerate(ledger.rows):
        out.saw(f"{name} phase {i}", live=r[6], budget=r[7], copies=r[8], removed=r[9], bound=math.sqrt(r[7]) / (far + math.sqrt(r[7])) * r[6])
    out.claim(name, PHASES[0], all(r[6] * r[7] <= n0 * b for r in ledger.rows))
    out.claim(name, PHASES[1], all(r[8] <= r[6] * r[7] for r in ledger.rows))
    out.claim(name, PHASES[2], all(r[9] > 0 for r in ledger.rows))
    if budget is None:
        out.claim(name, SHARE, all(r[9] >= math.floor(r[6] * math.sqrt(r[7]) / (far + math.sqrt(r[7]))) for r in ledger.rows if r[6] - r[9] > 0))
    return out


for _f in ("F3", "F4", "F5", "F7(2)"):
    for _b in (2, 8, 64, *([None] if _f in ("F3", "F4") else [])):
        _n = f"{_f} budget {_b or 'cubed diameter'}"
        workload(f"w6_phases_{_f}_{_b or 'd3'}", [(_n, c) for c in (*PHASES, *([] if _b else [SHARE]))], f=_f, budget=_b)(w6_phases)


@workload("w7_doubling", [(f, "doubling takes ceil(log2 depth) rounds, one more at most") for f in ("F3", "F5", "F10", "F8", "path 24")] + [(f, "flooding takes a round a step") for f in ("F8", "path 24")])
def w7_doubling(s: SparkSession, d: str) -> Findings:
    """Pointer doubling against flooding; flooding on the longer ones takes as many rounds as nodes."""
    out = Findings()
    for f in ("F3", "F5", "F10", "F8", "path 24"):
        p, ledger = cut(path_forest(s, (24,)) if f == "path 24" else PARENTS[f](s, d), "parents"), RoundLedger(machines=MACHINES)
        depth = jump_to_root(p, ledger).agg(F.max("depth")).first()[0]
        least = max(0, (depth - 1)).bit_length()
        out.saw(f, depth=depth, doubling_rounds=ledger.rounds(), log2=least, busiest_machine=ledger.busiest)
        out.claim(f, "doubling takes ceil(log2 depth) rounds, one more at most", least <= ledger.rounds() <= least + 1)
    for f in ("F8", "path 24"):
        p, ledger = cut(path_forest(s, (24,)) if f == "path 24" else PARENTS[f](s, d), "parents"), RoundLedger()
        flood_labels(fs.forest_of(p).cut(), ledger)
        far = jump_to_root(p).agg(F.max("depth")).first()[0]  # the least id is at an end of each path
        out.saw(f, flooding_rounds=ledger.rounds(), diameter=far)
        out.claim(f, "flooding takes a round a step", ledger.rounds() == far + 1)
    return out


@workload("w8_leftovers", [(f, c) for f in ("F5", "F6 reduced") for c in ("more rounds leave fewer nodes", "what is left lies in small components")])
def w8_leftovers(s: SparkSession, d: str) -> Findings:
    out, f6 = Findings(), forest(s, d, "F6")
    for f, g in (("F5", forest(s, d, "F5")), ("F6 reduced", reduce_degree(f6, TreeMisParams(gather="label"))[1])):
        left, n = [], g.nodes.count()
        for rounds in (2, 6):
            _, rest = shatter(g, rounds)
            row = leftover_sizes(rest).agg(F.sum("components").alias("c"), F.max("size").alias("m")).first()
            left.append((rest.nodes.count(), row.m or 0))
            out.saw(f"{f} {rounds} rounds", left=left[-1][0], components=row.c, largest=row.m)
        out.claim(f, "more rounds leave fewer nodes", left[1][0] < left[0][0] or left[0][0] == 0)
        out.claim(f, "what is left lies in small components", left[1][1] <= math.log2(max(2, n)) ** 2)
    return out


@workload("w9_finish", [(x, MIS) for x in ("completion", "in space", "local rounds")])
def w9_finish(s: SparkSession, d: str) -> Findings:
    out, (_, rest) = Findings(), shatter(forest(s, d, "F5"), 3)
    _solved(out, "completion", rest, lambda g, led: finish(g, "clique", ledger=led))
    _solved(out, "in space", rest, lambda g, led: finish(g, "inspace", ledger=led))
    _solved(out, "local rounds", rest, lambda g, led: bl.finish_by_local_rounds(g, ledger=led))
    return out


def w10_hub_passes(s: SparkSession, d: str, f: str, mem_exp: float) -> Findings:
    out, g, name = Findings(), forest(s, d, f), f"{f} mem_exp {mem_exp}"
    n = g.nodes.count()
    _, left = with_hub_cleanup(g, TreeMisParams(mem_exp=mem_exp, gather="clique"))
    bound = 2 * (n - 1) / n ** (mem_exp / 2)
    out.saw(name, passes=len(left), left_after_first=left[0], bound=bound)
    out.claim(name, "a pass leaves no more than the hubs", left[0] <= bound)
    out.claim(name, "passes within 2 / mem_exp, one more at most", len(left) <= math.ceil(2 / mem_exp) + 1)
    return out


for _f in ("F2", "F6"):
    for _a in (0.25, 0.5, 0.75):
        workload(f"w10_hub_passes_{_f}_{int(100 * _a)}", [(f"{_f} mem_exp {_a}", c) for c in ("a pass leaves no more than the hubs", "passes within 2 / mem_exp, one more at most")], f=_f, mem_exp=_a)(w10_hub_passes)


@workload("w11_components", [*((f"G1 {m}", "labels equal those of the stars") for m in ("completion", "flooding", "sets", "contraction")), *((f"G2 {m}", "labels equal those of the stars") for m in ("flooding", "contraction")), ("G2 completion", "refused by its pairs")])
def w11_components(s: SparkSession, d: str) -> Findings:
    """Sets on G2 hold a set of all nodes at the least one, and completion its square."""
    out = Findings()
    for f in ("G1", "G2"):
        g = Forest.of(fs.GRAPHS[f](s, d)).cut()
        want = component_labels(g)
        runs = {"completion": clique_gather, "flooding": flood_labels, "sets": minset_labels, "contraction": lambda g, led: contract_labels(g, ledger=led)}
        for name in runs if f == "G1" else ("flooding", "contraction"):
            ledger = RoundLedger()
            differ = runs[name](g, ledger).exceptAll(want).count()
            out.saw(f"{f} {name}", rounds=ledger.rounds(), differ=differ)
            out.claim(f"{f} {name}", "labels equal those of the stars", differ == 0)
        if f == "G2":
            try:
                clique_gather(g, most_pairs=g.edges.count() * 4)
                refused = False
            except TooManyPairs:
                refused = True
            out.claim("G2 completion", "refused by its pairs", refused)
    return out


def w12_small_memory(s: SparkSession, d: str, mem_exp: float, how: str) -> Findings:
    out, g = Findings(), forest(s, d, "F6")
    _solved(out, f"mem_exp {mem_exp} {how}", g, lambda g, led: with_hub_cleanup(g, TreeMisParams(mem_exp=mem_exp, gather=how, diameter=8), led)[0])
    return out


for _a, _h in ((0.4, "clique"), (0.4, "inspace"), (0.8, "clique")):
    workload(f"w12_small_memory_{int(100 * _a)}_{_h}", [(f"mem_exp {_a} {_h}", MIS)], mem_exp=_a, how=_h)(w12_small_memory)


@workload("w13_packing", [(f, c) for f in ("F8", "F3") for c in ("no bin over the capacity", "all nodes are packed")])
def w13_packing(s: SparkSession, d: str, capacity: int = 256) -> Findings:
    out = Findings()
    for f in ("F8", "F3"):
        g = forest(s, d, f)
        sizes = component_labels(g).groupBy("leader").agg(F.count("*").alias("size"))
        bins = pack_components(sizes, capacity).groupBy("bin").agg(F.sum("size").alias("load")).agg(F.max("load").alias("most"), F.count("*").alias("bins"), F.sum("load").alias("all")).first()
        out.saw(f, largest_load=bins.most, capacity=capacity, bins=bins.bins, mean_load=bins["all"] / bins.bins)
        out.claim(f, "no bin over the capacity", bins.most <= capacity)
        out.claim(f, "all nodes are packed", bins["all"] == g.nodes.count() and binned(component_labels(g), capacity).count() == bins["all"])
    return out


def w14_application(s: SparkSession, d: str) -> DataFrame:
    """(user_id, chosen, events, total): a user's non-adjacent events in a maximal set, with their value."""
    picked = tree_mis(forest(s, d, "F3"), gather="label")
    e = table(s, d, "events").select(F.col("event_id").alias("v"), "user_id", "value")
    return e.join(picked.withColumn("in", F.lit(1)), "v", "left").groupBy("user_id").agg(F.count("in").alias("chosen"), F.count("*").alias("events"), F.round(F.sum("value"), 4).alias("total"))


@workload("ablations", [(x, MIS) for x in ("full", "no reduction", "no shattering", "literal singletons", "larger class")])
def ablations(s: SparkSession, d: str) -> Findings:
    """Parts of the solver left out one at a time."""
    out, g, base = Findings(), forest(s, d, "F6"), TreeMisParams(gather="label", hub_cleanup=False)
    for name, p in (("full", base), ("no reduction", replace(base, max_steps=0)), ("no shattering", replace(base, shatter_rounds=0)), ("literal singletons", replace(base, singleton="coin")), ("larger class", replace(base, local="colour"))):
        _solved(out, name, g, lambda g, led, p=p: tree_mis(g, p, led))
    return out


@workload("success_rate", [("F6, 20 copies", "every copy reaches the floor")])
def success_rate(s: SparkSession, d: str, seeds: int = 20) -> Findings:
    """Reductions with independent coins: copies of the forest side by side, whose ids and so coins differ."""
    out, g, apart = Findings(), forest(s, d, "F6"), 2**40
    floor = TreeMisParams().floor_for(g.nodes.count())
    at = F.explode(F.sequence(F.lit(0), F.lit(seeds - 1)))
    many = Forest(g.nodes.select("v", at.alias("i")).select((F.col("v") + F.col("i") * apart).alias("v")), g.edges.select("src", "dst", at.alias("i")).select((F.col("src") + F.col("i") * apart).alias("src"), (F.col("dst") + F.col("i") * apart).alias("dst"))).cut()
    rest = reduce_degree(many, TreeMisParams(gather="label", degree_floor=floor))[1]
    good = seeds - degrees(rest).where(F.col("degree") > floor).select((F.col("v") / apart).cast("int").alias("i")).distinct().count()
    out.saw("F6, 20 copies", copies=seeds, reached_floor=good)
    out.claim("F6, 20 copies", "every copy reaches the floor", good == seeds)
    return out


@workload("memory", [("F10 doubling", LOAD), ("F10 doubling", "no machine sends and receives over its bound"), ("F8 completion", LOAD), ("F8 in space", LOAD), ("F5 priority", LOAD)])
def memory(s: SparkSession, d: str) -> Findings:
    """What the fullest of the logical machines holds, against twice the mean and a log factor of the heaviest key."""
    out, ledger = Findings(), RoundLedger(machines=MACHINES)
    n = jump_to_root(fs.time_line(s, d), ledger).count()
    out.saw("F10 doubling", largest_load=ledger.max_load(), busiest=ledger.busiest, rows_moved=sum(r[4] for r in ledger.rows))
    out.claim("F10 doubling", LOAD, ledger.max_load() <= cost.load_bound(n, MACHINES, 1))
    out.claim("F10 doubling", "no machine sends and receives over its bound", ledger.busiest <= cost.load_bound(2 * n, MACHINES, MACHINES))
    for name, f, run, rows, heaviest in (
        ("F8 completion", "F8", clique_gather, lambda n, k: n * k, lambda k: k),
        ("F8 in space", "F8", lambda g, led: root_forest(g, 8, 8, led), lambda n, k: n * k, lambda k: k),
        ("F5 priority", "F5", lambda g, led: bl.priority_mis(g, ledger=led), lambda n, k: 2 * n, lambda k: k),
    ):
        g, ledger = forest(s, d, f), RoundLedger(machines=MACHINES)
        k = max_degree(g) if f == "F5" else component_labels(g).groupBy("leader").count().agg(F.max("count")).first()[0]
        run(g, ledger)
        out.saw(name, largest_load=ledger.max_load(), rows_moved=sum(r[4] for r in ledger.rows))
        out.claim(name, LOAD, ledger.max_load() <= cost.load_bound(rows(g.nodes.count(), k), MACHINES, heaviest(k)))
    return out


@workload("set_quality", [(f, c) for f in ("F2", "F8", "F7") for c in ("no set is larger than the maximum", "trees are solved to a maximum by levels")])
def set_quality(s: SparkSession, d: str) -> Findings:
    """Sizes of the sets against the maximum, which the local tree programme must reach."""
    out = Findings()
    for f in ("F2", "F8", "F7"):
        g = forest(s, d, f)
        most = tree_max_independent_set(PARENTS[f](s, d)).agg(F.sum("size")).first()[0]
        sizes = {"solver": tree_mis(g, gather="label").count(), "priority": bl.priority_mis(g).count(), "larger class": finish(g, "label", "colour").count(), "maximum": finish(g, "label", "dp").count()}
        out.saw(f, best=most, **{k.replace(" ", "_") + "_ratio": v / most for k, v in sizes.items()})
        out.claim(f, "no set is larger than the maximum", max(sizes.values()) <= most)
        out.claim(f, "trees are solved to a maximum by levels", sizes["maximum"] == most)
    return out


def main() -> None:
    spark = SparkSession.builder.master("local[*]").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    for name in sys.argv[2:] or WORKLOADS:
        measures(spark, sys.argv[1], name).show(200, False)


if __name__ == "__main__":
    main()
