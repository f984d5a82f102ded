"""Rooting forests inside a memory budget.

Every live node may add so many edges in a phase. In a growth round a node that can
pay joins all pairs of its neighbours; after enough rounds it knows a connected piece
of its tree. A node that sees the whole of every branch but one points into that
one and leaves; the edges added are dropped and the rest goes on with a budget that
grows as the number of live nodes falls, their product kept constant.

Each edge (src, dst) carries the first step of the tree path from src to dst and the
first step back. With it, what a node knows of a branch is a group of its edges, and
the branch is closed exactly if the tree degrees of those nodes sum to twice their
number less one: a connected piece of p nodes has p - 1 edges inside, one edge to the
node itself, and any other edge leaves it. So the parent choice is two aggregations.

New edges get their steps from the node x that adds them: the tree around x is known
to it, with pointers towards x. That alone is local work (one pass over x's rows); it
runs for nodes that passed a prefilter, so hubs never expand. Nodes are dealt to groups
of bounded rows, and a node's rows are in one group because the grouping asks for it: a
plain repartition is only a wish that the planner may drop or split.

Completion rule. Nodes that know their whole tree have no open branch and could never
choose; they root at the greatest id among them, which all of them see.

In a large job what needs no growth is not grown. A node always sees which of its neighbours are
leaves, so a phase begins with the nodes that choose by that alone, and a phase that has removed
its share of the nodes ends: after that first choice, or between two growth rounds.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from grove.operators.graph import Forest
from grove.operators.ledger import RoundLedger
from grove.session import Parts, cut, drop_cut

_NEW = "x long, src long, dst long, hop_out long, hop_in long"
#: Rows of a group that one call of the expansion holds, about.
GROUP_ROWS = 20_000
#: Pairs that are worked on at once.
SQUARES = 2_000_000
#: Nodes times budget up to which phases only grow and choose; beyond it they are kept short.
PLAIN_MASS = 1_000_000
#: Share of the live nodes that a phase removes before it may end.
ENOUGH = 1 / 2
#: Rows of grown edges from which on a phase looks after every round whether enough nodes can choose.
CHECK_ROWS = 1_000_000


def tree_edges(edges: DataFrame) -> DataFrame:
    """(src, dst, hop_out, hop_in): the tree's own edges."""
    return edges.select("src", "dst", F.col("dst").alias("hop_out"), F.col("src").alias("hop_in"))


def affordable(edges: DataFrame, budget: DataFrame) -> DataFrame:
    """(x, k, left): nodes of degree k whose pairs may be within budget(v, left, seen), by a bound that needs
    no pair: of C(k, 2) pairs at most half the sum of min(k - 1, degree - 1) exist. A node that was complete
    at degree ``seen`` and has that degree still needs nothing."""
    deg = edges.groupBy(F.col("src").alias("w")).agg(F.count("*").alias("d"))
    k = deg.withColumnsRenamed({"w": "x", "d": "k"}).where("k >= 2").join(budget.withColumnRenamed("v", "x"), "x").where("k <> seen")
    at = edges.select(F.col("src").alias("x"), F.col("dst").alias("w")).join(k, "x").join(deg, "w")
    sums = at.groupBy("x", "k", "left").agg(F.sum(F.least(F.col("k") - 1, F.col("d") - 1)).alias("s"))
    return sums.where(F.col("k") * (F.col("k") - 1) / 2 - F.col("s") / 2 <= F.col("left")).select("x", "k", "left")


def _pairs_of(src: np.ndarray, dst: np.ndarray, back: np.ndarray) -> list[np.ndarray]:
    """[x, a, b, step a to b, step b to a] for all pairs a < b of the neighbours of each x, from rows sorted by
    (src, dst); back is dst's step towards src. All nodes at once: a square of steps for each, laid end to end."""
    new = np.diff(src, prepend=src[0] - 1) != 0
    first = np.flatnonzero(new)[np.cumsum(new) - 1]
    row = np.arange(len(src))
    size = np.bincount(first, minlength=len(src))[first]
    names, rank = np.unique(np.concatenate([dst, back]), return_inverse=True)
    key = (np.cumsum(new) - 1) * len(names)
    here, there = key + rank[: len(dst)], key + rank[len(dst) :]
    up = np.minimum(np.searchsorted(here, there), len(here) - 1)
    inside = here[up] == there
    lost = ~inside & (back != src)
    if lost.any():
        raise RuntimeError(f"the rows of node {src[lost][0]} are not complete: a step towards it leads out of its neighbourhood")
    up[~inside] = -1
    local, at = row - first, np.cumsum(size) - size
    step = np.repeat(back, size)  # the step from a to b is the step towards x, unless b hangs below a
    cur = who = row
    while len(cur):
        above = up[cur]
        go = above >= 0
        cur, who, above = cur[go], who[go], above[go]
        step[at[above] + local[who]] = dst[cur]
        cur = above
    one = np.repeat(row, size)
    col = np.arange(len(one)) - at[one]
    upper = col > local[one]
    one, col = one[upper], col[upper]
    other = first[one] + col
    return [src[one], dst[one], dst[other], step[at[one] + col], step[at[other] + local[one]]]


def _expand(t: pa.Table) -> pa.Table:
    t = t.sort_by([("src", "ascending"), ("dst", "ascending")])
    src, dst, back = (t.column(c).to_numpy() for c in ("src", "dst", "hop_in"))
    starts = np.flatnonzero(np.diff(src, prepend=src[0] - 1))
    squares = np.cumsum(np.diff(np.append(starts, len(src))) ** 2)
    cuts = np.append(starts[np.flatnonzero(np.diff(squares // SQUARES, prepend=-1))], len(src))
    parts = [_pairs_of(src[a:b], dst[a:b], back[a:b]) for a, b in zip(cuts[:-1], cuts[1:], strict=True)]
    return pa.table([pa.array(np.concatenate(c)) for c in zip(*parts, strict=True)], names=["x", "src", "dst", "hop_out", "hop_in"])


def missing_pairs(edges: DataFrame, able: DataFrame, groups: int) -> DataFrame:
    """(x, src, dst, hop_out, hop_in): the pairs of neighbours that each node of ``able(x)`` does not see joined."""
    mine = edges.join(able.select(F.col("x").alias("src")), "src", "left_semi").select("src", "dst", "hop_in")
    pairs = mine.groupBy(F.pmod(F.xxhash64("src"), F.lit(groups))).applyInArrow(_expand, _NEW)
    return pairs.join(edges.select("src", "dst"), ["src", "dst"], "left_anti")


def payers(missing: DataFrame, able: DataFrame) -> DataFrame:
    """(x, n, k): nodes that can pay for all their n missing pairs, none included, and so are complete at degree k."""
    need = missing.groupBy("x").agg(F.count("*").alias("n"))
    return able.join(need, "x", "left").select("x", F.coalesce("n", F.lit(0)).alias("n"), "k", "left").where("n <= left").drop("left")


def added(missing: DataFrame, spent: DataFrame) -> DataFrame:
    """The edges that are paid for, both ways; two nodes that add the same one agree on its steps."""
    paid = missing.join(spent.select("x"), "x", "left_semi").dropDuplicates(["src", "dst"]).select("src", "dst", "hop_out", "hop_in")
    back = paid.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.col("hop_in").alias("hop_out"), F.col("hop_out").alias("hop_in"))
    return paid.unionByName(back)


class Growth:
    """A phase at work: edges with steps and the bill, each with a part for every round."""

    def __init__(self, tree: DataFrame, nodes: DataFrame, budget: int):
        self.nodes, self.b, self.rounds = nodes, budget, 0
        self.edges = Parts(tree.sparkSession, "grown", "src long, dst long, hop_out long, hop_in long")
        self.bill = Parts(tree.sparkSession, "bill", "x long, n long, k long")
        self.size = self.edges.add(tree_edges(tree)).count()

    def budget(self) -> DataFrame:
        """(v, left, seen): what each node may still add, and the degree at which it was last complete."""
        paid = self.bill.frame().groupBy(F.col("x").alias("v")).agg(F.sum("n").alias("n"), F.max("k").alias("k"))
        return self.nodes.join(paid, "v", "left").select("v", (F.lit(self.b) - F.coalesce("n", F.lit(0))).alias("left"), F.coalesce("k", F.lit(0)).alias("seen"))

    def round(self) -> int:
        """One growth round; the number of rows it added (an edge is two)."""
        edges = self.edges.frame()
        able = cut(affordable(edges, self.budget()), "able")
        missing = cut(missing_pairs(edges, able, 1 + self.size // GROUP_ROWS), "missing")
        fresh = self.edges.add(added(missing, self.bill.add(payers(missing, able)))).count()
        drop_cut(able, missing)
        self.size, self.rounds = self.size + fresh, self.rounds + 1
        return fresh

    def drop(self) -> None:
        self.edges.drop(), self.bill.drop()


def budget_round(edges: DataFrame, budget: DataFrame) -> tuple[DataFrame, DataFrame]:
    """One growth round: (new edges both ways, spent(x, n)) for edges with steps and budget(v, left)."""
    able = cut(affordable(edges, budget.select("v", "left", F.lit(0).cast("long").alias("seen"))), "able")
    missing = cut(missing_pairs(edges, able, 1 + edges.count() // GROUP_ROWS), "missing")
    spent = cut(payers(missing, able), "spent")
    return added(missing, spent), spent.select("x", "n")


def choose_parents(nodes: DataFrame, tree: DataFrame, edges: DataFrame) -> DataFrame:
    """(v, parent) for the nodes that choose: one open branch, or the whole tree known."""
    deg = tree.groupBy(F.col("src").alias("dst")).agg(F.count("*").alias("d"))
    branch = edges.join(deg, "dst").groupBy(F.col("src").alias("v"), "hop_out").agg(F.sum("d").alias("s"), F.count("*").alias("n"))
    state = branch.groupBy("v").agg(
        F.sum((F.col("s") != 2 * F.col("n") - 1).cast("int")).alias("open"), F.max(F.when(F.col("s") != 2 * F.col("n") - 1, F.col("hop_out"))).alias("to")
    )
    state = cut(nodes.join(state, "v", "left").select("v", F.coalesce("open", F.lit(0)).alias("open"), "to"), "state")
    informed = state.where("open = 0").select("v")
    seen = (
        edges.join(informed.select(F.col("v").alias("src")), "src", "left_semi").join(informed.select(F.col("v").alias("dst")), "dst", "left_semi")
        .groupBy(F.col("src").alias("v")).agg(F.max(F.struct("dst", "hop_out")).alias("m"))
    )
    rooted = informed.join(seen, "v", "left").select("v", F.when(F.coalesce(F.col("m.dst"), F.col("v")) <= F.col("v"), F.col("v")).otherwise(F.col("m.hop_out")).alias("parent"))
    return state.where("open = 1").select("v", F.col("to").alias("parent")).unionByName(rooted)


def settle_roots(chosen: DataFrame) -> DataFrame:
    """Of two nodes that chose each other the greater is the root."""
    other = chosen.select(F.col("v").alias("parent"), F.col("parent").alias("back"))
    return chosen.join(other, "parent", "left").select("v", F.when((F.col("back") == F.col("v")) & (F.col("v") > F.col("parent")), F.col("v")).otherwise(F.col("parent")).alias("parent"))


def choose_by_leaves(nodes: DataFrame, tree: DataFrame) -> DataFrame:
    """(v, open, parent) of every node, by what :func:`choose_parents` finds in the tree's own edges, from sums by
    node alone: a branch is closed if it is a leaf, and where one neighbour is none, the ids of all neighbours
    and of the leaves among them differ by that one. A centre of leaves alone knows its tree, and roots it likewise."""
    deg = tree.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("n"), F.bit_xor("dst").alias("all"), F.max("dst").alias("top"))
    leaves = deg.where("n = 1").groupBy(F.col("all").alias("v")).agg(F.count("*").alias("k"), F.bit_xor("v").alias("low"))
    zero = F.lit(0).cast("long")
    at = nodes.join(deg, "v", "left").join(leaves, "v", "left").select("v", F.coalesce("n", zero).alias("n"), F.coalesce("all", zero).alias("all"), F.coalesce("k", zero).alias("k"), F.coalesce("low", zero).alias("low"), "top")
    to = F.when(F.col("n") - F.col("k") == 1, F.col("all").bitwiseXOR(F.col("low"))).otherwise(F.greatest("v", "top"))
    return at.select("v", (F.col("n") - F.col("k")).alias("open"), to.alias("parent"))


def growth_rounds(diameter: int) -> int:
    return max(1, int(diameter - 1).bit_length() if diameter > 1 else 1) + 1


def root_forest(g: Forest, budget: int, diameter: int | None = None, ledger: RoundLedger | None = None, strict_budget: bool = True, max_phases: int = 200) -> DataFrame:
    """(v, parent) for every node of a forest; a root is its own parent.

    ``budget`` is B_0 edges a node; B_i = n_0 B_0 / n_i, so that live nodes times budget
    stays the same. ``diameter`` bounds the growth rounds of a phase; without it a phase
    grows until a round adds nothing. With ``strict_budget=False`` (an extension) a phase
    that removes under a quarter of the live nodes doubles the product. Where n_0 B_0
    is over ``PLAIN_MASS`` a phase may end once it has removed half of its nodes, or what its
    budget is known to remove if that is more."""
    nodes, tree = cut(g.nodes, "live"), cut(g.edges.select("src", "dst"), "tree")
    n0 = live = nodes.count()
    # open: branches that are not closed; rows of 2 and more did not choose. Only nodes of one phase choose each
    # other, so that is settled once, at the end
    mass, done = n0 * max(2, budget), Parts(g.nodes.sparkSession, "parents", "v long, open long, parent long")

    lean = mass > PLAIN_MASS

    def leave(left: DataFrame) -> None:
        nonlocal tree, nodes
        rest = cut(tree.join(left.withColumnRenamed("v", "src"), "src", "left_semi").join(left.withColumnRenamed("v", "dst"), "dst", "left_semi"), "tree")
        drop_cut(tree)
        tree, nodes = rest, left

    for phase in range(max_phases):
        if live == 0:
            break
        b = max(2, min(mass // live, n0 * n0))
        share = max(ENOUGH, b**0.5 / (diameter + b**0.5) if diameter else 0)
        rounds = copies = 0
        if ledger is not None:
            ledger.load(tree, "src")
        after = live
        if lean:
            leave(done.add(choose_by_leaves(nodes, tree)).where("open > 1").select("v"))
            after = nodes.count()
        if not lean or after > (1 - share) * live:
            grown, chosen = Growth(tree, nodes, b), None
            while grown.rounds < (growth_rounds(diameter) if diameter else 64) and grown.round():
                if lean and grown.size > CHECK_ROWS:
                    chosen = cut(choose_parents(nodes, tree, grown.edges.frame()), "chosen")
                    if after - chosen.count() <= (1 - share) * live:
                        break
                    drop_cut(chosen)
                    chosen = None
            if ledger is not None:
                ledger.load(grown.edges.frame(), "src")
                copies = grown.bill.frame().agg(F.sum("n")).first()[0] or 0
            rounds = grown.rounds
            gone = done.add((chosen if chosen is not None else choose_parents(nodes, tree, grown.edges.frame())).select("v", F.lit(0).cast("long").alias("open"), "parent"))
            leave(cut(nodes.join(gone.select("v"), "v", "left_anti"), "live"))
            grown.drop()
            after = nodes.count()
        if ledger is not None:
            ledger.record("root_phase", rounds=rounds + 1, live=live, delta=b, copies=copies, edges=live - after, note=f"phase {phase}")
        if after == live:
            raise RuntimeError("a phase removed no node: the graph has a cycle")
        if not strict_budget and 4 * (live - after) < live:
            mass *= 2
        live = after
    if live:
        raise RuntimeError(f"{live} nodes are left after {max_phases} phases")
    return settle_roots(done.frame().where("open < 2").select("v", "parent"))
