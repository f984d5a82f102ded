"""The methods that the tree solver is compared with. Each returns (v), a maximal independent set."""

from __future__ import annotations

import itertools
import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from grove.functions.coins import SIDES, coin
from grove.operators.clique import balls
from grove.operators.graph import Forest, degrees, induced, max_degree, remove_closed
from grove.operators.ledger import RoundLedger
from grove.operators.local import Arrays, greedy
from grove.operators.shatter import CAP, shatter
from grove.session import Parts, cut, drop_cut


#: Rows of a graph up to which a machine holds them all as arrays; larger graphs pass by it in order.
HELD_ROWS = 5_000_000


def _solo(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The greedy set of the whole graph in rows (src, dst, rank), a loop a node; by rising (rank, id)."""
    got = [b for b in batches if b.num_rows]
    if got:
        t = pa.Table.from_batches(got)
        a, b, rank = (t.column(c).to_numpy() for c in ("src", "dst", "rank"))
        loop = a == b
        order = np.lexsort((a[loop], rank[loop]))
        place = np.empty(len(order), np.int64)
        by_id = np.argsort(a[loop])
        place[order] = np.arange(len(order))
        at = lambda x: place[by_id][np.searchsorted(a[loop][by_id], x)]
        arrays = Arrays(np.arange(len(order)), at(a[~loop]), at(b[~loop]))
        yield pa.RecordBatch.from_arrays([pa.array(a[loop][order][greedy(arrays)])], names=["v"])


def _ranked(g: Forest, rank: Column) -> DataFrame:
    return g.edges.select("src", "dst", F.lit(0).cast("long").alias("rank")).unionByName(g.nodes.select(F.col("v").alias("src"), F.col("v").alias("dst"), rank.cast("long").alias("rank")))


def _placed(g: Forest, rank: Column) -> tuple[DataFrame, int]:
    """(v, at), n: places 0 .. n - 1 of the nodes by rising (rank, id), from sorted ranges and their sizes."""
    ranges = g.nodes.select("v", rank.cast("long").alias("rank")).repartitionByRange("rank", "v").sortWithinPartitions("rank", "v")
    rows = cut(ranges.select("v", F.monotonically_increasing_id().alias("row")), "places")
    part = F.shiftright("row", 33)
    sizes = sorted((r.part, r.n) for r in rows.groupBy(part.alias("part")).agg(F.count("*").alias("n")).collect())
    before = [0, *itertools.accumulate(n for _, n in sizes)]
    starts = rows.sparkSession.createDataFrame([(k, at) for (k, _), at in zip(sizes, before, strict=False)], "part long, start long")
    placed = rows.withColumn("part", part).join(F.broadcast(starts), "part").select("v", (F.col("start") + F.col("row").bitwiseAND(2**33 - 1)).alias("at"))
    return placed, before[-1]


def _passing(n: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """The greedy set of the places 0 .. n - 1 from their edges (hi, lo), lo < hi, by rising hi. What is held is a
    byte a place: once a place's edges come, all places before it are decided."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = bytearray(b"\x01") * n
        state = np.frombuffer(held, np.uint8)
        for b in batches:
            if b.num_rows:
                hi, lo = b.column(0).to_numpy(), b.column(1).to_numpy()
                old = lo < hi[0]
                state[hi[old][state[lo[old]] == 1]] = 0
                for x, y in zip(hi[~old].tolist(), lo[~old].tolist(), strict=True):
                    if held[y]:
                        held[x] = 0
        for k in range(0, n, 1 << 20):
            yield pa.RecordBatch.from_arrays([pa.array(np.flatnonzero(state[k : k + (1 << 20)]) + k)], names=["at"])

    return run


def _greedy_by(g: Forest, rank: Column, held_rows: int) -> DataFrame:
    """(v): the sequential greedy set by rising (rank, id), on one machine. Up to ``held_rows`` rows it holds the
    graph; beyond that edges pass by it in the order of their later end."""
    rows = cut(_ranked(g, rank), "ranked")
    if rows.count() <= held_rows:
        return rows.coalesce(1).mapInArrow(_solo, "v long")
    drop_cut(rows)
    placed, n = _placed(g, rank)
    ends = g.edges.where("src < dst").join(placed.select(F.col("v").alias("src"), F.col("at").alias("a")), "src").join(placed.select(F.col("v").alias("dst"), F.col("at").alias("b")), "dst")
    passing = ends.select(F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo")).repartition(1).sortWithinPartitions("hi")
    return placed.join(cut(passing.mapInArrow(_passing(n), "at long"), "greedy"), "at").select("v")


class _Loop:
    """What the loops share: parts of the set, the live graph, and the last round's tables to delete."""

    def __init__(self, g: Forest, name: str):
        self.g, self.set, self.old, self.n = g, Parts(g.nodes.sparkSession, name, "v long"), [], 0

    def join(self, new: DataFrame) -> None:
        """``new`` joins the set and leaves the graph with its neighbours."""
        self.g = remove_closed(self.g, self.set.add(new)).cut()
        drop_cut(*self.old)
        self.old, self.n = [self.g.nodes, self.g.edges], self.n + 1


def solo_mis(g: Forest, held_rows: int = HELD_ROWS) -> DataFrame:
    """One machine runs through the whole graph by rising id; beyond ``held_rows`` rows it holds a byte a node."""
    return cut(_greedy_by(g, F.lit(0), held_rows), "solo")


def priority_round(g: Forest, seed: int, tag: str) -> DataFrame:
    """(v): nodes whose (coin, id) is less than that of every neighbour."""
    mine = F.struct(coin("v", seed, tag).alias("p"), F.col("v").alias("id"))
    near = g.edges.select("src", F.struct(coin("dst", seed, tag).alias("p"), F.col("dst").alias("id")).alias("q")).groupBy(F.col("src").alias("v")).agg(F.min("q").alias("q"))
    return g.nodes.join(near, "v", "left").where(F.col("q").isNull() | (mine < F.col("q"))).select("v")


def priority_mis(g: Forest, fresh: bool = True, seed: int = 7, ledger: RoundLedger | None = None) -> DataFrame:
    """Local minima of random priorities join, for any graph. With ``fresh=False`` one order is
    kept, and the result is the sequential greedy set in that order."""
    run = _Loop(g, "priority")
    while live := run.g.nodes.count():
        if ledger is not None:
            ledger.load(run.g.edges, "src")
            ledger.record("priority_mis", rounds=1, live=live)
        run.join(priority_round(run.g, seed, f"priority{run.n if fresh else 0}"))
    return run.set.frame()


def marking_mis(g: Forest, seed: int = 7, ledger: RoundLedger | None = None) -> DataFrame:
    """A node marks itself with probability 1 / (2 degree); of marked neighbours the one of higher (degree, id) stays."""
    run = _Loop(g, "marking")
    while live := run.g.nodes.count():
        if ledger is not None:
            ledger.record("marking_mis", rounds=1, live=live)
        deg = cut(degrees(run.g), "deg")
        marked = deg.where((F.col("degree") == 0) | (coin("v", seed, f"degree{run.n}") < F.lit(SIDES) / (2 * F.col("degree")))).select("v", F.col("degree").alias("d"))
        best = (
            run.g.edges.join(marked.select(F.col("v").alias("dst"), F.struct("d", "v").alias("q")), "dst").groupBy(F.col("src").alias("v")).agg(F.max("q").alias("q"))
        )
        run.join(marked.join(best, "v", "left").where(F.col("q").isNull() | (F.struct("d", "v") > F.col("q"))).select("v"))
        drop_cut(deg)
    return run.set.frame()


def tree_local_mis(g: Forest, seed: int = 7, ledger: RoundLedger | None = None) -> DataFrame:
    """The desire process alone until nothing is left; the published tree process is known here by its bound only."""
    chosen, rest = shatter(g, 400, seed, ledger)
    return chosen.unionByName(priority_mis(rest, seed=seed)) if rest.nodes.limit(1).count() else chosen


def bit_reduction_round(state: DataFrame) -> DataFrame:
    """(v, parent, c) -> the same with c := 2 i + bit i of c, i the lowest bit in which c differs
    from the parent's; a root takes i = 0."""
    up = state.select(F.col("v").alias("parent"), F.col("c").alias("pc"))
    diff = F.col("c").bitwiseXOR(F.when(F.col("v") == F.col("parent"), F.col("c").bitwiseXOR(F.lit(1).cast("long"))).otherwise(F.col("pc")))
    i = F.bit_count(diff.bitwiseAND(-diff) - 1)
    return state.join(up, "parent").select("v", "parent", (2 * i + F.call_function("getbit", F.col("c"), i)).cast("long").alias("c"))


def rooted_three_colour(parents: DataFrame, ledger: RoundLedger | None = None) -> DataFrame:
    """(v, c) with c in 0..2, proper on the rooted forest parents(v, parent); ids must not be negative."""
    now = cut(parents.select("v", "parent", F.col("v").alias("c")), "colour")
    while (now.agg(F.max("c")).first()[0] or 0) > 5:
        now = cut(bit_reduction_round(now), "colour")
        if ledger is not None:
            ledger.record("bit_reduction", rounds=1)
    for x in (5, 4, 3):
        up = now.select(F.col("v").alias("parent"), F.col("c").alias("pc"))
        root = F.col("v") == F.col("parent")
        down = cut(now.join(up, "parent").select("v", "parent", F.when(root, (F.col("c") + 1) % 3).otherwise(F.col("pc")).alias("c"), F.col("c").alias("old")), "shift")
        # after the shift all children of a node have its old colour
        up = down.select(F.col("v").alias("parent"), F.col("c").alias("pc"))
        others = F.array(F.when(root, F.lit(-1).cast("long")).otherwise(F.col("pc")), F.col("old"))
        free = F.array_min(F.array_except(F.array(*[F.lit(k).cast("long") for k in range(3)]), others))
        now = cut(down.join(up, "parent").select("v", "parent", F.when(F.col("c") == x, free).otherwise(F.col("c")).alias("c")), "colour")
        if ledger is not None:
            ledger.record("shift_down", rounds=1)
    return now.select("v", "c")


def rooted_mis(g: Forest, parents: DataFrame, ledger: RoundLedger | None = None) -> DataFrame:
    """Colour classes of the three-colouring join in turn where nothing near has."""
    colour, run = cut(rooted_three_colour(parents, ledger), "three"), _Loop(g, "classes")
    for k in range(3):
        run.join(run.g.nodes.join(colour.where(F.col("c") == k), "v", "left_semi"))
    return run.set.frame()


def prefix_greedy_mis(g: Forest, seed: int = 7, ledger: RoundLedger | None = None, most_rows: int | None = None, held_rows: int = HELD_ROWS) -> DataFrame:
    """Prefixes of a random order, each solved greedily in that order on one machine of memory about n.

    The order is that of (coin, id): a node is in a prefix while its coin is under a growing
    bound. The result is the sequential greedy set in that order. A prefix of more than ``held_rows``
    rows that are still live passes by its machine in order; one of more than ``most_rows``, if given, is refused."""
    deg = max(2, max_degree(g))
    shares = list(itertools.takewhile(lambda s: s < 1 / 2, (1 / deg ** (0.75**i) for i in range(40))))
    run = _Loop(g, "prefixes")
    for bound in [*(int(SIDES * s) for s in shares), SIDES]:
        sub = induced(run.g, cut(run.g.nodes.where(coin("v", seed, "rank") < bound), "prefix"))
        sub = sub.cut()
        if most_rows is not None and sub.nodes.count() + sub.edges.count() > most_rows:
            raise ValueError(f"more than {most_rows} rows do not fit one machine")
        run.join(_greedy_by(sub, coin("v", seed, "rank"), held_rows))
        drop_cut(sub.nodes, sub.edges)
        if ledger is not None:
            ledger.record("prefix_greedy", rounds=1, live=run.g.nodes.count())
    return run.set.frame()


def sequential_greedy(ids: list[int], edges: list[tuple[int, int]], order: dict[int, int] | None = None) -> set[int]:
    """The exact sequential greedy set, for fixtures."""
    near: dict[int, set[int]] = {i: set() for i in ids}
    for a, b in edges:
        near[a].add(b), near[b].add(a)
    out: set[int] = set()
    for i in sorted(ids, key=(order or {}).get if order else None):
        if not near[i] & out:
            out.add(i)
    return out


def _simulate(t: pa.Table, rounds: int) -> pa.Table:
    """(v, e, joins, live) of each centre v after ``rounds`` desire rounds inside its own ball.

    Rows: (v, a, b, d, e, coins), a loop for each node a of v's ball at distance d with its level and
    coins, and an edge a to b for each a that isn't on the rim. A round's decisions hold one step
    further in than what they are made from, its removals two; the centre of a ball of radius
    2 * rounds is right after all of them."""
    v, a, b = (t.column(c).to_numpy() for c in ("v", "a", "b"))
    loop = a == b
    names, rank = np.unique(np.concatenate([v, a, b]), return_inverse=True)
    rv, ra, rb = (rank[k * len(v) : (k + 1) * len(v)].astype(np.int64) for k in range(3))
    key = rv * len(names) + ra
    order = np.argsort(key[loop])
    nodes = key[loop][order]
    src, dst = np.searchsorted(nodes, key[~loop]), np.searchsorted(nodes, (rv * len(names) + rb)[~loop])
    e, d = t.column("e").to_numpy()[loop][order].astype(np.int64), t.column("d").to_numpy()[loop][order]
    coins = t.column("coins").combine_chunks().filter(pa.array(loop)).flatten().to_numpy().reshape(-1, rounds)[order]
    live, joined, n = np.ones(len(nodes), bool), np.zeros(len(nodes), bool), len(nodes)
    for r in range(rounds):
        on = live[src] & live[dst]
        s, x = src[on], dst[on]
        want = 0.5**e
        marked = live & (coins[:, r] < SIDES * want)
        joins = marked & (np.bincount(s, marked[x], n) == 0)
        total = np.bincount(s, want[x], n)
        joined |= joins
        live &= ~(joins | (np.bincount(s, joins[x], n) > 0))
        e = np.where(total >= 2, np.minimum(e + 1, CAP), np.maximum(e - 1, 1))
    mid = d == 0
    return pa.table({"v": pa.array(names[nodes[mid] // len(names)]), "e": pa.array(e[mid].astype(np.int32)), "joins": pa.array(joined[mid]), "live": pa.array(live[mid])})


def ball_gather_mis(g: Forest, rounds: int = 2, seed: int = 7, ledger: RoundLedger | None = None, group_rows: int = 200_000, most_pairs: int = 200_000_000) -> DataFrame:
    """Every node gathers the ball of radius 2 * ``rounds`` around it, and its machine runs ``rounds``
    desire rounds on it without a message; then what is left goes on. The set is that of the
    desire process round by round. The published process is known here by its bound only.

    Balls that would take more than ``most_pairs`` pairs to find are refused: the process is for
    graphs of low degree."""
    run, state = _Loop(g, "balls"), g.nodes.select("v", F.lit(1).alias("e"))
    while live := run.g.nodes.count():
        near = balls(run.g, 2 * rounds, most_pairs)
        ball = cut(near.select("v", F.col("w").alias("a"), "d").unionByName(run.g.nodes.select("v", F.col("v").alias("a"), F.lit(0).alias("d"))), "ball")
        coins = F.array(*[coin("v", seed, f"mark{run.n * rounds + k}") for k in range(rounds)])
        said = state.select(F.col("v").alias("a"), "e", coins.alias("coins"))
        inner = ball.where(F.col("d") < 2 * rounds).join(run.g.edges.select(F.col("src").alias("a"), F.col("dst").alias("b")), "a")
        rows = ball.join(said, "a").select("v", "a", F.col("a").alias("b"), "d", "e", "coins").unionByName(inner.select("v", "a", "b", "d", F.lit(0).alias("e"), F.array().cast("array<long>").alias("coins")))
        rows = cut(rows, "gathered")
        groups = 1 + rows.count() // group_rows
        done = cut(rows.groupBy(F.pmod(F.xxhash64("v"), F.lit(groups))).applyInArrow(lambda t: _simulate(t, rounds), "v long, e int, joins boolean, live boolean"), "simulated")
        if ledger is not None:
            ledger.load(rows, "v")
            ledger.record("ball_gather", rounds=1, live=live, copies=ball.count())
        run.set.add(done.where("joins").select("v"))
        state = done.where("live").select("v", "e")
        run.g = induced(run.g, state.select("v")).cut()
        drop_cut(ball, rows, *run.old)
        run.old, run.n = [run.g.nodes, run.g.edges, done], run.n + 1
    return run.set.frame()


def finish_by_local_rounds(g: Forest, seed: int = 7, ledger: RoundLedger | None = None) -> DataFrame:
    """Leftovers solved by message rounds instead of gathering."""
    return priority_mis(g, fresh=True, seed=seed, ledger=ledger)


def predicted_rounds(method: str, n: float, delta: float = 2, d: float = 2, decay: float = 0.5, alpha: float = 0.5) -> float:
    """The published bound with constants 1 and base-2 logarithms; for comparing shapes only."""
    lg = math.log2(max(4, n))
    ll = math.log2(max(2, lg))
    star, x = 0, n
    while x > 1:
        x, star = math.log2(x), star + 1
    return {
        "clique": ll**2, "inspace": ll**3, "small_memory": ll**2 / alpha, "priority": lg, "tree_local": math.sqrt(lg) * ll, "rooted": star, "prefix": ll, "ball": math.sqrt(lg),
        "local_finish": 2 ** math.sqrt(ll), "gather_clique": math.ceil(math.log2(max(2, d))) + 1, "gather_inspace": math.log2(max(2, d)) * ll, "flood": d,
        "reduction_steps": math.log(max(2, math.log2(max(4, delta))), 1 + decay), "sparse_matching": ll**2, "arboricity": math.sqrt(lg), "list_colouring": math.sqrt(ll), "lower_bound": ll,
    }[method]
