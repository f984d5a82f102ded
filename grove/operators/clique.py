"""Gathering by neighbourhood completion.

In a round every node joins all pairs of its neighbours, so distances halve and after
ceil(log2 d) rounds a component of diameter d is a clique; one quiet round more shows
it. The least id of a node's closed neighbourhood is then its component's label.

Only new edges are extended (semi-naive): pairs of a new and any edge at their middle
node, less what is there already. How many nodes add an edge is counted in blocks: nodes
from which steps to the least id in sight meet lie close together and share most of their neighbours,
so a task multiplies their neighbourhoods as matrices and sends each pair on once, with its
number. The pairs of a hub are joined row by row. What is at work is the number of pairs,
about k^3 copies for a component of k nodes, so :func:`grove.operators.gather.gather` sends
only small components here.

Once a round has more than ``WHOLE_PAIRS`` pairs ahead, components go on one by one as matrices
(:mod:`grove.operators.whole`), with the same rounds, copies and labels; those too large for that stay here.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from grove.operators.graph import Forest
from grove.operators.ledger import RoundLedger
from grove.operators.whole import complete_whole
from grove.session import cut, drop_cut

#: Neighbours up to which the pairs of a node are counted in blocks.
BLOCK_DEGREE = 512
#: Names of a block, rows of a task's group, rows up to which small blocks are put together, entries of a block's rows.
BLOCK_NAMES, GROUP_ROWS, FEW_ROWS, BLOCK_CELLS = 2_048, 100_000, 512, 4_000_000
#: Times that the least ids near nodes are doubled to deal nodes; where a node is dealt changes the work, never a result.
JUMPS = 2
#: Pairs ahead from which on components go on as matrices; a ledger that measures loads keeps the rounds on rows.
WHOLE_PAIRS = 1_000_000
#: Pairs that a round on rows looks at, at most; who allows less wants :class:`TooManyPairs` before any such work.
MOST_PAIRS = 100_000_000_000


def _block(mid: np.ndarray, dst: np.ndarray, fresh: np.ndarray) -> list[list[np.ndarray]]:
    """[[src, dst, copies, open]] with src < dst: pairs of neighbours of the nodes ``mid`` (sorted, their rows whole) and
    how many of these have both, less pairs that a row or two old rows show to be joined. A pair is open if the rows of
    neither end are here, so that it may be joined already."""
    mids, row = np.unique(mid, return_inverse=True)
    names, col = np.unique(dst, return_inverse=True)
    if len(mids) > 1 and (len(names) > BLOCK_NAMES or len(mids) * len(names) > BLOCK_CELLS):
        half = np.searchsorted(mid, mids[len(mids) // 2])
        return _block(mid[:half], dst[:half], fresh[:half]) + _block(mid[half:], dst[half:], fresh[half:])
    near = np.zeros((len(mids), len(names)), np.float32)
    near[row, col] = 1
    count = near.T @ near
    near[row[fresh], col[fresh]] = 0
    count[near.T @ near > 0] = 0
    at = np.minimum(np.searchsorted(names, mid), len(names) - 1)
    own = names[at] == mid
    count[at[own], col[own]] = count[col[own], at[own]] = 0
    a, b = np.nonzero(np.triu(count, 1))
    here = np.zeros(len(names), bool)
    here[at[own]] = True
    return [[names[a], names[b], count[a, b].astype(np.int64), ~(here[a] | here[b])]]


def _count_pairs(t: pa.Table) -> pa.Table:
    """(src, dst, copies, open) of a group of whole nodes (m, mid, dst, fresh), block by block; a block is one m or several small ones."""
    t = t.sort_by([("m", "ascending"), ("mid", "ascending")])
    m, mid, dst, fresh = (t.column(c).to_numpy() for c in ("m", "mid", "dst", "fresh"))
    starts = [*np.flatnonzero(np.diff(m, prepend=m[0] - 1)).tolist(), len(m)]
    found, a = [], 0
    for end, then in zip(starts[1:], [*starts[2:], len(m) + FEW_ROWS + 1], strict=True):
        if then - a > FEW_ROWS:
            order = a + np.argsort(mid[a:end], kind="stable")
            found += _block(mid[order], dst[order], fresh[order])
            a = end
    return pa.table([pa.array(np.concatenate(c)) for c in zip(*found, strict=True)], names=["src", "dst", "copies", "open"])


def _round(rows: DataFrame) -> tuple[DataFrame, list[DataFrame]]:
    """(src, dst, copies), src < dst, of the edges that a round adds to ``rows(src, dst, fresh)``; tables to drop after use."""
    rows = rows.select(F.col("src").alias("mid"), "dst", "fresh")
    near = rows.groupBy("mid").agg(F.least(F.min("dst"), F.first("mid")).alias("m"), F.count("*").alias("k"), F.max("fresh").alias("any")).where("k > 1 and any").select("mid", "m", "k")
    used = [near := cut(near, "near")]
    held = near.agg(F.sum(F.when(F.col("k") <= BLOCK_DEGREE, F.col("k"))).alias("rows"), F.count_if(F.col("k") > BLOCK_DEGREE).alias("hubs")).first()
    few, groups = near.where(F.col("k") <= BLOCK_DEGREE).select("mid", "m", "k"), 1 + (held.rows or 0) // GROUP_ROWS
    for _ in range(JUMPS if groups > 1 else 0):
        few = few.join(near.select(F.col("mid").alias("m"), F.col("m").alias("to")), "m", "left").select("mid", F.coalesce("to", "m").alias("m"), "k")
        used.append(few := cut(few, "homes"))
        near = few
    load = few.groupBy("m").agg(F.sum("k").alias("rows"))
    part = F.pmod(F.xxhash64("mid"), F.lit(1) + F.floor(F.col("rows") / GROUP_ROWS))
    dealt = few.join(load, "m").select("mid", "m", F.pmod(F.xxhash64("m", part), F.lit(groups)).alias("grp"))
    pairs = rows.join(dealt, "mid").groupBy("grp").applyInArrow(_count_pairs, "src long, dst long, copies long, open boolean")
    if held.hubs:
        hubs = used[0].where(F.col("k") > BLOCK_DEGREE).select("mid")
        used.append(at := cut(rows.join(hubs, "mid", "left_semi"), "hubs"))
        joined = at.where("fresh").select("mid", F.col("dst").alias("a")).join(at.select("mid", F.col("dst").alias("b")), "mid").where("a <> b")
        once = joined.select("mid", F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst")).distinct()
        pairs = pairs.unionByName(once.groupBy("src", "dst").agg(F.count("*").alias("copies")).withColumn("open", F.lit(True)))
    used.append(pairs := cut(pairs, "pairs"))
    if not pairs.where("open").limit(1).count():
        return pairs.groupBy("src", "dst").agg(F.sum("copies").alias("copies")), used
    known = rows.where("mid < dst").select(F.col("mid").alias("src"), "dst", F.lit(0).cast("long").alias("copies"), F.lit(True).alias("known"))
    every = pairs.select("src", "dst", "copies", F.lit(False).alias("known")).unionByName(known).groupBy("src", "dst").agg(F.sum("copies").alias("copies"), F.max("known").alias("known"))
    return every.where("not known").drop("known"), used


def completion_round(edges: DataFrame, fresh: DataFrame) -> DataFrame:
    """(src, dst, copies), src < dst: edges that a round adds; copies counts the nodes that add each."""
    new = fresh.select("src", "dst", F.lit(True).alias("fresh"))
    return _round(edges.join(new, ["src", "dst"], "left").select("src", "dst", F.coalesce("fresh", F.lit(False)).alias("fresh")))[0]


class TooManyPairs(ValueError):
    """Completing the neighbourhoods would make more pairs than allowed."""


def pairs_ahead(rows: DataFrame) -> tuple[int, int]:
    """Pairs that a round on ``rows(src, dst, fresh)`` would look at, and how many of them are joined row by row, from
    degrees alone: no hub is expanded to find out."""
    deg = rows.groupBy("src").agg(F.count_if("fresh").alias("a"), F.count("*").alias("b"))
    work = F.col("a").cast("double") * F.col("b")
    row = deg.agg(F.sum(work).alias("all"), F.sum(F.when(F.col("b") > BLOCK_DEGREE, work)).alias("hubs")).first()
    return int(row["all"] or 0), int(row.hubs or 0)


def cliques(edges: DataFrame) -> DataFrame:
    """(v): nodes of components that are cliques already, found without a pair. Nodes that have the same least id
    near them are such a component if none has a neighbour outside and each has all the others for neighbours."""
    least = edges.groupBy(F.col("src").alias("v")).agg(F.least(F.min("dst"), F.first("src")).alias("m"))
    seen = edges.join(least.select(F.col("v").alias("dst"), "m"), "dst").groupBy(F.col("src").alias("v")).agg(
        F.least(F.min("dst"), F.first("src")).alias("m"), F.min("m").alias("a"), F.max("m").alias("b"), F.count("*").alias("d")
    )
    whole = seen.groupBy("m").agg(F.count("*").alias("k"), F.min("d").alias("low"), F.max("d").alias("high"), F.max(((F.col("a") != F.col("m")) | (F.col("b") != F.col("m"))).cast("int")).alias("leaves"))
    return seen.join(whole.where("leaves = 0 and low = k - 1 and high = k - 1").select("m"), "m", "left_semi").select("v")


def clique_gather(
    g: Forest, ledger: RoundLedger | None = None, max_rounds: int = 40, most_pairs: int = MOST_PAIRS, settle_pairs: int = 1_000_000, most_joined: int = 2_000_000_000
) -> DataFrame:
    """(v, leader) for any graph; records rounds, copies and distinct added edges.

    A round that would join more than ``settle_pairs`` row by row, or look at more than ``most_pairs``, leaves out
    components that are cliques already: they add nothing, and joining all their pairs is most of the work. Raises :class:`TooManyPairs` before a round
    that would look at more than ``most_pairs``, or join more than ``most_joined`` row by row at hubs. Both limits
    hold for what is not completed as matrices."""
    edges, start, whole, labels = cut(g.edges.select("src", "dst", F.lit(0).alias("born")), "clique"), 0, [], None
    for n in range(max_rounds):
        rows, kept = edges.select("src", "dst", (F.col("born") == n).alias("fresh")), []
        ahead, joined = pairs_ahead(rows)
        if labels is None and ahead > WHOLE_PAIRS and most_pairs >= MOST_PAIRS and not (ledger and ledger.machines):
            start, (whole, labels, rest) = n, complete_whole(edges)
            drop_cut(edges)
            edges, rows = rest, rest.select("src", "dst", (F.col("born") == n).alias("fresh"))
            ahead, joined = pairs_ahead(rows)
        if n and (joined > settle_pairs or ahead > most_pairs):
            rows = cut(rows.join(cliques(edges).withColumnRenamed("v", "src"), "src", "left_anti"), "open")
            kept, (ahead, joined) = [rows], pairs_ahead(rows)
        if ahead > most_pairs or joined > most_joined:
            raise TooManyPairs(f"{ahead} pairs in round {n}, {joined} of them at hubs")
        copies, fresh = whole[n - start] if n - start < len(whole) else (0, 0)
        if ahead:
            new, used = _round(rows)
            added = cut(new, "fresh")
            drop_cut(*kept, *used)
            row = added.agg(F.count("*").alias("n"), F.sum("copies").alias("c")).first()
            copies, fresh = copies + (row.c or 0), fresh + row.n
        if ledger is not None:
            ledger.load(edges, "src")
            ledger.record("clique_gather", rounds=1, copies=copies, edges=fresh)
        if fresh == 0:
            break
        if not ahead:
            continue
        both = added.select(F.explode(F.array(F.struct("src", "dst"), F.struct(F.col("dst").alias("src"), F.col("src").alias("dst")))).alias("e")).select("e.src", "e.dst", F.lit(n + 1).alias("born"))
        grown = cut(edges.unionByName(both), "clique")
        drop_cut(edges, added)
        edges = grown
    else:
        raise RuntimeError(f"not gathered after {max_rounds} rounds")
    near = edges.groupBy(F.col("src").alias("v")).agg(F.min("dst").alias("m"))
    if labels is not None:
        near = near.unionByName(labels.withColumnRenamed("leader", "m"))
    return g.nodes.join(near, "v", "left").select("v", F.least("v", F.coalesce("m", "v")).alias("leader"))


def balls(g: Forest, hops: int, most_pairs: int = 2_000_000_000) -> DataFrame:
    """(v, w, d): w is d edges from v, 1 <= d <= ``hops``, by ceil(log2 hops) squarings of the reach.

    Raises :class:`TooManyPairs` before a squaring that would look at more than ``most_pairs``."""
    reach = g.edges.select(F.col("src").alias("v"), F.col("dst").alias("w"), F.lit(1).alias("d"))
    done = 1
    while done < hops:
        ahead, _ = pairs_ahead(reach.select(F.col("v").alias("src"), F.lit(True).alias("fresh")))
        if ahead > most_pairs:
            raise TooManyPairs(f"{ahead} pairs in balls of {2 * done} hops")
        a, b = reach.select("v", F.col("w").alias("m"), "d"), reach.select(F.col("v").alias("m"), "w", F.col("d").alias("e"))
        far = a.join(b, "m").where((F.col("v") != F.col("w")) & (F.col("d") + F.col("e") <= hops)).select("v", "w", (F.col("d") + F.col("e")).alias("d"))
        reach = cut(reach.unionByName(far).groupBy("v", "w").agg(F.min("d").alias("d")), "reach")
        done *= 2
    return reach.where(F.col("d") <= hops)


def neighbourhood(g: Forest, hops: int) -> DataFrame:
    """(v, w): w is within ``hops`` edges of v."""
    return balls(g, hops).select("v", "w")
