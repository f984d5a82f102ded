"""What the findings of round 3 named: rounds of completion and of rooting that were too large as rows."""

import random

import pytest

from grove.operators import clique, whole
from grove.operators.clique import TooManyPairs, clique_gather
from grove.operators.graph import Forest
from grove.operators.ledger import RoundLedger


def _tangle(spark):
    """Paths with shuffled ids, a tree with hubs, a cycle and a clique, side by side."""
    r, edges = random.Random(5), []
    for i, n in enumerate((2, 3, 9, 33, 40)):
        ids = [1000 * (i + 1) + k for k in range(n)]
        r.shuffle(ids)
        edges += list(zip(ids[:-1], ids[1:], strict=True))
    edges += [(20_000 + k, 20_000 + r.randrange(max(1, k // 6))) for k in range(1, 90)]
    edges += [(30_000 + k, 30_000 + (k + 1) % 11) for k in range(11)]
    edges += [(40_000 + a, 40_000 + b) for a in range(7) for b in range(a)]
    return Forest.of(spark.createDataFrame(edges, "src long, dst long"), spark.createDataFrame([(5,)], "v long")).cut()


@pytest.mark.parametrize("small,strip,largest,pairs", [(20, 16, 100, 0), (8, 5, 35, 2_000)])
def test_completion_as_matrices_has_the_same_rounds(spark, monkeypatch, small, strip, largest, pairs):
    g, plain, ledger = _tangle(spark), RoundLedger(), RoundLedger()
    want = {tuple(x) for x in clique_gather(g, plain).collect()}
    for name, value in (("SMALL", small), ("STRIP", strip), ("LARGEST", largest)):
        monkeypatch.setattr(whole, name, value)
    monkeypatch.setattr(clique, "WHOLE_PAIRS", pairs)
    assert {tuple(x) for x in clique_gather(g, ledger).collect()} == want
    assert [r[8:10] for r in ledger.rows] == [r[8:10] for r in plain.rows]


def test_a_hub_over_the_joined_pairs_is_completed(spark, monkeypatch):
    star = Forest.of(spark.createDataFrame([(0, i) for i in range(1, 700)] + [(1, 1000)], "src long, dst long")).cut()
    with pytest.raises(TooManyPairs):
        clique_gather(star, most_joined=1_000)
    monkeypatch.setattr(clique, "WHOLE_PAIRS", 1_000)
    assert {r.leader for r in clique_gather(star, most_joined=1_000).collect()} == {0}
