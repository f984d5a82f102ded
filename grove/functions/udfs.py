"""Functions for SQL users: aggregates in native form, table functions by component."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import udtf

from grove.functions import coins


def component_digest(member: str | Column) -> Column:
    """Order-free hash of a group's members; merges map-side."""
    return F.bit_xor(F.xxhash64(member))


def mis_weight(weight: str | Column, in_set: str | Column) -> Column:
    """Total weight of the chosen rows of a group."""
    return F.sum(F.when(F.col(in_set) if isinstance(in_set, str) else in_set, F.col(weight) if isinstance(weight, str) else weight).otherwise(0))


def lowest_diff_bit(a: Column, b: Column) -> Column:
    """Index of the lowest bit in which two BIGINTs differ (64 if equal)."""
    x = a.bitwiseXOR(b)
    return F.bit_count(x.bitwiseAND(-x) - 1)


@F.pandas_udf(T.IntegerType())
def lowest_diff_bit_pandas(a: pd.Series, b: pd.Series) -> pd.Series:
    """The same as an Arrow-batched function."""
    import numpy as np

    x = (a.to_numpy(np.int64) ^ b.to_numpy(np.int64)).view(np.uint64)
    low = x & (~x + np.uint64(1))
    return pd.Series(np.bitwise_count(low - np.uint64(1)).astype(np.int32))


@udtf(returnType="v: bigint, in_set: boolean")
class SolveComponent:
    """solve_component(TABLE(select leader, src, dst ...) PARTITION BY leader): greedy set of each component.

    A row with src = dst is a node."""

    def __init__(self) -> None:
        self.near: dict[int, set[int]] = {}

    def eval(self, row) -> None:
        a, b = row["src"], row["dst"]
        self.near.setdefault(a, set())
        self.near.setdefault(b, set())
        if a != b:
            self.near[a].add(b)
            self.near[b].add(a)

    def terminate(self) -> Iterator[tuple[int, bool]]:
        out: set[int] = set()
        for v in sorted(self.near):
            if not self.near[v] & out:
                out.add(v)
            yield v, v in out


@udtf(returnType="v: bigint, ancestor: bigint, dist: int")
class TreePaths:
    """tree_paths(TABLE(select root, v, parent ...) PARTITION BY root): every ancestor of every node of a tree."""

    def __init__(self) -> None:
        self.up: dict[int, int] = {}

    def eval(self, row) -> None:
        self.up[row["v"]] = row["parent"]

    def terminate(self) -> Iterator[tuple[int, int, int]]:
        for v in self.up:
            x, n = v, 0
            while self.up.get(x, x) != x:
                x, n = self.up[x], n + 1
                yield v, x, n


def register(spark: SparkSession) -> None:
    coins.register(spark)
    spark.udtf.register("solve_component", SolveComponent)
    spark.udtf.register("tree_paths", TreePaths)
