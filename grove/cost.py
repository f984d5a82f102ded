"""Cost figures that need no run: machines and memory of the model, predicted rounds."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession

from grove.operators.baselines import predicted_rounds

METHODS = ("clique", "inspace", "small_memory", "priority", "tree_local", "rooted", "prefix", "ball", "local_finish", "gather_clique", "gather_inspace", "flood", "reduction_steps", "sparse_matching", "arboricity", "list_colouring", "lower_bound")


def mpc_plan(variant: str, n: int, mem_exp: float = 0.5) -> tuple[str, int, int, int, int]:
    """(variant, n, rows a machine holds, machines, rows in all): S = n^a; n^(1 - a / 3) machines
    for clique gathering, n^(1 - a) in space."""
    s = round(n**mem_exp)
    m = round(n ** (1 - mem_exp / 3) if variant == "clique" else n ** (1 - mem_exp))
    return variant, n, s, m, s * m


def mpc_plans(spark: SparkSession, sizes: list[int], mem_exp: float = 0.5) -> DataFrame:
    rows = [mpc_plan(v, n, mem_exp) for n in sizes for v in ("clique", "inspace")]
    return spark.createDataFrame(rows, "variant string, n long, local_memory long, machines long, total long")


def predictions(spark: SparkSession, sizes: list[int], delta: int = 64, d: int = 32, decay: float = 0.5, alpha: float = 0.5) -> DataFrame:
    rows = [(m, n, round(float(predicted_rounds(m, n, delta, d, decay, alpha)), 6)) for n in sizes for m in METHODS]
    return spark.createDataFrame(rows, "method string, n long, rounds double")


def load_bound(rows: int, machines: int, heaviest: int) -> float:
    """What a machine may hold when ``rows`` rows lie on ``machines`` machines by a hash of their key and no
    key has more than ``heaviest`` of them: twice the mean and a log factor of the heaviest."""
    return 2 * rows / machines + heaviest * (math.log2(machines) + 4)
