"""The ledger of a run: logical rounds, the exchanges of the plans that were run, and, for a
given number of logical machines, what the fullest one holds, sends and receives."""

from __future__ import annotations

import re
from collections.abc import Iterator
from contextlib import contextmanager
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from grove import session

_FIELDS = "seq int, stage string, logical_rounds int, exchanges int, rows_moved long, max_bucket_rows long, live long, delta long, copies long, distinct_edges long, note string"


def exchanges_of(df: DataFrame) -> int:
    """Shuffles and broadcasts in the plan that Spark made for ``df``."""
    return len(re.findall(r"\b(?:Broadcast)?Exchange ", df._jdf.queryExecution().executedPlan().toString()))


def bucket_load(df: DataFrame, key: str, machines: int) -> DataFrame:
    """(bucket, rows): what each of ``machines`` logical machines would hold, hashed by ``key``."""
    return df.groupBy(F.pmod(F.xxhash64(key), F.lit(machines)).alias("bucket")).agg(F.count("*").alias("rows"))


def bucket_traffic(messages: DataFrame, sender: str, receiver: str, machines: int) -> DataFrame:
    """(bucket, sent, received): messages between logical machines; what one machine sends to one receiver is one message."""
    at = lambda c: F.pmod(F.xxhash64(c), F.lit(machines))
    once = messages.select(at(sender).alias("a"), at(receiver).alias("b"), receiver).distinct()
    return (
        once.select(F.explode(F.array(F.struct(F.col("a").alias("bucket"), F.lit(1).alias("s"), F.lit(0).alias("r")), F.struct(F.col("b").alias("bucket"), F.lit(0).alias("s"), F.lit(1).alias("r")))).alias("x"))
        .groupBy("x.bucket").agg(F.sum("x.s").alias("sent"), F.sum("x.r").alias("received"))
    )


@dataclass
class RoundLedger:
    """Counts only: a row of O(1) numbers for each recorded round.

    ``machines`` logical machines make it measure loads and traffic; :meth:`measuring` makes it
    count the shuffles of every plan that is written."""

    machines: int | None = None
    rows: list[tuple] = field(default_factory=list)
    seen: int = 0
    held: int = 0
    moved: int = 0
    busiest: int = 0

    @contextmanager
    def measuring(self) -> Iterator[RoundLedger]:
        def watch(df: DataFrame) -> None:
            self.seen += exchanges_of(df)

        session.WATCHERS.append(watch)
        try:
            yield self
        finally:
            session.WATCHERS.remove(watch)

    def load(self, df: DataFrame, key: str) -> None:
        """Measure what the machines hold; goes with the next record."""
        if self.machines:
            row = bucket_load(df, key, self.machines).agg(F.max("rows").alias("m"), F.sum("rows").alias("t")).first()
            self.held, self.moved = max(self.held, row.m or 0), self.moved + (row.t or 0)

    def traffic(self, messages: DataFrame, sender: str, receiver: str) -> None:
        if self.machines:
            row = bucket_traffic(messages, sender, receiver, self.machines).agg(F.max(F.col("sent") + F.col("received")).alias("m"), F.sum("sent").alias("t")).first()
            self.busiest, self.moved = max(self.busiest, row.m or 0), self.moved + (row.t or 0)

    def record(self, stage: str, rounds: int = 0, live: int = -1, delta: int = -1, copies: int = 0, edges: int = 0, note: str = "") -> None:
        self.rows.append((len(self.rows), stage, rounds, self.seen, self.moved, self.held, live, delta, copies, edges, note))
        self.seen = self.moved = self.held = 0

    def rounds(self, stage: str | None = None) -> int:
        return sum(r[2] for r in self.rows if stage in (None, r[1]))

    def exchanges(self) -> int:
        return sum(r[3] for r in self.rows)

    def copies(self) -> int:
        return sum(r[8] for r in self.rows)

    def max_load(self) -> int:
        return max((r[5] for r in self.rows), default=0)

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows, _FIELDS)
