"""Streams around the batch core: windows, chains, and upkeep of an independent set."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from grove.operators.graph import Forest, induced
from grove.operators.verify import certify_mis
from grove.session import cut


def with_late_policy(events: DataFrame, delay: str = "10 minutes") -> DataFrame:
    return events.withWatermark("ts", delay)


def windowed_degree(events: DataFrame, size: str = "1 hour", slide: str | None = None) -> DataFrame:
    """(start, event_type, n, users): tumbling, or sliding with ``slide``."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return events.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"), F.approx_count_distinct("user_id").alias("users")).select(F.col("w.start").alias("start"), "event_type", "n", "users")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """(user_id, start, end, n): a user's events with no gap of ``gap``."""
    s = events.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n"))
    return s.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def dedupe(events: DataFrame, delay: str = "10 minutes") -> DataFrame:
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def _chain(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
    last = state.get[0] if state.exists else None
    parents = [last if last is not None else int(rows["event_id"].iloc[0]), *rows["event_id"].iloc[:-1].tolist()]
    state.update((int(rows["event_id"].iloc[-1]),))
    yield pd.DataFrame({"v": rows["event_id"].to_numpy(), "parent": parents})


def stream_chain_edges(events: DataFrame) -> DataFrame:
    """(v, parent): each event's predecessor of its user; the state is a user's last event.

    Micro-batches must come in the order of time, as they do from a time-ordered log."""
    return events.select("user_id", "ts", "event_id").groupBy("user_id").applyInPandasWithState(_chain, "v long, parent long", "last long", "append", GroupStateTimeout.NoTimeout)


def clicks_before_purchase(events: DataFrame, within: str = "1 hour", delay: str = "2 hours") -> DataFrame:
    """(user_id, click, purchase): stream-stream interval join."""
    c = events.where("event_type = 'click'").select("user_id", F.col("event_id").alias("click"), F.col("ts").alias("click_ts")).withWatermark("click_ts", delay)
    p = events.where("event_type = 'purchase'").select(F.col("user_id").alias("u"), F.col("event_id").alias("purchase"), F.col("ts").alias("purchase_ts")).withWatermark("purchase_ts", delay)
    return c.join(p, F.expr(f"user_id = u and click_ts <= purchase_ts and click_ts >= purchase_ts - interval {within}")).select("user_id", "click", "purchase")


def repair(g: Forest, s: DataFrame, added: DataFrame) -> tuple[Forest, DataFrame]:
    """(grown graph, maximal independent set) after edges(src, dst) were added.

    Of two members that became adjacent the greater id goes; only nodes without a
    member near them are solved again."""
    from grove.operators.baselines import priority_mis

    grown = Forest.of(g.edges.unionByName(added.select("src", "dst")), g.nodes).cut()
    inside = grown.edges.join(s.select(F.col("v").alias("src")), "src", "left_semi").join(s.select(F.col("v").alias("dst")), "dst", "left_semi")
    kept = cut(s.join(inside.where("src > dst").select(F.col("src").alias("v")), "v", "left_anti"), "kept")
    near = grown.edges.join(kept.select(F.col("v").alias("src")), "src", "left_semi").select(F.col("dst").alias("v"))
    free = cut(grown.nodes.join(kept.unionByName(near), "v", "left_anti"), "free")
    return grown, cut(kept.unionByName(priority_mis(induced(grown, free).cut())), "mis")


class SetUpkeep:
    """foreachBatch handler that keeps a maximal independent set of all edges seen so far."""

    def __init__(self, g: Forest, s: DataFrame):
        self.g, self.s = g, s

    def __call__(self, batch: DataFrame, epoch: int) -> None:
        self.g, self.s = repair(self.g, self.s, batch)

    def certificate(self) -> DataFrame:
        return certify_mis(self.g, self.s)


def run_to_memory(stream: DataFrame, name: str, checkpoint: str, mode: str = "append", each: Callable | None = None) -> None:
    """Drive a stream over what is there now; for tests and replays."""
    w = stream.writeStream.trigger(availableNow=True).option("checkpointLocation", checkpoint).outputMode(mode)
    (w.foreachBatch(each) if each else w.format("memory").queryName(name)).start().awaitTermination()
