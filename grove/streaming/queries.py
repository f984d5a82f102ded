"""Streaming runs over what the event log holds now, with the batch result as their check."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from grove.operators.graph import Forest
from grove.session import cut, scratch, table
from grove.streaming import events as ev


def _stream(s: SparkSession, d: str) -> DataFrame:
    """The log as a stream of files; a pattern, so that one file will do as well as a folder."""
    raw = s.readStream.schema(table(s, d, "events").schema).parquet(f"{d}/events.parque[t]")
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def _sink(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run a stream to its end into files of the shared folder, and read them."""
    s = stream.sparkSession
    out, check = scratch(s, name), scratch(s, name + "-log")

    def write(batch: DataFrame, epoch: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/epoch={epoch}")

    ev.run_to_memory(stream, name, check, mode, write)
    return s.read.schema(stream.schema).parquet(f"{out}/epoch=*")


def tumbling(s: SparkSession, d: str) -> DataFrame:
    return _sink(ev.windowed_degree(_stream(s, d), "1 day"), "tumbling", "complete").select(F.date_format("start", "yyyy-MM-dd HH:mm").alias("start"), "event_type", "n")


def sliding(s: SparkSession, d: str) -> DataFrame:
    return _sink(ev.windowed_degree(_stream(s, d), "2 hours", "1 hour"), "sliding", "complete").groupBy("event_type").agg(F.sum("n").alias("n"))


def session_counts(s: SparkSession, d: str) -> DataFrame:
    return _sink(ev.sessions(_stream(s, d), "30 minutes"), "sessions", "complete").groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("events"))


def chains(s: SparkSession, d: str) -> DataFrame:
    return _sink(ev.stream_chain_edges(_stream(s, d)), "chains")


def deduped(s: SparkSession, d: str) -> DataFrame:
    twice = _stream(s, d).unionByName(_stream(s, d))
    return _sink(ev.dedupe(twice, "1000 days").select("event_id"), "deduped").agg(F.count("*").alias("n"), F.countDistinct("event_id").alias("kinds"))


def click_pairs(s: SparkSession, d: str) -> DataFrame:
    return _sink(ev.clicks_before_purchase(_stream(s, d), "1 hour", "1000 days"), "pairs")


def upkeep(s: SparkSession, d: str) -> DataFrame:
    """The certificate of the set kept over all events: chain edges stream in, after each batch the set is repaired."""
    e = table(s, d, "events").select(F.col("event_id").alias("v"))
    g = Forest(cut(e, "nodes"), cut(e.select(F.col("v").alias("src"), F.col("v").alias("dst")).limit(0), "edges"))
    keep = ev.SetUpkeep(g, g.nodes)
    stream = ev.stream_chain_edges(_stream(s, d)).where("v <> parent").select(F.col("v").alias("src"), F.col("parent").alias("dst"))
    ev.run_to_memory(stream, "upkeep", scratch(s, "upkeep-log"), "append", keep)
    return keep.certificate()


def late_rows(s: SparkSession, d: str) -> DataFrame:
    """Daily counts under the watermark's policy for late rows; the log is in order, so none is late."""
    return _sink(ev.windowed_degree(ev.with_late_policy(_stream(s, d), "10 minutes"), "1 day"), "late", "complete").groupBy("event_type").agg(F.sum("n").alias("n"))


def catalog() -> dict:
    chain = "select event_id as v, coalesce(lag(event_id) over (partition by user_id order by ts, event_id), event_id) as parent from events"
    return {
        "stream_tumbling": (tumbling, "select strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M') as start, event_type, count(*) as n from events group by 1, 2"),
        "stream_sliding": (sliding, "select event_type, 2 * count(*) as n from events group by 1"),
        "stream_sessions": (
            session_counts,
            "select user_id, cast(sum(new) as bigint) as sessions, count(*) as events from (select user_id, case when epoch_us(ts) - lag(epoch_us(ts)) over (partition by user_id order by ts) < 1800000000 then 0 else 1 end as new from events) group by 1",
        ),
        "stream_chain_edges": (chains, chain),
        "stream_dedupe": (deduped, "select count(*) as n, count(*) as kinds from events"),
        "stream_interval_join": (click_pairs, "select c.user_id, c.event_id as click, p.event_id as purchase from events c join events p on c.user_id = p.user_id and c.event_type = 'click' and p.event_type = 'purchase' and c.ts <= p.ts and epoch_us(c.ts) >= epoch_us(p.ts) - 3600000000"),
        "stream_set_upkeep": (upkeep, "with c as (" + chain + ") select (select count(*) from c) as n_nodes, (select count(*) from c where v <> parent) as n_edges, 0::bigint as inside_edges, 0::bigint as undominated"),
        "stream_late_policy": (late_rows, "select event_type, count(*) as n from events group by 1"),
    }
