"""Streaming queries: each runs its stream to the end and returns what was written."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkveil.operators import block
from linkveil.queries import linkage, surrounding
from linkveil.streaming import link

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def register(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLE_SQL[f.__name__] = sql
        return f

    return register


def _events(spark, sf_dir, where):
    """The events as a stream of four files in order of time, two to a micro-batch."""
    events = surrounding.events(spark, sf_dir)
    events.repartitionByRange(4, "ts").write.parquet(f"{where}/in")
    return link.event_stream(spark, f"{where}/in", events.schema, 2)


@query(linkage.ORACLE_SQL["threshold_predictions"])
def stream_incremental(spark, sf_dir):
    """B's encoded records arrive in files and are linked with A's stored ones: the same pairs as the batch."""
    where = link.folder(spark, "arrivals")
    keyed = linkage.record_filters(spark, sf_dir).join(block.keys(linkage.registry(spark, sf_dir), linkage.P.key).select("rec_id", "keys"), "rec_id")
    stored, arriving = keyed.where("owner = 'A'"), keyed.where("owner = 'B'")
    arriving.repartition(4).write.parquet(f"{where}/in")
    stream = spark.readStream.schema(arriving.schema).option("maxFilesPerTrigger", 2).parquet(f"{where}/in")
    return link.link_arrivals(stream, stored, linkage.T, where).select("left_id", "right_id", "g", "p")


@query(surrounding.ORACLE_SQL["op_time_windows"])
def stream_throughput(spark, sf_dir):
    """Hourly counts of a stream in complete mode."""
    where = link.folder(spark, "throughput")
    link.run_batches(link.throughput(_events(spark, sf_dir, where)), link.keep_last(where), where, "complete")
    out = spark.read.parquet(f"{where}/out")
    return out.select(F.col("hour").cast("timestamp_ntz").alias("hour"), "event_type", "n")


@query(surrounding.ORACLE_SQL["op_sessions"])
def stream_sessions(spark, sf_dir):
    where = link.folder(spark, "sessions")
    link.run_batches(link.sessions(_events(spark, sf_dir, where)), link.keep_last(where), where, "complete")
    return spark.read.parquet(f"{where}/out").groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"))


@query(surrounding.ORACLE_SQL["op_join_interval"])
def stream_replies(spark, sf_dir):
    """Stream-stream interval join of requests and replies."""
    where = link.folder(spark, "replies")
    link.run_batches(link.answered(_events(spark, sf_dir, where), "click", "purchase"), link.append_to(where), where)
    return spark.read.parquet(f"{where}/out").select("request", "reply")


@query()
def stream_request_ttl(spark, sf_dir):
    """Open, completed and expired requests by user, from a custom state."""
    where = link.folder(spark, "ttl")
    link.run_batches(link.request_states(_events(spark, sf_dir, where), "click", "purchase"), link.append_to(where), where, "update")
    return spark.read.parquet(f"{where}/out").select("user_id", "open", "completed", "expired")


@query()
def stream_late_replies(spark, sf_dir):
    """The newer half of the events first, then the older ones in two micro-batches: rows that are behind the watermark of the
    micro-batch before are dropped and counted."""
    where = link.folder(spark, "late")
    events = surrounding.events(spark, sf_dir)
    at = F.col("ts").cast("timestamp").cast("double")
    low, middle = events.agg(F.percentile_approx(at, [0.25, 0.5])).first()[0]
    for part in (events.where(at >= middle), events.where((at >= low) & (at < middle)), events.where(at < low)):
        part.coalesce(1).write.mode("append").parquet(f"{where}/in")
    stream = link.event_stream(spark, f"{where}/in", events.schema, 1)
    progress = link.run_batches(link.throughput(stream, delay="1 hour"), link.append_to(where), where)
    dropped = sum(s["numRowsDroppedByWatermark"] for p in progress for s in p["stateOperators"])
    seen = sum(p["numInputRows"] for p in progress)
    return spark.createDataFrame([(seen, dropped)], "seen long, dropped long")
