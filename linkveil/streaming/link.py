"""Linkage of arriving records, and the queue of requests and replies, as Structured Streaming.

All streams here run to the end of what is there (``availableNow``), keep their progress in the session's checkpoint
folder and write Parquet.  Micro-batches are written under their number, so a repeated batch replaces itself.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkveil.functions import bits
from linkveil.operators import block, classify, compare
from linkveil.session import checkpoint_dir


def folder(spark: SparkSession, name: str) -> str:
    return f"{checkpoint_dir(spark)}/stream-{name}-{uuid.uuid4().hex}"


def run_batches(stream: DataFrame, handle: Callable[[DataFrame, int], None], where: str, mode: str = "append") -> dict | None:
    """Runs a stream to its end with ``handle`` on each micro-batch; the last progress report."""
    query = stream.writeStream.outputMode(mode).foreachBatch(handle).option("checkpointLocation", f"{where}/progress").trigger(availableNow=True).start()
    query.awaitTermination()
    return [dict(p) if isinstance(p, dict) else p for p in query.recentProgress]


def link_arrivals(arrivals: DataFrame, stored: DataFrame, t: float, where: str, m: int = 1024) -> DataFrame:
    """Arriving encoded records (rec_id, words, ones, keys) against the stored ones: left_id, right_id, sim, g, p, batch.

    The stored side is read anew in each micro-batch, and the threshold is that of the batch's start.
    """
    spark = stored.sparkSession
    columns = [*bits.names(m), "ones"]

    def handle(batch: DataFrame, number: int) -> None:
        pairs = block.candidates(stored, batch, columns, per_task=None)
        found = classify.threshold(compare.record_similarity(pairs, m), t)
        found.select("left_id", "right_id", "sim", "g", "p").write.mode("overwrite").parquet(f"{where}/links/batch={number}")

    run_batches(arrivals, handle, where)
    return spark.read.parquet(f"{where}/links")


def uncertain_requests(links: DataFrame, p_limit: float = 0.8) -> DataFrame:
    """Links to ask the owners about."""
    return links.where(F.col("p") < p_limit).select(F.concat_ws("-", "left_id", "right_id").alias("pair_id"), "left_id", "right_id", "p")


def event_stream(spark: SparkSession, path: str, schema, per_trigger: int | None = None) -> DataFrame:
    """Events with a time zone, as watermarks need it."""
    reader = spark.readStream.schema(schema)
    if per_trigger:
        reader = reader.option("maxFilesPerTrigger", per_trigger)
    return reader.parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def throughput(stream: DataFrame, length: str = "1 hour", delay: str = "2 hours", slide: str | None = None) -> DataFrame:
    """Reviews by window (tumbling, or sliding with ``slide``) and kind."""
    window = F.window("ts", length, slide) if slide else F.window("ts", length)
    return stream.withWatermark("ts", delay).groupBy(window.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("hour"), "event_type", "n")


def sessions(stream: DataFrame, gap: str = "30 minutes", delay: str = "2 hours") -> DataFrame:
    """Sessions of each reviewer."""
    return stream.withWatermark("ts", delay).groupBy("user_id", F.session_window("ts", gap).alias("s")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("s.start").alias("start"), "n")


def answered(stream: DataFrame, ask: str, reply: str, within: str = "1 hour", delay: str = "2 hours") -> DataFrame:
    """Requests joined with the replies that come within a time, both sides forgotten after their watermarks."""
    side = lambda kind, name: stream.where(F.col("event_type") == kind).select(F.col("event_id").alias(name), F.col("user_id").alias(f"{name}_user"), F.col("ts").alias(f"{name}_ts")).withWatermark(f"{name}_ts", delay)
    a, b = side(ask, "request"), side(reply, "reply")
    on = (F.col("request_user") == F.col("reply_user")) & (F.col("reply_ts") > F.col("request_ts")) & (F.col("reply_ts") <= F.col("request_ts") + F.expr(f"INTERVAL {within}"))
    return a.join(b, on).select("request", "reply")


LIFE = 3600.0


def _track(key: tuple, chunks: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
    """One key's open requests: completed by a later reply, or expired after LIFE of event time, by a timer if nothing comes."""
    asked = list(state.get[0]) if state.exists else []
    done = expired = 0
    for rows in [] if state.hasTimedOut else chunks:
        for at, kind in sorted(zip(rows["at"].tolist(), rows["event_type"].tolist(), strict=True)):
            expired += sum(a < at - LIFE for a in asked)
            asked = [a for a in asked if a >= at - LIFE]
            if kind == "reply":
                done += len(asked)
                asked = []
            else:
                asked.append(at)
    now = state.getCurrentWatermarkMs() / 1000
    expired += sum(a < now - LIFE for a in asked)
    asked = sorted(a for a in asked if a >= now - LIFE)
    if asked:
        state.update((asked,))
        state.setTimeoutTimestamp(int(max(asked[0] + LIFE, now) * 1000) + 1000)
    elif state.exists:
        state.remove()
    yield pd.DataFrame({"user_id": [key[0]], "open": [len(asked)], "completed": [done], "expired": [expired]})


def request_states(stream: DataFrame, ask: str, reply: str, delay: str = "1 hour") -> DataFrame:
    """user_id, open (now), completed and expired (in this micro-batch): a custom state with a life of an hour for each open request.

    Rows behind the watermark are dropped.  A user's state goes with the last open request, which a timer sees to for users who
    send nothing more."""
    rows = stream.withWatermark("ts", delay).where(F.col("event_type").isin(ask, reply))
    rows = rows.select("ts", "user_id", F.col("ts").cast("double").alias("at"), F.when(F.col("event_type") == reply, "reply").otherwise("ask").alias("event_type"))
    return rows.groupBy("user_id").applyInPandasWithState(
        _track, "user_id long, open long, completed long, expired long", "asked array<double>", "update", "EventTimeTimeout"
    )


def keep_last(where: str) -> Callable[[DataFrame, int], None]:
    """A handler for complete output: the latest state replaces the one before."""

    def handle(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{where}/out")

    return handle


def append_to(where: str) -> Callable[[DataFrame, int], None]:
    def handle(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{where}/out/batch={number}")

    return handle
