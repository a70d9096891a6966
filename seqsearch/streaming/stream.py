"""Sequences, histograms and the index from a stream of events."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqsearch.functions.times import micros

from ..operators.index import merge_index
from ..plans.retrieve import RetrievalPlan, retrieve
from ..sources.tokens import event_token


def sessions(events: DataFrame, gap: str = "30 minutes", delay: str | None = "1 hour", buckets: int = 1) -> DataFrame:
    """SEQ of closed sessions: events of a user without a pause of ``gap``; works on streams and on tables alike.

    Rows later than ``delay`` behind the newest are dropped on a stream (None: all are kept, in complete mode).  seq_id is a hash of user and start.
    """
    rows = events.select("user_id", "ts", "event_id", event_token(buckets).alias("token"))
    if events.isStreaming and delay:
        rows = rows.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)
    item = F.struct("ts", "event_id", "token")
    grouped = rows.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.array_sort(F.collect_list(item)).alias("items"))
    start = F.col("w.start")
    times = F.transform("items", lambda x: (micros(x["ts"]) - micros(start)) / 1_000_000.0)
    return grouped.select(F.xxhash64("user_id", start).alias("seq_id"), F.col("user_id").cast("string").alias("class_id"), F.lit(0).alias("instance_id"), F.col("items.token").alias("tokens"), times.alias("times"), F.size("items").alias("len"), start.alias("start"))


def histograms(events: DataFrame, width: str = "1 day", slide: str | None = None, delay: str | None = "1 day", buckets: int = 1) -> DataFrame:
    """(user_id, start, word, cnt) of tumbling or sliding windows."""
    rows = events.select("user_id", "ts", event_token(buckets).alias("word"))
    if events.isStreaming and delay:
        rows = rows.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return rows.groupBy(w.alias("w"), "user_id", "word").agg(F.count("*").alias("cnt")).select("user_id", F.col("w.start").alias("start"), "word", "cnt")


def without_replays(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Each event id once, within the watermark."""
    if not events.isStreaming:
        return events.dropDuplicates(["event_id"])
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def index_batch(path: str, buckets: int = 16) -> Callable[[DataFrame, int], None]:
    """For foreachBatch: merge closed sequences into the index, as the batch of that number.  A batch that was committed is not
    merged again, and one that a crash cut short is written anew, so a replay changes nothing."""

    def merge(batch: DataFrame, batch_id: int) -> None:
        merge_index(batch.sparkSession, path, batch, buckets, f"stream-{batch_id:09d}")

    return merge


def match_batch(base: DataFrame, sink: str, plan: RetrievalPlan = RetrievalPlan(policy="capped")) -> Callable[[DataFrame, int], None]:
    """For foreachBatch: each closed sequence retrieves from a static base; answers are written by batch id."""

    def match(batch: DataFrame, batch_id: int) -> None:
        batch.persist()
        retrieve(batch, base, plan).write.mode("overwrite").parquet(f"{sink}/batch={batch_id}")
        batch.unpersist()

    return match


def code_drift(assigned: DataFrame, alpha: float = 0.5) -> DataFrame:
    """(code, hits, ema): stateful counts of codes and their moving average per micro-batch, on a stream of (code)."""
    out, state = "code int, hits long, ema double", "hits long, ema double"

    def update(key, frames, kept):
        hits, ema = kept.get if kept.exists else (0, 0.0)
        new = sum(len(f) for f in frames)
        hits, ema = hits + new, alpha * ema + (1 - alpha) * new
        kept.update((hits, ema))
        yield pd.DataFrame({"code": [key[0]], "hits": [hits], "ema": [ema]})

    return assigned.groupBy("code").applyInPandasWithState(update, out, state, "update", "NoTimeout")
