"""Relational operators around the methods: joins that Spark lacks, windows, subtotals, comparisons, samples."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from seqsearch.functions.times import micros


def interval_join(left: DataFrame, right: DataFrame, key: str, ts_left: str, ts_right: str, low: float, high: float, bucket: float | None = None) -> DataFrame:
    """Pairs of equal key with low <= right - left <= high seconds.

    Time is cut into buckets of the interval's width; each left row looks into the buckets that its interval touches, so the
    join is by equality and never pairs a whole key with itself.
    """
    width = bucket or max(high - low, 1e-6)
    a, b = micros(ts_left) / 1_000_000.0, micros(ts_right) / 1_000_000.0
    first, last = F.floor((a + low) / width), F.floor((a + high) / width)
    le = left.withColumn("__b", F.explode(F.sequence(first, last)))
    ri = right.withColumn("__b", F.floor(b / width))
    gap = b - a
    return le.join(ri, [key, "__b"]).where((gap >= low) & (gap <= high)).drop("__b")


def asof_join(left: DataFrame, right: DataFrame, key: str, ts: str, values: list[str], direction: str = "backward", tolerance: float | None = None, tie: str | None = None) -> DataFrame:
    """``left`` with, for each row, ``values`` of the latest (backward) or next (forward) row of ``right`` of the same key.

    Both sides are stacked and a window carries the last right row on: one shuffle and sort, no join.  ``tie`` orders right rows of equal
    time.  At equal times the right row counts.
    """
    packed = F.struct(F.col(ts).alias("t"), *[F.col(v) for v in values])
    r = right.select(F.col(key), F.col(ts), packed.alias("__r"), F.lit(None).cast("struct<x:int>").alias("__none"), (F.col(tie).cast("double") if tie else F.lit(0.0)).alias("__tie"), F.lit(0 if direction == "backward" else 1).alias("__side"))
    own = [c for c in left.columns]
    le = left.select(F.col(key), F.col(ts), F.struct(*[F.col(c) for c in own]).alias("__l"), F.lit(0.0).alias("__tie"), F.lit(1 if direction == "backward" else 0).alias("__side"))
    both = le.unionByName(r.drop("__none"), allowMissingColumns=True)
    order = Window.partitionBy(key).orderBy(ts, "__side", "__tie")
    if direction == "backward":
        found = F.last("__r", ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, Window.currentRow))
    else:
        found = F.first("__r", ignorenulls=True).over(order.rowsBetween(Window.currentRow, Window.unboundedFollowing))
    out = both.withColumn("__m", found).where(F.col("__l").isNotNull())
    near = F.lit(True)
    if tolerance is not None:
        near = F.abs(micros(ts) - micros("__m.t")) <= int(tolerance * 1_000_000)
    names = {v: v if v not in own else f"{v}_right" for v in values}
    return out.select("__l.*", *[F.when(near, F.col(f"__m.{v}")).alias(names[v]) for v in values])


def keep(df: DataFrame, ids: DataFrame, left: str, right: str) -> DataFrame:
    return df.join(ids, df[left] == ids[right], "left_semi")


def exclude(df: DataFrame, ids: DataFrame, left: str, right: str) -> DataFrame:
    return df.join(ids, df[left] == ids[right], "left_anti")


def breakdown(df: DataFrame, dims: list[str], measures: dict[str, Column], how: str = "rollup", sets: list[list[str]] | None = None) -> DataFrame:
    """Subtotals by rollup, cube or given grouping sets."""
    agg = [m.alias(n) for n, m in measures.items()]
    if how == "sets":
        return df.groupingSets(sets or [dims, []], *dims).agg(*agg)
    return getattr(df, how)(*dims).agg(*agg)


def sequence_stats(sequences: DataFrame, by: str = "class_id") -> DataFrame:
    """(class, sequences, items, longest, distinct, top_token): one explode, counted before it is shuffled."""
    items = sequences.select(by, F.explode("tokens").alias("w")).groupBy(by, "w").agg(F.count("*").alias("c"))
    words = items.groupBy(by).agg(F.sum("c").alias("items"), F.count("*").alias("distinct"), F.max_by("w", F.struct("c", -F.col("w"))).alias("top_token"))
    sizes = sequences.groupBy(by).agg(F.count("*").alias("sequences"), F.max("len").alias("longest"))
    return sizes.join(words, by, "left")


def rank_candidates(pairs: DataFrame, k: int, how: str = "row_number", by: str = "score") -> DataFrame:
    """Answers with rank, dense_rank or row_number up to k; ties share a rank but in row_number, where the id decides."""
    order = [F.round(by, 9).desc()] + ([F.asc("cand_id")] if how == "row_number" else [])
    return pairs.withColumn("rank", getattr(F, how)().over(Window.partitionBy("query_id").orderBy(*order))).where(F.col("rank") <= k)


def event_gaps(events: DataFrame) -> DataFrame:
    """Events with the seconds since the user's previous one and until the next."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    t = micros("ts") / 1_000_000.0
    return events.select("event_id", "user_id", (t - F.lag(t).over(w)).alias("since"), (F.lead(t).over(w) - t).alias("until"))


def running_mix(events: DataFrame, rows: int = 5) -> DataFrame:
    """Share of purchases among each user's last ``rows`` events."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-(rows - 1), 0)
    return events.select("event_id", "user_id", F.avg((F.col("event_type") == "purchase").cast("double")).over(w).alias("mix"))


def range_frame(events: DataFrame, seconds: int = 3600) -> DataFrame:
    """Number and value of a user's events in the last so many seconds, this one included."""
    w = Window.partitionBy("user_id").orderBy(micros("ts")).rangeBetween(-seconds * 1_000_000, 0)
    return events.select("event_id", "user_id", F.count("*").over(w).alias("n"), F.max("value").over(w).alias("top"))


def top_pairs(pairs: DataFrame, k: int, by: str = "score") -> DataFrame:
    return pairs.orderBy(F.round(by, 9).desc(), "query_id", "cand_id").limit(k)


def compare_results(a: DataFrame, b: DataFrame) -> DataFrame:
    """(which, n): how many (query, candidate) are in both, only in a, only in b."""
    x, y = a.select("query_id", "cand_id").distinct(), b.select("query_id", "cand_id").distinct()
    joined = x.withColumn("a", F.lit(1)).join(y.withColumn("b", F.lit(1)), ["query_id", "cand_id"], "full")
    which = F.when(F.col("a").isNull(), "only_b").when(F.col("b").isNull(), "only_a").otherwise("both")
    return joined.groupBy(which.alias("which")).agg(F.count("*").alias("n"))


def stratified(df: DataFrame, by: str, k: int, key: str, seed: int = 7) -> DataFrame:
    """k rows of each stratum, by a hash of the key: the same on every run."""
    h = F.md5(F.concat_ws("|", F.lit(str(seed)), F.col(key).cast("string")))
    return df.withColumn("__n", F.row_number().over(Window.partitionBy(by).orderBy(h, key))).where(F.col("__n") <= k).drop("__n")


def like_length_pairs(sequences: DataFrame, ratio: float) -> DataFrame:
    """(a, b), a < b, of all sequences whose lengths differ by a factor of ``ratio`` at most; an empty one meets only empty ones.

    Lengths fall into bands of one factor each, so that a pair is in the same band or the next: an equi-join on the band, where
    one side is in two, with the lengths as residual.
    """
    band = F.floor(F.log(F.greatest(F.col("len"), F.lit(1)).cast("double")) / math.log(ratio) + 1e-9)
    rows = sequences.select(F.col("seq_id").alias("id"), F.col("len").alias("n"), F.when(F.col("len") > 0, band).otherwise(F.lit(-9)).cast("int").alias("band"))
    left = rows.select(F.col("id").alias("x"), F.col("n").alias("m"), "band")
    right = rows.select(F.col("id").alias("y"), "n", F.explode(F.array("band", F.col("band") + 1)).alias("band"))
    near = left.join(right, "band").where(F.greatest("m", "n") <= ratio * F.least("m", "n"))
    # in neighbouring bands the longer one is on the left; in the same band each pair comes from either side
    return near.where("x <> y").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct()
