"""Protocols and measures: leave-one-out, K references a class, rank scores, rates, recall, cost."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..config import RANK_DECAY


def leave_k_out(sequences: DataFrame, k: int = 1, seed: int = 7) -> tuple[DataFrame, DataFrame]:
    """(references, queries): ``k`` references of each class, chosen by a hash; the rest are queries."""
    order = F.md5(F.concat_ws("|", F.lit(str(seed)), F.col("seq_id").cast("string")))
    place = F.row_number().over(Window.partitionBy("class_id").orderBy(order, "seq_id"))
    rows = sequences.withColumn("place", place)
    return rows.where(F.col("place") <= k).drop("place"), rows.where(F.col("place") > k).drop("place")


def filter_classes(sequences: DataFrame, min_per_class: int = 2, max_per_class: int | None = None, n_classes: int | None = None) -> DataFrame:
    """Classes with at least so many sequences; of each at most so many; the largest classes."""
    sizes = sequences.groupBy("class_id").agg(F.count("*").alias("size")).where(F.col("size") >= min_per_class)
    if n_classes is not None:
        sizes = sizes.orderBy(F.desc("size"), "class_id").limit(n_classes)
    out = sequences.join(sizes.select("class_id"), "class_id", "left_semi")
    if max_per_class is not None:
        place = F.row_number().over(Window.partitionBy("class_id").orderBy("seq_id"))
        out = out.withColumn("place", place).where(F.col("place") <= max_per_class).drop("place")
    return out


def at_level(sequences: DataFrame, level: str, genres: int = 10) -> DataFrame:
    """The truth at a level of the labels: choreography (the class itself) or genre (classes in ``genres`` groups, by number)."""
    if level == "choreography":
        return sequences
    if level != "genre":
        raise ValueError(level)
    return sequences.withColumn("class_id", F.pmod(F.col("class_id").cast("bigint"), F.lit(genres)).cast("string"))


def query_scores(ranked: DataFrame, truth: DataFrame, queries: DataFrame | None = None, k: int = 3) -> DataFrame:
    """(query_id, class_id, best_rank, score): the first rank of the same class within k, and what it counts.

    ``truth``: (seq_id, class_id) of all sequences.  Queries without any answer count 0 if ``queries`` (seq_id) is given.
    """
    cls = truth.select("seq_id", "class_id")
    mine = cls.select(F.col("seq_id").alias("query_id"), "class_id")
    theirs = cls.select(F.col("seq_id").alias("cand_id"), F.col("class_id").alias("cand_class"))
    asked = (queries if queries is not None else ranked.select(F.col("query_id").alias("seq_id")).distinct()).select(F.col("seq_id").alias("query_id"))
    hits = ranked.where(F.col("rank") <= k).join(theirs, "cand_id").join(mine, "query_id").where("class_id = cand_class").groupBy("query_id").agg(F.min("rank").alias("best_rank"))
    out = asked.join(mine, "query_id").join(hits, "query_id", "left")
    score = F.coalesce(F.get(F.array(*[F.lit(x) for x in RANK_DECAY]), F.col("best_rank") - 1), F.lit(0.0))
    return out.select("query_id", "class_id", "best_rank", score.alias("score"))


def measures(scores: DataFrame, method: str, k: int = 3) -> DataFrame:
    """METRICS: one row: mean score, match rate and rank-1 rate in percent, number of queries, histogram of best ranks."""
    hit = F.col("best_rank").isNotNull()
    bins = F.map_from_arrays(F.array(*[F.lit(x) for x in (*map(str, range(1, k + 1)), "none")]), F.array(*[F.sum((F.col("best_rank") == r).cast("long")) for r in range(1, k + 1)], F.sum((~hit).cast("long"))))
    return scores.agg(F.avg("score").alias("mean_score"), (100 * F.avg(hit.cast("double"))).alias("match_rate"), (100 * F.avg(F.coalesce(F.col("best_rank") == 1, F.lit(False)).cast("double"))).alias("rank1_rate"), F.count("*").alias("queries"), bins.alias("rank_hist")).select(F.lit(method).alias("method"), "*")


def rank_distribution(scores: DataFrame, k: int = 3) -> DataFrame:
    """(best_rank, queries, share): counts of the best ranks 1..k and none; empty ones show 0."""
    spark = scores.sparkSession
    names = spark.createDataFrame([(str(r),) for r in range(1, k + 1)] + [("none",)], "best_rank string")
    found = scores.groupBy(F.coalesce(F.col("best_rank").cast("string"), F.lit("none")).alias("best_rank")).agg(F.count("*").alias("queries"))
    total = scores.agg(F.count("*").alias("total"))
    out = names.join(found, "best_rank", "left").crossJoin(total)  # one row: the count
    return out.select("best_rank", F.coalesce("queries", F.lit(0)).alias("queries"), F.when(F.col("total") > 0, F.coalesce("queries", F.lit(0)) / F.col("total")).otherwise(0.0).alias("share"))


def per_class(scores: DataFrame, dims: tuple[str, ...] = ("class_id",), how: str = "rollup") -> DataFrame:
    """Subtotals of the measures by the dimensions: rollup or cube."""
    grouped = getattr(scores, how)(*dims)
    return grouped.agg(F.count("*").alias("queries"), F.avg("score").alias("mean_score"), F.avg(F.col("best_rank").isNotNull().cast("double")).alias("match_rate"))


def confusion(ranked: DataFrame, truth: DataFrame) -> DataFrame:
    """(class_id, answer_class, n): the class of the first answer against that of the query."""
    cls = truth.select("seq_id", "class_id")
    a = cls.select(F.col("seq_id").alias("query_id"), "class_id")
    b = cls.select(F.col("seq_id").alias("cand_id"), F.col("class_id").alias("answer_class"))
    return ranked.where("rank = 1").join(a, "query_id").join(b, "cand_id").groupBy("class_id", "answer_class").agg(F.count("*").alias("n"))


def relative_performance(index: DataFrame, exhaustive: DataFrame) -> DataFrame:
    """One row of ratios of two METRICS rows."""
    a = index.select("mean_score", "match_rate", "rank1_rate")
    b = exhaustive.select(*[F.col(c).alias(f"{c}_all") for c in ("mean_score", "match_rate", "rank1_rate")])
    ratio = [F.when(F.col(f"{c}_all") != 0, F.col(c) / F.col(f"{c}_all")).alias(c) for c in ("mean_score", "match_rate", "rank1_rate")]
    return a.crossJoin(b).select(*ratio)  # one row by one row


def shortlist_recall(short: DataFrame, exhaustive: DataFrame) -> DataFrame:
    """(found, wanted, recall): how many of the exhaustive answers are in the shortlist."""
    keys = ["query_id", "cand_id"]
    found = exhaustive.join(short.select(*keys).withColumn("hit", F.lit(1)), keys, "left")
    return found.agg(F.sum(F.coalesce("hit", F.lit(0))).cast("bigint").alias("found"), F.count("*").alias("wanted")).withColumn("recall", F.col("found") / F.col("wanted"))


def cost_counters(queries: DataFrame, base: DataFrame, pairs: DataFrame) -> DataFrame:
    """One row: cosine comparisons, postings touched, pairs re-ranked, and alignment cells of those pairs (one measure)."""
    from ..operators.histogram import word_counts

    touched = word_counts(base).join(word_counts(queries).select("word"), "word").agg(F.count("*").alias("postings_touched"))
    q = queries.select(F.col("seq_id").alias("query_id"), F.col("len").alias("m"))
    s = base.select(F.col("seq_id").alias("cand_id"), F.col("len").alias("n"))
    work = pairs.select("query_id", "cand_id").join(q, "query_id").join(s, "cand_id").agg(F.count("*").alias("pairs_reranked"), F.coalesce(F.sum(F.col("m").cast("long") * F.col("n")), F.lit(0)).alias("cells"))
    nq, ns = queries.agg(F.count("*").alias("nq")), base.agg(F.count("*").alias("ns"))
    return nq.crossJoin(ns).crossJoin(touched).crossJoin(work).select((F.col("nq") * F.col("ns")).alias("comparisons"), "postings_touched", "pairs_reranked", "cells")  # single rows


def timed(make: Callable[[], DataFrame]) -> tuple[float, int]:
    """(seconds, rows) of running a query to the end."""
    began = time.time()
    df = make()
    df.write.format("noop").mode("overwrite").save()
    return time.time() - began, df.count()
