"""Shortlists: how many, and which."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..config import SHORTLIST_CAP
from .histogram import cosine_pairs
from .nearest import nearest
from .onepass import MOST_KEPT, histogram_block, top_cosine

#: Most queries that meet the base in one pass over it; more are dealt out themselves, if the base's histograms may be broadcast.
ONE_PASS = 1_000


def shortlist_size(n: int | Column, policy: str = "printed", cap: int = SHORTLIST_CAP):
    """printed: max(n div 2, min(cap, n)), which grows with n; capped: min(cap, n); fixed: cap."""
    if isinstance(n, int):
        return {"printed": max(n // 2, min(cap, n)), "capped": min(cap, n), "fixed": cap}[policy]
    least = F.least(F.lit(cap).cast("bigint"), n.cast("bigint"))
    return {"printed": F.greatest(F.floor(n / 2), least), "capped": least, "fixed": F.lit(cap).cast("bigint")}[policy]


def ranked(pairs: DataFrame, by: str, k: int | None = None, decimals: int = 9) -> DataFrame:
    """Pairs with ``rank`` per query: by the rounded score, then by id; ``k`` limits before the shuffle."""
    w = Window.partitionBy("query_id").orderBy(F.round(by, decimals).desc(), "cand_id")
    out = pairs.withColumn("rank", F.row_number().over(w))
    return out.where(F.col("rank") <= k) if k is not None else out


def shortlist(queries: DataFrame, base: DataFrame, policy: str = "printed", cap: int = SHORTLIST_CAP, n: int | None = None, exclude_self: bool = True, fill: bool = True, postings: DataFrame | None = None) -> DataFrame:
    """(query_id, cand_id, cosine, rank): the L most similar of the base for each query, ties by id.

    ``n`` is the size of the base, from the index's metadata if known.  Where fewer than L share a word with the query, the
    rest is filled in order of id (``fill``).  Few queries meet the base in one pass that keeps L of each query in a partition;
    many, or many answers, are dealt out to tasks that have the base's histograms (``nearest``); where those are more than may be
    broadcast, there is a join of postings, where only queries that need it meet candidates that they share nothing with.
    """
    if n is None and policy != "fixed":
        n = base.count()
    size = shortlist_size(n or 0, policy, cap)
    if fill:
        asked = queries.count()
        if asked > ONE_PASS or asked * size > MOST_KEPT:
            found = nearest(queries, base, size, exclude_self)
            if found is not None:
                return found
        block = histogram_block(queries, size)
        near = block and top_cosine(block, base, size, exclude_self)
        if near is not None:
            return ranked(near, "cosine", size).select("query_id", "cand_id", "cosine", "rank")
    top = ranked(cosine_pairs(queries, base, exclude_self, postings=postings).select("query_id", "cand_id", "cosine"), "cosine", size)
    if not fill:
        return top
    have = top.groupBy("query_id").agg(F.count("*").alias("have"))
    short = queries.select(F.col("seq_id").alias("query_id")).join(have, "query_id", "left").where(F.coalesce("have", F.lit(0)) < size).select("query_id", F.coalesce("have", F.lit(0)).alias("have"))
    # the first ids of the base: as many as any query can lack, besides those that it has
    spare = base.select(F.col("seq_id").alias("cand_id")).orderBy("cand_id").limit(2 * size + 1)
    lack = short.join(spare, F.lit(True)).join(top.select("query_id", "cand_id"), ["query_id", "cand_id"], "left_anti")
    if exclude_self:
        lack = lack.where("query_id <> cand_id")
    w = Window.partitionBy("query_id").orderBy("cand_id")
    extra = lack.withColumn("rank", F.row_number().over(w) + F.col("have")).where(F.col("rank") <= size).select("query_id", "cand_id", F.lit(0.0).alias("cosine"), F.col("rank").cast("int").alias("rank"))
    return top.unionByName(extra)
