"""Retrieval: two stages, exhaustive, histogram only, bounded; identification, classes, segments, embeddings."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import SHORTLIST_CAP, TOP_K, WEIGHTS, MetricParams, check_weights
from ..functions import wavefront
from ..functions.metrics import USER_METRICS, attach_tokens, batch_similarities, batch_values, combine, pair_distance, pair_metric
from ..operators.histogram import cosine_pairs
from ..operators.periodicity import periodicity
from ..operators.shortlist import ranked, shortlist
from ..operators.onepass import ALIGNED, QueryBlock, best_segments, copies, each_copy, every_pair, histogram_block, picked, query_block, scan, top_classes, top_cosine, top_vectors


#: Different queries from which a first look for scores to prune by is worth its jobs.
MANY = 500


@dataclass(frozen=True)
class RetrievalPlan:
    """What a retrieval does; terms of weight zero are dropped before planning."""

    k: int = TOP_K
    policy: str = "printed"
    cap: int = SHORTLIST_CAP
    weights: dict[str, float] = field(default_factory=lambda: dict(WEIGHTS))
    params: MetricParams = MetricParams()
    how: str = "arrow"
    timed: bool = False
    exclude_self: bool = True
    strategy: str = "auto"

    @property
    def metrics(self) -> list[str]:
        return list(check_weights(self.weights))


def _answer(scored: DataFrame, k: int) -> DataFrame:
    return ranked(scored, "score", k).select("query_id", "rank", "cand_id", "score")


def score_pairs(pairs: DataFrame, queries: DataFrame, base: DataFrame, plan: RetrievalPlan) -> DataFrame:
    """SCORED: all similarities of the plan, and the score."""
    full = attach_tokens(pairs.select("query_id", "cand_id"), queries, base, plan.strategy)
    return combine(pair_metric(full, plan.metrics, plan.params, plan.how, plan.timed), plan.weights)


def all_pairs(queries: DataFrame, base: DataFrame, exclude_self: bool = True, max_len_ratio: float | None = None) -> DataFrame:
    """(query_id, cand_id) of a stated set of queries against the whole base: the exhaustive baseline's pairs.

    Only ids and lengths meet; Spark broadcasts the smaller side if its size allows, and else deals out blocks of both.
    """
    q = queries.select(F.col("seq_id").alias("query_id"), F.col("len").alias("m"))
    s = base.select(F.col("seq_id").alias("cand_id"), F.col("len").alias("n"))
    on = F.lit(True)
    if exclude_self:
        on = on & (F.col("query_id") != F.col("cand_id"))
    if max_len_ratio is not None:
        on = on & (F.greatest("m", "n") <= max_len_ratio * F.least("m", "n"))
    return s.join(q, on).select("query_id", "cand_id")


def distances(queries: DataFrame, base: DataFrame, metric: str, params: MetricParams = MetricParams(), timed: bool = False, decimals: int | None = None) -> DataFrame:
    """(query_id, cand_id, value) of all pairs: the distance itself, infinity as null; one pass over the base if the queries may
    be broadcast, where equal sequences are aligned, and their values rounded, once."""

    def compute(names, rows, x, cols, y, rows_t=None, cols_t=None):
        if (metric != "twed" or rows_t is None) and (v := wavefront.quick_at(metric, rows, x, cols, y, params)) is not None:
            return {"value": v}
        a, b, ta, tb = picked(rows, x, cols, y, rows_t, cols_t)
        return batch_values(lambda a, b, ta, tb: {"value": wavefront.twed(a, b, ta, tb, params) if metric == "twed" else getattr(wavefront, metric)(a, b, params)}, a, b, ta, tb, names)

    asked = copies(queries, timed)
    found = every_pair(asked, copies(base, timed), ["value"], compute, {}, timed)
    if found is None:
        return _rounded(pair_distance(attach_tokens(all_pairs(queries, base), queries, base), metric, params, "arrow", timed), decimals)
    return each_copy(_rounded(found.withColumn("value", F.when(F.abs("value") < float("inf"), F.col("value"))), decimals), asked)


def _rounded(df: DataFrame, decimals: int | None) -> DataFrame:
    kinds = dict(df.dtypes)
    return df if decimals is None else df.select(*[F.round(c, decimals).alias(c) if kinds[c] == "double" else c for c in df.columns])


def _every_score(asked: DataFrame, base: DataFrame, plan: RetrievalPlan) -> DataFrame | None:
    """(query_id, ids, s_..., score) by ``every_pair``, if the measures are known ones and the queries may be broadcast."""
    if any(m in USER_METRICS for m in plan.metrics) or plan.how != "arrow":
        return None

    def compute(names, rows, x, cols, y, rows_t=None, cols_t=None):
        found = {n: v for n in names if (n != "s_twed" or rows_t is None) and n[2:] in ALIGNED and (v := wavefront.quick_similarity_at(n[2:], rows, x, cols, y, plan.params)) is not None}
        rest = [n[2:] for n in names if n not in found]
        return found | ({f"s_{k}": v for k, v in batch_similarities(rest, *picked(rows, x, cols, y, rows_t, cols_t), plan.params).items()} if rest else {})

    grams = {"s_hist": 1} | ({"s_ngram": plan.params.ngram} if plan.params.ngram_kind == "cosine" else {})
    columns = [f"s_{m}" for m in plan.metrics]
    found = every_pair(asked, base, columns, compute, {c: n for c, n in grams.items() if c in columns}, plan.timed)
    return found and combine(found, plan.weights)


def score_all(queries: DataFrame, base: DataFrame, plan: RetrievalPlan, decimals: int | None = None) -> DataFrame:
    """SCORED of all pairs: as :func:`score_pairs`, by the same pass."""
    asked = copies(queries, plan.timed)
    found = _every_score(asked, copies(base, plan.timed), plan)
    if found is None:
        return _rounded(score_pairs(all_pairs(queries, base, plan.exclude_self), queries, base, plan), decimals)
    return each_copy(_rounded(found, decimals), asked, plan.exclude_self)


def retrieve(queries: DataFrame, base: DataFrame, plan: RetrievalPlan = RetrievalPlan(), n: int | None = None, periodic_only: bool = False, postings: DataFrame | None = None) -> DataFrame:
    """RANKED: histogram shortlist, then the weighted similarities of the shortlisted.  ``n`` and ``postings`` are the base's size
    and postings, if an index has them."""
    if periodic_only:
        # kept: it is counted, and read for its histograms and for the pairs' tokens
        base, n, postings = base.join(periodicity(base).where("is_periodic").select("seq_id"), "seq_id", "left_semi").persist(), None, None
    pairs = shortlist(queries, base, plan.policy, plan.cap, n, plan.exclude_self, postings=postings)
    return _answer(score_pairs(pairs, queries, base, plan), plan.k)


def _scanned(queries: DataFrame, base: DataFrame, plan: RetrievalPlan, prune: bool, counters: bool = False) -> DataFrame | None:
    """The one-pass form, if the measures are known ones and the queries may be broadcast."""
    if any(m in USER_METRICS for m in plan.metrics):
        return None
    if counters:
        block = query_block(queries, plan.k, plan.timed)
        reached = _reached(block, queries, base, plan) if block and prune else None
        return block and scan(block, base, plan.k, check_weights(plan.weights), plan.params, plan.timed, plan.exclude_self, prune, counters, reached)
    # Equal sequences are scored once.  Their scores are equal, so only the k of them with the smallest ids can be answers; and every
    # row of copies before a candidate's, by score and smallest id, has a candidate before it, so the best k rows hold the best k
    # candidates.  One more of both where the query itself is left out after.
    asked, k = copies(queries, plan.timed), plan.k + plan.exclude_self
    rows = copies(base, plan.timed, k, first=True).persist()
    block = query_block(asked, k, plan.timed)
    if block is None:
        return None
    once = replace(plan, k=k, exclude_self=False)
    reached = _reached(block, asked, rows, once) if prune and len(block.ids) >= MANY else None
    found = scan(block, rows, k, check_weights(plan.weights), plan.params, plan.timed, False, prune, False, reached)
    if found is None:
        return None
    top = ranked(found, "score", k).select("query_id", "cand_id", "score")
    return each_copy(top.join(rows.select(F.col("seq_id").alias("cand_id"), "ids"), "cand_id").select("query_id", "ids", "score"), asked, plan.exclude_self)


def _reached(block: QueryBlock, queries: DataFrame, base: DataFrame, plan: RetrievalPlan) -> np.ndarray | None:
    """For each query of the block the k-th score among its nearest by histogram: every partition may prune by it from the start."""
    near = top_cosine(block, base, 4 * plan.k, plan.exclude_self)
    if near is None:
        return None
    early = _answer(score_pairs(ranked(near, "cosine", 4 * plan.k), queries, base, plan), plan.k)
    rows = early.where(F.col("rank") == plan.k).select("query_id", "score").collect()  # a number for each query of the block
    low = {r["query_id"]: r["score"] for r in rows}
    return np.array([low.get(int(i), -np.inf) for i in block.ids])


def retrieve_exhaustive(queries: DataFrame, base: DataFrame, plan: RetrievalPlan = RetrievalPlan()) -> DataFrame:
    """The baseline: every candidate gets every similarity.  One pass over the base if the queries may be broadcast; else all
    pairs are made."""
    found = _scanned(queries, base, plan, prune=False) if plan.how == "arrow" else None
    return _answer(found if found is not None else score_pairs(all_pairs(queries, base, plan.exclude_self), queries, base, plan), plan.k)


def retrieve_histogram(queries: DataFrame, base: DataFrame, k: int = TOP_K, exclude_self: bool = True) -> DataFrame:
    """Stage 1 alone: the order of the cosines."""
    top = shortlist(queries, base, "fixed", k, None, exclude_self)
    return top.select("query_id", "rank", "cand_id", F.col("cosine").alias("score"))


def score_bound(weights: dict[str, float], params: MetricParams) -> Column:
    """An upper bound of the score from lengths m, n, common items c, sums of gap distances ga, gb, and exact ``s_hist``.

    LCSS is at most c; EDR at least max(m, n) - c; ERP at least beta times the difference of the gap sums (beta up to 1);
    TWED at least lam |m - n|; terms without a bound count as 1.
    """
    m, n, c = F.col("m"), F.col("n"), F.col("common")
    mean = F.when(m + n > 0, (m + n) / 2).otherwise(1.0)
    exact = params.lcss_eps == 0, params.edr_eps == 0
    bounds = {
        "hist": F.col("s_hist"),
        "lcss": F.least(F.lit(1.0), c / mean) if exact[0] else F.least(m, n) / mean,
        "edr": c / F.greatest(m, n, F.lit(1)) if exact[1] else F.least(m, n) / F.greatest(m, n, F.lit(1)),
        "erp": F.exp(-params.beta * F.abs(F.col("ga") - F.col("gb")) / mean) if params.beta <= 1 else F.lit(1.0),
        "twed": F.exp(-params.lam * F.abs(m - n) / (2 * mean)),
    }
    total = F.lit(0.0)
    for k, w in weights.items():
        total = total + w * bounds.get(k, F.lit(1.0))
    return F.when((m > 0) & (n > 0), total).otherwise(1.0)


def bounded_pairs(queries: DataFrame, base: DataFrame, plan: RetrievalPlan) -> DataFrame:
    """(query_id, cand_id, bound) of all pairs: from counts that both sides share, without aligning any."""
    from ..operators.histogram import word_counts

    q = word_counts(queries).select(F.col("seq_id").alias("query_id"), "word", F.col("cnt").alias("cq"))
    s = word_counts(base).select(F.col("seq_id").alias("cand_id"), "word", F.col("cnt").alias("cs"))
    shared = s.join(q, "word").groupBy("query_id", "cand_id").agg(F.sum(F.least("cq", "cs")).alias("common"))
    cosine = cosine_pairs(queries, base, plan.exclude_self).select("query_id", "cand_id", F.col("cosine").alias("s_hist"))
    gap = F.aggregate("tokens", F.lit(0.0), lambda t, w: t + F.abs(w - plan.params.gap))
    mq = queries.select(F.col("seq_id").alias("query_id"), F.col("len").alias("m"), gap.alias("ga"))
    ms = base.select(F.col("seq_id").alias("cand_id"), F.col("len").alias("n"), gap.alias("gb"))
    pairs = all_pairs(queries, base, plan.exclude_self).join(shared, ["query_id", "cand_id"], "left").join(cosine, ["query_id", "cand_id"], "left")
    pairs = pairs.join(mq, "query_id").join(ms, "cand_id").na.fill(0, ["common"]).na.fill(0.0, ["s_hist"])
    return pairs.select("query_id", "cand_id", score_bound(plan.weights, plan.params).alias("bound"))


def retrieve_bounded(queries: DataFrame, base: DataFrame, plan: RetrievalPlan = RetrievalPlan(), probe: int | None = None) -> DataFrame:
    """The exhaustive answer, aligning fewer pairs.

    One pass over the base if the queries may be broadcast (see ``onepass.Scorer``).  Else the most promising pairs by bound are
    scored first; their k-th score is a threshold, and only pairs whose bound reaches it are scored after.
    """
    found = _scanned(queries, base, plan, prune=True)
    if found is not None:
        return _answer(found, plan.k)
    bounds = bounded_pairs(queries, base, plan).persist()
    first = ranked(bounds, "bound", probe or 4 * plan.k).select("query_id", "cand_id")
    early = score_pairs(first, queries, base, plan).select("query_id", "cand_id", "score").persist()
    kth = _answer(early, plan.k).groupBy("query_id").agg(F.min("score").alias("low"), F.count("*").alias("n"))
    threshold = kth.select("query_id", F.when(F.col("n") >= plan.k, F.col("low")).otherwise(-1.0).alias("low"))
    rest = bounds.join(threshold, "query_id").where(F.col("bound") >= F.col("low") - 1e-9).join(first, ["query_id", "cand_id"], "left_anti")
    return _answer(early.unionByName(score_pairs(rest, queries, base, plan).select("query_id", "cand_id", "score")), plan.k)


def pruning_counters(queries: DataFrame, base: DataFrame, plan: RetrievalPlan = RetrievalPlan()) -> DataFrame:
    """One row: pairs, pairs of which anything was aligned, alignment cells visited, and cells of the exhaustive baseline."""
    found = _scanned(queries, base, plan, prune=True, counters=True)
    if found is None:
        raise ValueError("more queries than may be broadcast")
    return found.agg(*[F.sum(c).alias(c) for c in found.columns])


def identify(answers: DataFrame, base: DataFrame, vote: str = "top1", min_score: float | None = None) -> DataFrame:
    """(query_id, class_id): one identifier for each query, from its ranked answers.

    top1: the class of the first; majority: the most frequent class; score: the largest sum of scores; ties by best rank.
    Below ``min_score`` (of the first answer) there is none.
    """
    rows = answers.join(base.select(F.col("seq_id").alias("cand_id"), "class_id"), "cand_id")
    by_class = rows.groupBy("query_id", "class_id").agg(F.count("*").alias("n"), F.sum("score").alias("total"), F.min("rank").alias("first"), F.max("score").alias("best"))
    order = {"top1": F.struct(-F.col("first")), "majority": F.struct("n", -F.col("first")), "score": F.struct(F.round("total", 9), -F.col("first"))}[vote]
    best = by_class.groupBy("query_id").agg(F.max_by("class_id", order).alias("class_id"), F.max("best").alias("best"))
    found = F.col("class_id") if min_score is None else F.when(F.col("best") >= min_score, F.col("class_id"))
    return best.select("query_id", found.alias("class_id"))


def retrieve_classes(scored: DataFrame, base: DataFrame, k: int = TOP_K, by: str = "max") -> DataFrame:
    """(query_id, rank, class_id, score): classes by their best or mean instance."""
    rows = scored.join(base.select(F.col("seq_id").alias("cand_id"), "class_id"), "cand_id")
    total = F.max("score") if by == "max" else F.avg("score")
    out = rows.groupBy("query_id", "class_id").agg(total.alias("score"))
    return ranked(out.withColumnRenamed("class_id", "cand_id"), "score", k).select("query_id", "rank", F.col("cand_id").alias("class_id"), "score")


def retrieve_classes_histogram(queries: DataFrame, base: DataFrame, k: int = TOP_K, by: str = "max", exclude_self: bool = True) -> DataFrame:
    """The same by the cosine of histograms, over sequences that share a word: classes are summed up where the cosines are made,
    if the queries' histograms may be broadcast; else the pairs are."""
    block = histogram_block(queries, k)
    found = block and top_classes(block, base, k, by, exclude_self)
    if found is None:
        return retrieve_classes(cosine_pairs(queries, base, exclude_self).withColumnRenamed("cosine", "score"), base, k, by)
    return ranked(found.withColumnRenamed("class_id", "cand_id"), "score", k).select("query_id", "rank", F.col("cand_id").alias("class_id"), "score")


def segments(base: DataFrame, window: int, hop: int) -> DataFrame:
    """SEQ of windows: (seq_id of the whole, start, tokens, times, len); sequences shorter than a window are one segment.

    Windows start at 0, hop, 2 hop, ...; where the last of them ends before the sequence does, one more ends with it.
    """
    last = F.greatest(F.lit(0), F.col("len") - window)
    starts = F.array_union(F.sequence(F.lit(0), last, F.lit(hop)), F.array(last))
    rows = base.select("seq_id", "class_id", "tokens", "times", F.explode(starts).alias("start"))
    cut = rows.withColumn("tokens", F.slice("tokens", F.col("start") + 1, F.lit(window))).withColumn("times", F.slice("times", F.col("start") + 1, F.lit(window)))
    return cut.withColumn("len", F.size("tokens"))


def retrieve_segments(queries: DataFrame, base: DataFrame, window: int, hop: int, plan: RetrievalPlan = RetrievalPlan()) -> DataFrame:
    """(query_id, rank, cand_id, start, score): the best segment of each sequence, and the best sequences.

    If the queries may be broadcast, equal sequences are cut and scored once, as in :func:`retrieve_exhaustive`, and of every
    partition only the best sequences of each query are sent."""
    asked, k = copies(queries, plan.timed), plan.k + plan.exclude_self
    if plan.how == "arrow" and not any(m in USER_METRICS for m in plan.metrics):
        rows = copies(base, plan.timed, k, first=True).persist()
        found = best_segments(asked, rows, window, hop, k, check_weights(plan.weights), plan.params, plan.timed)
        if found is not None:
            flat = ranked(found, "score", k)
            every = flat.join(rows.select(F.col("seq_id").alias("cand_id"), "ids"), "cand_id").select("query_id", "ids", "start", "score")
            return ranked(each_copy(every, asked, plan.exclude_self), "score", plan.k).select("query_id", "rank", "cand_id", "start", "score")
    key = F.struct(F.col("seq_id").alias("whole"), "start").alias("seq_id")
    parts = segments(base, window, hop).select(key, "class_id", "tokens", "times", "len")
    q = queries.select("seq_id", "tokens", "times", "len")
    pairs = all_pairs(q, parts, exclude_self=False)
    if plan.exclude_self:
        pairs = pairs.where(F.col("query_id") != F.col("cand_id.whole"))
    scored = score_pairs(pairs, q, parts, plan).select("query_id", "cand_id.whole", "cand_id.start", "score")
    best = scored.groupBy("query_id", "whole").agg(F.max(F.struct(F.round("score", 9).alias("s"), (-F.col("start")).alias("m"))).alias("b"))
    flat = best.select("query_id", F.col("whole").alias("cand_id"), (-F.col("b.m")).alias("start"), F.col("b.s").alias("score"))
    return ranked(flat, "score", plan.k).select("query_id", "rank", "cand_id", "start", "score")


def retrieve_embedding(queries: DataFrame, base: DataFrame, k: int = TOP_K, vec: str = "embedding", vec_id: str = "vec_id") -> DataFrame:
    """The continuous baseline: cosine of vectors, a stated set of queries against all; the query itself is left out.

    One pass of matrix products over the base if the queries may be broadcast; else all pairs are made.  A zero vector has
    cosine 0 with all; vectors of another length than the query's are no candidates.
    """
    found = top_vectors(queries.select(F.col(vec_id).alias("seq_id"), F.col(vec).alias("v")), base.select(F.col(vec_id).alias("seq_id"), F.col(vec).alias("v")), k)
    if found is not None:
        return _answer(found, k)

    def norm(c: str) -> Column:
        return F.sqrt(F.aggregate(F.transform(c, lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda s, x: s + x))

    q = queries.select(F.col(vec_id).alias("query_id"), F.col(vec).alias("x"), norm(vec).alias("nx"))
    s = base.select(F.col(vec_id).alias("cand_id"), F.col(vec).alias("y"), norm(vec).alias("ny"))
    dot = F.aggregate(F.zip_with("x", "y", lambda u, v: u.cast("double") * v.cast("double")), F.lit(0.0), lambda t, u: t + u)
    pairs = s.join(q, (F.col("query_id") != F.col("cand_id")) & (F.size("x") == F.size("y")))
    score = F.when((F.col("nx") > 0) & (F.col("ny") > 0), dot / (F.col("nx") * F.col("ny"))).otherwise(0.0)
    return _answer(pairs.select("query_id", "cand_id", score.alias("score")), k)


def retrieve_embedding_approx(queries: DataFrame, base: DataFrame, k: int = TOP_K, distance: float = 1.2, vec: str = "embedding", vec_id: str = "vec_id", tables: int = 8, width: float = 1.0) -> DataFrame:
    """The same by MLlib's random projections: answers within ``distance`` of unit vectors that share a bucket."""
    from pyspark.ml.feature import BucketedRandomProjectionLSH, Normalizer
    from pyspark.ml.functions import array_to_vector

    def unit(df: DataFrame, name: str) -> DataFrame:
        rows = df.select(F.col(vec_id).alias(name), array_to_vector(F.transform(vec, lambda x: x.cast("double"))).alias("raw"))
        return Normalizer(inputCol="raw", outputCol="unit").transform(rows).select(name, "unit")

    q, s = unit(queries, "query_id"), unit(base, "cand_id")
    model = BucketedRandomProjectionLSH(inputCol="unit", outputCol="hashes", bucketLength=width, numHashTables=tables, seed=7).fit(s)
    near = model.approxSimilarityJoin(q, s, distance, "d").select("datasetA.query_id", "datasetB.cand_id", (1 - F.col("d") * F.col("d") / 2).alias("score"))
    return _answer(near.where("query_id <> cand_id"), k)
