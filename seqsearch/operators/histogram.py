"""Token histograms and their cosine by inverted postings."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.times import let


def word_counts(sequences: DataFrame) -> DataFrame:
    """POSTING: (seq_id, word, cnt).  A sequence is one row, so nearly all counting is done before the shuffle."""
    return sequences.select("seq_id", F.explode("tokens").alias("word")).groupBy("seq_id", "word").agg(F.count("*").alias("cnt"))


def norms(counts: DataFrame) -> DataFrame:
    """(seq_id, norm2): the squared length of each histogram, an exact integer."""
    return counts.groupBy("seq_id").agg(F.sum(F.col("cnt") * F.col("cnt")).alias("norm2"))


def norm_of(tokens: str | Column) -> Column:
    """The squared length from the sequence itself, without a shuffle."""
    w = F.array_sort(F.col(tokens) if isinstance(tokens, str) else tokens)
    zero = F.struct(F.lit(None).cast("int").alias("word"), F.lit(0).cast("bigint").alias("run"), F.lit(0).cast("bigint").alias("total"))

    def step(s: Column, x: Column) -> Column:
        run = F.when(s["word"].eqNullSafe(x), s["run"] + 1).otherwise(F.lit(1).cast("bigint"))
        return F.struct(x.alias("word"), run.alias("run"), (s["total"] + 2 * run - 1).alias("total"))

    return F.aggregate(w, zero, step, lambda s: s["total"])


def histogram(sequences: DataFrame, norm: str = "l2") -> DataFrame:
    """(seq_id, word, cnt, weight) with weights of length one (l2), sum one (l1), or counts (none)."""
    counts = word_counts(sequences)
    if norm == "none":
        return counts.withColumn("weight", F.col("cnt").cast("double"))
    size = norms(counts) if norm == "l2" else counts.groupBy("seq_id").agg(F.sum("cnt").alias("norm2"))
    by = F.sqrt(F.col("norm2").cast("double")) if norm == "l2" else F.col("norm2")
    return counts.join(size, "seq_id").select("seq_id", "word", "cnt", (F.col("cnt") / by).alias("weight"))


def dense_histogram(sequences: DataFrame, vocabulary: int) -> DataFrame:
    """(seq_id, hist): the l2-normalised histogram as an array of ``vocabulary`` numbers, from one sort of the tokens."""
    rows = sequences.select("seq_id", runs("tokens").alias("runs"), F.sqrt(norm_of("tokens").cast("double")).alias("n"))
    rows = rows.select("seq_id", F.map_from_entries("runs").alias("m"), "n")
    value = lambda k: F.coalesce(F.try_element_at("m", k.cast("int")) / F.col("n"), F.lit(0.0))
    return rows.select("seq_id", F.transform(F.sequence(F.lit(0), F.lit(vocabulary - 1)), value).alias("hist"))


def runs(tokens: str) -> Column:
    """Array of (word, count) of a sequence, by word, without a shuffle: each end of a run in the sorted tokens, less the one before."""
    def counted(w: Column) -> Column:
        n = F.size(w)
        ends = F.filter(F.sequence(F.lit(1), n), lambda i: (i == n) | (F.element_at(w, i) != F.get(w, i)))
        ends = F.when(n > 0, ends).otherwise(F.array().cast("array<int>"))
        return let(ends, lambda e: F.transform(e, lambda i, k: F.struct(F.element_at(w, i).alias("word"), (i - F.when(k > 0, F.get(e, k - 1)).otherwise(0)).alias("cnt"))))

    return let(F.array_sort(tokens), counted)


def cosine_pairs(queries: DataFrame, base: DataFrame, exclude_self: bool = True, broadcast_rows: int = 200_000, postings: DataFrame | None = None) -> DataFrame:
    """(query_id, cand_id, dot, cosine) of all pairs that share a word.

    Queries whose histograms may be broadcast meet the base in one pass of matrix products, unless ``postings`` are stored; others
    by the join of both sides' postings on the word, which makes a row for each word that a pair shares.  Dot products and norms are integers until the last division.  The queries' postings are broadcast if their number, which is
    counted first, is small; the sums are pre-aggregated before the shuffle by pair.  ``postings`` are the base's, if stored.
    """
    if postings is None:
        from .onepass import MOST_IN_BLOCKS, every_cosine, histogram_block

        block = histogram_block(queries, most=MOST_IN_BLOCKS)
        found = block and every_cosine(block, base, exclude_self)
        if found is not None:
            return found
    q = queries.select("seq_id", "tokens", norm_of("tokens").alias("n2"))
    s = base.select("seq_id", "tokens", norm_of("tokens").alias("n2"))
    left = word_counts(q).select(F.col("seq_id").alias("query_id"), "word", F.col("cnt").alias("cq"))
    right = (word_counts(s) if postings is None else postings).select(F.col("seq_id").alias("cand_id"), "word", F.col("cnt").alias("cs"))
    small = queries.select(F.sum(F.least("len", F.lit(10_000))).alias("n")).first()["n"] or 0
    joined = right.join(F.broadcast(left) if small <= broadcast_rows else left, "word")
    if exclude_self:
        joined = joined.where("query_id <> cand_id")
    dots = joined.groupBy("query_id", "cand_id").agg(F.sum(F.col("cq") * F.col("cs")).alias("dot"))
    nq, ns = q.select(F.col("seq_id").alias("query_id"), F.col("n2").alias("nq")), s.select(F.col("seq_id").alias("cand_id"), F.col("n2").alias("ns"))
    return dots.join(nq, "query_id").join(ns, "cand_id").select("query_id", "cand_id", "dot", (F.col("dot") / F.sqrt(F.col("nq").cast("double") * F.col("ns").cast("double"))).alias("cosine"))


def cluster_histograms(sequences: DataFrame, k: int, vocabulary: int, seed: int = 7) -> DataFrame:
    """(seq_id, cluster): k-means over the histograms, as sparse vectors of length one."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.feature import CountVectorizerModel, Normalizer

    words = sequences.select("seq_id", F.transform("tokens", lambda w: w.cast("string")).alias("words"))
    counts = CountVectorizerModel.from_vocabulary([str(w) for w in range(vocabulary)], "words", "raw").transform(words)
    rows = Normalizer(inputCol="raw", outputCol="features").transform(counts)
    model = KMeans(k=k, seed=seed, featuresCol="features", predictionCol="cluster").fit(rows)
    return model.transform(rows).select("seq_id", "cluster")
