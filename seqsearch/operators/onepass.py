"""One pass over the base with the queries at hand.

The queries are few, and broadcast once their size is checked.  Every partition of the base compares its sequences with all
of them by matrix products, and keeps the best k of each query; only those are shuffled.  Beyond the bound there is the join
of postings (``histogram.cosine_pairs``) or of pairs.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import MetricParams
from ..functions import wavefront
from ..functions.metrics import batch_similarities, batch_values
from .histogram import runs

#: Most queries, tokens of queries and answers of a partition for which the queries are broadcast.
MOST_QUERIES, MOST_TOKENS, MOST_KEPT = 20_000, 4_000_000, 2_000_000
#: Most words of histograms that are broadcast: of one query each word counts once.
MOST_WORDS = 4_000_000
#: The same for queries that meet the base in blocks.
MOST_IN_BLOCKS = 16_000_000
#: Numbers in one matrix.
_CELLS = 2_000_000
ALIGNED = ("twed", "lcss", "edr", "erp")


@dataclass
class QueryBlock:
    ids: np.ndarray
    tokens: list[np.ndarray]
    times: list[np.ndarray] | None


def query_block(queries: DataFrame, k: int, timed: bool = False) -> QueryBlock | None:
    """The queries on the driver, or None if they are more than may be broadcast, or if k of each are too many to keep."""
    rows = queries.select("seq_id", "tokens", *(["times"] if timed else []))
    size = rows.agg(F.count("*").alias("n"), F.sum(F.size("tokens")).alias("t")).first()
    if size["n"] > MOST_QUERIES or (size["t"] or 0) > MOST_TOKENS or size["n"] * k > MOST_KEPT:
        return None
    got = rows.toArrow().combine_chunks()
    tokens = [np.asarray(t, np.int64) for t in got.column("tokens").to_pylist()]
    times = [np.asarray(t, float) if t is not None else np.arange(1.0, len(w) + 1) for t, w in zip(got.column("times").to_pylist(), tokens, strict=True)] if timed else None
    return QueryBlock(got.column("seq_id").to_numpy().astype(np.int64), tokens, times)


@dataclass
class HistogramBlock:
    """Histograms of queries: their ids, and (row, word, count) of each word."""

    ids: np.ndarray
    at: np.ndarray
    word: np.ndarray
    count: np.ndarray

    def space(self) -> GramSpace:
        return GramSpace.of_counts(len(self.ids), self.at, self.word, self.count)


def histogram_block(queries: DataFrame, k: int = 1, most: int | None = None) -> HistogramBlock | None:
    """The queries' histograms on the driver, or None if they don't fit one matrix, or if k of each are too many to keep.
    With ``most``, of the words of all, they need not fit one matrix.

    A histogram over few words is far smaller than its sequence, so many more queries fit than in :func:`query_block`.
    """
    rows = queries.select("seq_id", F.array_distinct("tokens").alias("words"))
    size = rows.agg(F.count("*").alias("n"), F.sum(F.size("words")).alias("t"), F.max(F.array_max("words")).alias("top"), F.min(F.array_min("words")).alias("low")).first()
    if size["n"] * k > MOST_KEPT or (size["t"] or 0) > (most or MOST_WORDS):
        return None
    if most is None and size["top"] is not None and size["n"] > MOST_QUERIES and size["n"] * (size["top"] - size["low"] + 1) > 4 * _CELLS:
        return None
    counted = queries.select("seq_id", runs("tokens").alias("runs"))
    got = counted.select("seq_id", F.col("runs.word").alias("w"), F.col("runs.cnt").alias("c")).toArrow().combine_chunks()
    ids, w, c = (got.column(k).combine_chunks() if isinstance(got.column(k), pa.ChunkedArray) else got.column(k) for k in range(3))
    sizes = np.asarray(pc.fill_null(pc.list_value_length(w), 0).to_numpy(zero_copy_only=False), np.int64)
    flat = (x.flatten().to_numpy(zero_copy_only=False).astype(np.int64) for x in (w, c))
    return HistogramBlock(ids.to_numpy(zero_copy_only=False).astype(np.int64), np.repeat(np.arange(len(ids)), sizes), *flat)


def _flat(rows: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """(row number, token) of all tokens."""
    sizes = np.fromiter(map(len, rows), np.int64, len(rows))
    return np.repeat(np.arange(len(rows)), sizes), np.concatenate([*rows, np.zeros(0, np.int64)]).astype(np.int64)


def _counted(at: np.ndarray, word: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, word, count) of rows' words."""
    order = np.lexsort((word, at))
    a, w = at[order], word[order]
    first = np.flatnonzero(np.concatenate(([True], (a[1:] != a[:-1]) | (w[1:] != w[:-1])))) if len(a) else np.zeros(0, np.int64)
    return a[first], w[first], np.diff(np.append(first, len(a)))


class GramSpace:
    """Counts of n-grams as rows of a matrix, over the grams of the queries; other grams of a sequence only add to its length."""

    def __init__(self, rows: list[np.ndarray], n: int) -> None:
        self.n = n
        self.radix = int(max((int(r.max()) for r in rows if len(r)), default=0)) + 2
        self.possible = self.radix**n < 2**62
        at, gram = self._grams(rows)
        self.vocabulary, place = np.unique(gram, return_inverse=True)
        self.size = len(self.vocabulary)
        if self.fits(len(rows)):
            self.matrix = self._counts(at, place, len(rows))
            self.norm2 = (self.matrix * self.matrix).sum(1)

    @classmethod
    def of_counts(cls, rows: int, at: np.ndarray, word: np.ndarray, count: np.ndarray, matrix: bool = True) -> GramSpace:
        """Single words, whose counts are known; without ``matrix`` only the vocabulary is made."""
        self = cls.__new__(cls)
        self.n, self.possible, self.radix = 1, True, int(word.max(initial=0)) + 2
        self.vocabulary, place = np.unique(word, return_inverse=True)
        self.size = len(self.vocabulary)
        if matrix and self.fits(rows):
            self.matrix = np.zeros((rows, self.size))
            self.matrix[at, place] = count
            self.norm2 = (self.matrix * self.matrix).sum(1)
        return self

    def fits(self, rows: int) -> bool:
        return self.possible and rows * max(1, self.size) <= 4 * _CELLS

    def _grams(self, rows: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        at, token = _flat(rows)
        token = np.minimum(token, self.radix - 1)  # a token that no query has
        if self.n == 1 or len(token) < self.n:
            return (at, token) if self.n == 1 else (at[:0], token[:0])
        whole = at[: len(at) - self.n + 1] == at[self.n - 1 :]
        gram = np.zeros(len(whole), np.int64)
        for k in range(self.n):
            gram = gram * self.radix + token[k : k + len(whole)]
        return at[: len(whole)][whole], gram[whole]

    def _counts(self, at: np.ndarray, place: np.ndarray, rows: int) -> np.ndarray:
        return np.bincount(at * self.size + place, minlength=rows * self.size).reshape(rows, self.size).astype(float)

    def compare(self, rows: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        """(counts over the vocabulary, squared lengths over all grams) of sequences."""
        # squared lengths need exact grams, also of tokens that no query has
        at, token = _flat(rows)
        if self.n == 1:
            full_at, full = at, token
        else:
            radix = int(token.max(initial=0)) + 1
            whole = at[: max(0, len(at) - self.n + 1)] == at[self.n - 1 :]
            full = np.zeros(len(whole), np.int64)
            for k in range(self.n):
                full = full * radix + token[k : k + len(whole)]
            full_at, full = at[: len(whole)][whole], full[whole]
        order = np.lexsort((full, full_at))
        a, g = full_at[order], full[order]
        first = np.flatnonzero(np.concatenate(([True], (a[1:] != a[:-1]) | (g[1:] != g[:-1]))) if len(a) else np.zeros(0, bool))
        runs = np.diff(np.append(first, len(a)))
        norm2 = np.bincount(a[first], weights=(runs * runs).astype(float), minlength=len(rows)) if len(a) else np.zeros(len(rows))
        at, gram = self._grams(rows)
        place = np.searchsorted(self.vocabulary, gram)
        known = place < self.size
        known[known] = self.vocabulary[place[known]] == gram[known]
        return self._counts(at[known], place[known], len(rows)) if self.size else np.zeros((len(rows), 0)), norm2

    def cosine(self, counts: np.ndarray, norm2: np.ndarray) -> np.ndarray:
        """Rows: queries, columns: sequences.  Integers until the last division; 0 where either has no gram."""
        dot = self.matrix @ counts.T
        with np.errstate(divide="ignore", invalid="ignore"):
            return np.where(dot > 0, dot / np.sqrt(np.outer(self.norm2, norm2)), 0.0)


class Best:
    """The best k of each query so far: by rounded score, then by id."""

    def __init__(self, queries: int, k: int) -> None:
        self.k = k
        self.query, self.cand = np.zeros(0, np.int64), np.zeros(0, np.int64)
        self.rounded, self.value = np.zeros(0), np.zeros(0)
        self.extra = np.zeros(0, np.int64)
        self.kth = np.full(queries, -np.inf)

    def add(self, query: np.ndarray, cand: np.ndarray, value: np.ndarray, extra: np.ndarray | None = None) -> None:
        """``extra``: a number to keep with each."""
        extra = np.zeros(len(query), np.int64) if extra is None else extra
        rounded = np.round(value, 9)
        near = rounded >= self.kth[query]
        q, c, r, v, x = (np.concatenate((old, new[near])) for old, new in ((self.query, query), (self.cand, cand), (self.rounded, rounded), (self.value, value), (self.extra, extra)))
        order = np.lexsort((c, -r, q))
        q = q[order]
        begin = np.flatnonzero(np.concatenate(([True], q[1:] != q[:-1])) if len(q) else np.zeros(0, bool))
        sizes = np.diff(np.append(begin, len(q)))
        rank = np.arange(len(q)) - np.repeat(begin, sizes)
        keep = order[rank < self.k]
        self.query, self.cand, self.rounded, self.value, self.extra = q[rank < self.k], c[keep], r[keep], v[keep], x[keep]
        full = rank == self.k - 1
        self.kth[q[full]] = r[order[full]]

    def table(self, ids: np.ndarray, kinds: tuple[str, str, str]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(ids[self.query], pa.int64()), pa.array(self.cand, pa.int64()), pa.array(self.value)], names=list(kinds))


def _rows(batch: pa.RecordBatch, timed: bool) -> tuple[np.ndarray, list[np.ndarray], list[np.ndarray] | None]:
    ids = batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64)
    tokens = [np.zeros(0, np.int64) if t is None else np.asarray(t, np.int64) for t in batch.column(1).to_numpy(zero_copy_only=False)]
    if not timed:
        return ids, tokens, None
    return ids, tokens, [np.arange(1.0, len(w) + 1) if t is None else t for t, w in zip(batch.column(2).to_numpy(zero_copy_only=False), tokens, strict=True)]


def _slices(n: int, width: int) -> Iterator[slice]:
    step = max(1, _CELLS // max(1, width))
    return (slice(a, min(n, a + step)) for a in range(0, n, step))


def _spread(base: DataFrame, heavy: bool) -> DataFrame:
    """Alignment costs much for a few bytes, so there the base is dealt out by number of rows."""
    if not heavy:
        return base
    spark = base.sparkSession
    return base.repartition(max(2 * spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions"))))


def top_cosine(block: QueryBlock | HistogramBlock, base: DataFrame, k: int, exclude_self: bool = True) -> DataFrame | None:
    """(query_id, cand_id, cosine): of every partition of the base the k most similar of each query, also those of cosine 0.
    None if the queries have too many words for one matrix."""
    if isinstance(block, QueryBlock):
        at, word = _flat(block.tokens)
        block = HistogramBlock(block.ids, *_counted(at, word))
    if not block.space().fits(len(block.ids)):
        return None
    sent = base.sparkSession.sparkContext.broadcast((block.ids, block.at, block.word, block.count))  # arrays only: executors have no copy of this package

    def run(batches):
        ids, grams = sent.value[0], HistogramBlock(*sent.value).space()
        best = Best(len(ids), k)
        for batch in batches:
            cands, tokens, _ = _rows(batch, False)
            for part in _slices(len(cands), max(len(ids), grams.size)):
                cos = grams.cosine(*grams.compare(tokens[part]))
                q, i = np.nonzero(cos >= best.kth[:, None] - 2e-9)  # rounding follows for these only
                if exclude_self:
                    other = ids[q] != cands[part][i]
                    q, i = q[other], i[other]
                best.add(q, cands[part][i], cos[q, i])
        yield best.table(ids, ("query_id", "cand_id", "cosine"))

    rows = base.select("seq_id", "tokens")
    if len(block.ids) > MOST_QUERIES:  # each partition keeps k of every query: no more of them than keep the cores busy
        rows = rows.repartition(2 * base.sparkSession.sparkContext.defaultParallelism)
    return rows.mapInArrow(run, "query_id bigint, cand_id bigint, cosine double")


def every_cosine(block: HistogramBlock, base: DataFrame, exclude_self: bool = True) -> DataFrame | None:
    """(query_id, cand_id, dot, cosine) of all pairs that share a word: matrix products in one pass, no shuffle of pairs.

    The queries are as many as :func:`histogram_block` takes: they meet each slice of the base in blocks of one matrix each.
    None if they have too many different words for that."""
    if len(np.unique(block.word)) > _CELLS:
        return None
    small = [x.astype(np.int32) if x.max(initial=0) < 2**31 and x.min(initial=0) >= -(2**31) else x for x in (block.at, block.word, block.count)]
    sent = base.sparkSession.sparkContext.broadcast((block.ids, *small))  # arrays only: executors have no copy of this package

    def run(batches):
        ids, at, word, count = sent.value
        grams = GramSpace.of_counts(len(ids), at, word, count, matrix=False)
        place, step = np.searchsorted(grams.vocabulary, word), max(1, _CELLS // max(1, grams.size))
        begin = np.searchsorted(at, np.arange(0, len(ids) + step, step))
        for batch in batches:
            cands, tokens, _ = _rows(batch, False)
            for part in _slices(len(cands), 2 * grams.size):
                counts, norm2 = grams.compare(tokens[part])
                for k, (x, y) in enumerate(zip(begin[:-1], begin[1:], strict=True)):
                    own = ids[k * step : (k + 1) * step]
                    matrix = np.zeros((len(own), grams.size))
                    matrix[at[x:y] - k * step, place[x:y]] = count[x:y]
                    own2 = (matrix * matrix).sum(1)
                    for some in _slices(len(counts), 4 * len(own)):
                        dot = matrix @ counts[some].T
                        hit = dot > 0
                        if exclude_self:
                            hit &= own[:, None] != cands[part][some]
                        q, i = np.nonzero(hit)
                        found = dot[q, i]
                        value = found / np.sqrt(own2[q] * norm2[some][i])
                        yield pa.RecordBatch.from_arrays([pa.array(own[q], pa.int64()), pa.array(cands[part][some][i], pa.int64()), pa.array(found.astype(np.int64)), pa.array(value)], names=["query_id", "cand_id", "dot", "cosine"])

    return _spread(base.select("seq_id", "tokens"), True).mapInArrow(run, "query_id bigint, cand_id bigint, dot bigint, cosine double")


def top_classes(block: HistogramBlock, base: DataFrame, k: int, by: str = "max", exclude_self: bool = True) -> DataFrame | None:
    """(query_id, class_id, score): of every partition the k classes whose best or mean cosine with each query is largest, over the
    sequences that share a word with it.  A class is in one partition, so its sum is whole; no pairs are sent.
    None if the queries have too many words for one matrix."""
    if not block.space().fits(len(block.ids)):
        return None
    sent = base.sparkSession.sparkContext.broadcast((block.ids, block.at, block.word, block.count))  # arrays only: executors have no copy of this package

    def run(batches):
        ids, grams = sent.value[0], HistogramBlock(*sent.value).space()
        best, names = Best(len(ids), k), []

        def add(done):
            if done:
                names.extend(d[0] for d in done)
                total, n = np.stack([d[1] for d in done], 1), np.stack([d[2] for d in done], 1)
                value = total / np.maximum(1, n) if by == "mean" else total
                q, c = np.nonzero((n > 0) & (value >= best.kth[:, None] - 2e-9))  # rounding follows for these only
                best.add(q, c + len(names) - len(done), value[q, c])

        held, done = None, []
        for batch in batches:
            cands, tokens, _ = _rows(batch, False)
            classes = batch.column(2).to_pylist()
            for part in _slices(len(cands), 2 * max(len(ids), grams.size)):
                cos = grams.cosine(*grams.compare(tokens[part]))
                hit = cos > 0
                if exclude_self:
                    hit &= ids[:, None] != cands[part]
                own = classes[part]
                begin = [0, *(i for i in range(1, len(own)) if own[i] != own[i - 1])]
                join = np.add if by == "mean" else np.maximum
                totals, sizes = join.reduceat(np.where(hit, cos, 0.0), begin, axis=1), np.add.reduceat(hit, begin, axis=1, dtype=np.int64)
                for j, at in enumerate(begin):
                    if held is not None and held[0] == own[at]:  # a class that the slice before began
                        held = (held[0], join(held[1], totals[:, j]), held[2] + sizes[:, j])
                        continue
                    if held is not None:
                        done.append(held)
                    held = (own[at], totals[:, j], sizes[:, j])
                if len(done) >= 32:
                    add(done)
                    done = []
        add(done + ([held] if held is not None else []))
        yield pa.RecordBatch.from_arrays([pa.array(ids[best.query], pa.int64()), pa.array([names[c] for c in best.cand], pa.string()), pa.array(best.value)], names=["query_id", "class_id", "score"])

    # in order of the classes, so ties within a partition go by name
    rows = base.select("seq_id", "tokens", "class_id").repartition("class_id").sortWithinPartitions("class_id")
    return rows.mapInArrow(run, "query_id bigint, class_id string, score double")


def top_vectors(queries: DataFrame, base: DataFrame, k: int) -> DataFrame | None:
    """(query_id, cand_id, score): of every partition the k largest cosines of each query; None if the queries are too many."""
    size = queries.agg(F.count("*").alias("n"), F.sum(F.size("v")).alias("t")).first()
    if size["n"] > MOST_QUERIES or (size["t"] or 0) > MOST_TOKENS or size["n"] * k > MOST_KEPT:
        return None
    rows = sorted((r["seq_id"], [float(x) for x in r["v"]]) for r in queries.where("v is not null").collect())
    sent = base.sparkSession.sparkContext.broadcast(rows)

    def unit(x: np.ndarray) -> np.ndarray:
        return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-300)

    def run(batches):
        ids = np.array([r[0] for r in sent.value], np.int64)
        sizes = np.array([len(r[1]) for r in sent.value], np.int64)
        mine = {int(n): (np.flatnonzero(sizes == n), unit(np.array([r[1] for r in sent.value if len(r[1]) == n]))) for n in np.unique(sizes)}
        best = Best(len(ids), k)
        for batch in batches:
            cands, vectors = batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64), batch.column(1).to_numpy(zero_copy_only=False)
            lengths = np.array([-1 if v is None else len(v) for v in vectors], np.int64)
            for n in set(lengths.tolist()) & mine.keys():
                which, q = mine[n]
                at = np.flatnonzero(lengths == n)
                for part in _slices(len(at), len(which)):
                    cos = q @ unit(np.stack(vectors[at[part]]).astype(float)).T
                    a, i = np.nonzero((np.round(cos, 9) >= best.kth[which][:, None]) & (ids[which][:, None] != cands[at[part]]))
                    best.add(which[a], cands[at[part]][i], cos[a, i])
        yield best.table(ids, ("query_id", "cand_id", "score"))

    return base.mapInArrow(run, "query_id bigint, cand_id bigint, score double")


class Scorer:
    """Scores a block of queries against sequences and keeps the best; pairs that can't reach them are not aligned.

    Histogram and n-gram terms of all pairs are matrix products.  The alignment terms are bounded by lengths, shared tokens and
    gap sums; the most promising pairs are aligned first, and then, term by term, those whose bound still reaches the k-th
    score.  ``prune`` off: every pair gets every term.
    """

    def __init__(self, block: QueryBlock, k: int, weights: dict[str, float], params: MetricParams, exclude_self: bool, prune: bool, reached: np.ndarray | None = None) -> None:
        self.block, self.weights, self.params = block, weights, params
        self.exclude_self, self.prune, self.k = exclude_self, prune, k
        self.words = GramSpace(block.tokens, 1)
        self.grams = GramSpace(block.tokens, params.ngram) if "ngram" in weights and params.ngram_kind == "cosine" else None
        self.length = np.fromiter(map(len, block.tokens), float, len(block.tokens))
        self.gap = np.array([np.abs(t - params.gap).sum() for t in block.tokens])
        self.far = np.array([(t != params.gap).sum() for t in block.tokens], float)
        # by what a pair costs; the first two also bound the others
        self.terms = [t for t in ("lcss", "edr", "erp", "twed", "dtw") if t in weights]
        self.best = Best(len(block.ids), k)
        if reached is not None:
            self.best.kth = np.round(reached, 9) - 2e-9
        self.pairs = self.aligned = self.cells = self.all_cells = 0

    def fits(self) -> bool:
        n = len(self.block.ids)
        return self.words.fits(n) and (self.grams is None or self.grams.fits(n))

    def _align(self, term: str, q: np.ndarray, i: np.ndarray, rows, times, worst: np.ndarray | None) -> np.ndarray:
        """Similarities of the pairs by one measure; below ``worst`` a pair may be given up as 0."""
        timed, m, n = times is not None, self.length[q], np.fromiter(map(len, rows), float, len(rows))[i]
        self.cells += int((m * n).sum())
        if (term != "twed" or not timed) and (v := wavefront.quick_similarity_at(term, self.block.tokens, q, rows, i, self.params)) is not None:
            return v
        a, b = [self.block.tokens[x] for x in q], [rows[x] for x in i]
        ta, tb = ([self.block.times[x] for x in q], [times[x] for x in i]) if timed else (None, None)
        mean, longest = np.maximum(1, (m + n) / 2), np.maximum(1, np.maximum(m, n))
        if worst is None or term in ("lcss", "dtw"):
            return batch_similarities([term], a, b, ta, tb, self.params)[term]
        with np.errstate(divide="ignore"):
            least = np.clip(worst, 0.0, 1.0) - 1e-9
            most = {"edr": (1 - least) * longest, "erp": -np.log(np.maximum(least, 1e-300)) * mean, "twed": -np.log(np.maximum(least, 1e-300)) * 2 * mean}[term]
        most = np.where(worst <= 0, np.inf, most)

        def compute(x, y, u, v, stop):
            stop = np.array(stop)
            if term == "twed":
                return {term: wavefront.twed(x, y, u, v, self.params, stop)}
            return {term: getattr(wavefront, term)(x, y, self.params, stop)}

        d = _grouped(compute, a, b, ta, tb, most, term)
        out = 1 - d / longest if term == "edr" else np.exp(-d / (mean if term == "erp" else 2 * mean))
        return np.where(np.isfinite(d), out, 0.0)

    def feed(self, ids: np.ndarray, rows: list[np.ndarray], times) -> None:
        for part in _slices(len(ids), max(len(self.block.ids), self.words.size, self.grams.size if self.grams else 0)):
            self._feed(ids[part], rows[part], times[part] if times is not None else None)

    def _feed(self, ids: np.ndarray, rows: list[np.ndarray], times) -> None:
        w, p = self.weights, self.params
        counts, norm2 = self.words.compare(rows)
        n = np.fromiter(map(len, rows), float, len(rows))
        open_ = self.block.ids[:, None] != ids if self.exclude_self else np.ones((len(self.block.ids), len(ids)), bool)
        q, i = np.nonzero(open_)
        self.pairs += len(q)
        self.all_cells += int((self.length[q] * n[i]).sum()) * len(self.terms)
        value: dict[str, np.ndarray] = {}
        if "hist" in w:
            value["hist"] = self.words.cosine(counts, norm2)[q, i]
        if "ngram" in w:
            if self.grams is not None:
                value["ngram"] = self.grams.cosine(*self.grams.compare(rows))[q, i]
            else:
                a, b = [self.block.tokens[x] for x in q], [rows[x] for x in i]
                value["ngram"] = wavefront.similarities(["ngram"], a, b, p=p)["ngram"]
        bound = self._bounds(q, i, n, rows, counts) if self.prune else {}
        if not self.prune:
            for t in self.terms:
                value[t] = self._align(t, q, i, rows, times, None)
            self.aligned += len(q)
            self.best.add(q, ids[i], self._score(value, {}))
            return
        far = np.array([(t != p.gap).sum() for t in rows], float)
        upper = self._score(value, bound)
        order = np.lexsort((-upper, q))
        rank = np.arange(len(q)) - np.searchsorted(q[order], q[order])
        first = np.zeros(len(q), bool)
        first[order[rank < 2 * self.k]] = True
        first &= upper >= self.best.kth[q] - 2e-9
        for chosen in (first, ~first):
            at = np.flatnonzero(chosen & (upper >= self.best.kth[q] - 2e-9))
            self.aligned += len(at)
            known = {t: v[at] for t, v in value.items()}
            left = {t: v[at] for t, v in bound.items()}
            for t in self.terms:
                if not len(at):
                    break
                low = self.best.kth[q[at]]
                rest = self._score(known, left) - w[t] * left[t]
                worst = np.where(np.isfinite(low), (low - 2e-9 - rest) / w[t], -1.0)
                known[t] = self._align(t, q[at], i[at], rows, times, worst)
                del left[t]
                if t == "lcss":
                    self._tighten(known[t], q[at], n[i[at]], far[i[at]], left)
                elif t == "edr":
                    self._tighten_twed(known[t], q[at], n[i[at]], left, times is not None)
                still = self._score(known, left) >= self.best.kth[q[at]] - 2e-9
                at = at[still]
                known, left = {k: v[still] for k, v in known.items()}, {k: v[still] for k, v in left.items()}
            if len(at):
                self.best.add(q[at], ids[i[at]], self._score(known, left))

    def _tighten(self, lcss: np.ndarray, q: np.ndarray, n: np.ndarray, far: np.ndarray, left: dict[str, np.ndarray]) -> None:
        """No alignment has more matches than the longest common subsequence: EDR pays one for every other item of the longer
        sequence; TWED pays a mismatch for every other pair and at least ``lam`` for every single move; ERP pays ``beta`` or half
        a mismatch of whole numbers for every other item that isn't the gap's value (of which ``far`` are in the base's)."""
        p, m = self.params, self.length[q]
        if p.lcss_eps or p.lcss_delta is not None:
            return
        full = (m > 0) & (n > 0)
        matches = lcss * (m + n) / 2
        if "edr" in left and not p.edr_eps:
            left["edr"] = np.where(full, np.minimum(left["edr"], matches / np.maximum(1, np.maximum(m, n))), left["edr"])
        if "erp" in left and p.gap == int(p.gap) and p.beta >= 0:
            least = min(p.beta, 0.5) * np.maximum(0, self.far[q] + far - 2 * matches)
            left["erp"] = np.where(full, np.minimum(left["erp"], np.exp(-least / np.maximum(1, (m + n) / 2))), left["erp"])
        if "twed" in left and p.twed_cost == "discrete" and p.lam >= 0.5:
            least = np.maximum(0, np.minimum(m, n) - matches) + p.lam * np.abs(m - n)
            left["twed"] = np.where(full, np.minimum(left["twed"], np.exp(-least / np.maximum(1, m + n))), left["twed"])

    def _tighten_twed(self, edr: np.ndarray, q: np.ndarray, n: np.ndarray, left: dict[str, np.ndarray], timed: bool) -> None:
        """Every step of TWED's path costs what it costs EDR at least, besides that a single move costs ``lam``; and by positions a
        path that ends d places off the diagonal was 1, 2, ... d places off it before."""
        p, m = self.params, self.length[q]
        if "twed" not in left or p.edr_eps or p.twed_cost != "discrete" or min(p.lam, p.nu) < 0:
            return
        apart = np.abs(m - n)
        least = min(1.0, p.lam) * (1 - edr) * np.maximum(m, n) + (p.nu * apart * (apart + 1) / 2 if p.twed == "printed" and not timed else 0.0)
        left["twed"] = np.where((m > 0) & (n > 0), np.minimum(left["twed"], np.exp(-least / np.maximum(1, m + n))), left["twed"])

    def _score(self, value: dict[str, np.ndarray], bound: dict[str, np.ndarray]) -> np.ndarray:
        total: np.ndarray | float = 0.0
        for t, w in self.weights.items():  # in the order of the weights, as the column form adds them
            total = total + w * (value[t] if t in value else bound[t])
        return np.asarray(total)

    def _bounds(self, q: np.ndarray, i: np.ndarray, n: np.ndarray, rows: list[np.ndarray], counts: np.ndarray) -> dict[str, np.ndarray]:
        """Upper bounds of the alignment terms; see ``retrieve.score_bound``."""
        p, m, k = self.params, self.length[q], n[i]
        mean, longest = np.maximum(1, (m + k) / 2), np.maximum(1, np.maximum(m, k))
        common = np.empty(len(q))
        ends = np.searchsorted(q, np.arange(len(self.block.ids) + 1))  # the pairs are in order of the query
        for a, (x, y) in enumerate(zip(ends[:-1], ends[1:], strict=True)):
            common[x:y] = np.minimum(self.words.matrix[a], counts).sum(1)[i[x:y]]
        gap = np.array([np.abs(t - p.gap).sum() for t in rows])
        same = {"lcss": p.lcss_eps == 0, "edr": p.edr_eps == 0}
        out = {
            "lcss": np.minimum(1.0, (common if same["lcss"] else np.minimum(m, k)) / mean),
            "edr": (common if same["edr"] else np.minimum(m, k)) / longest,
            "erp": np.exp(-p.beta * np.abs(self.gap[q] - gap[i]) / mean) if p.beta <= 1 else np.ones(len(q)),
            "twed": np.exp(-p.lam * np.abs(m - k) / (2 * mean)),
            "dtw": np.ones(len(q)),
        }
        empty = (m == 0) | (k == 0)
        return {t: np.where(empty, 1.0, out[t]) for t in self.terms}


def _grouped(compute: Callable, a, b, ta, tb, most: np.ndarray, name: str) -> np.ndarray:
    """``batch_values`` with a bound for each pair."""
    at = list(range(len(a)))

    def run(x, y, u, v):
        k = [int(t[-1]) for t in x]
        strip = lambda rows: None if rows is None else [r[:-1] for r in rows]
        return compute(strip(x), y, strip(u), v, most[k])

    tagged = [np.append(r, j) for r, j in zip(a, at, strict=True)]
    times = None if ta is None else [np.append(r, 0.0) for r in ta]
    return batch_values(run, tagged, b, times, tb, [name])[name]


def copies(sequences: DataFrame, timed: bool = False, keep: int = 1_000, first: bool = False) -> DataFrame:
    """Equal sequences as one row: (seq_id, the smallest; tokens; times; len; ids, all in order).  More than ``keep`` copies
    are several rows, so that no task has all of a large group; with ``first`` the others are left out, for answers that they can't be among."""
    by = ["tokens", "times"] if timed else ["tokens"]
    rows = sequences.groupBy(*by).agg(F.array_sort(F.collect_list("seq_id")).alias("every"))
    starts = F.array(F.lit(1)) if first else F.sequence(F.lit(1), F.size("every"), F.lit(keep))
    parts = rows.select(*by, F.explode(F.transform(starts, lambda i: F.slice("every", i, F.lit(keep)))).alias("ids"))
    times = F.col("times") if timed else F.lit(None).cast("array<double>")
    return parts.select(F.col("ids")[0].alias("seq_id"), "tokens", times.alias("times"), F.size("tokens").alias("len"), "ids")


#: Pairs that :func:`every_pair` makes at once.
_PAIRS = 160_000


def picked(rows: list, x: np.ndarray, cols: list, y: np.ndarray, rows_t: list | None, cols_t: list | None) -> tuple:
    """The pairs (rows[x], cols[y]) as lists, and their times."""
    times = ([rows_t[k] for k in x], [cols_t[k] for k in y]) if rows_t is not None else (None, None)
    return [rows[k] for k in x], [cols[k] for k in y], *times


def every_pair(asked: DataFrame, base: DataFrame, columns: list[str], compute: Callable, grams: dict[str, int], timed: bool = False) -> DataFrame | None:
    """(query_id, ids, a number for each of ``columns``) of all pairs, in one pass over the base, without a shuffle of pairs.

    Both sides are rows of :func:`copies`, and so is a pair: see :func:`each_copy`.  ``compute(names, rows, x, cols, y, times of
    rows, of cols)`` gives the columns of the pairs (rows[x], cols[y]), of any lengths, that ``grams`` doesn't name; those are cosines of n-gram counts, of that n, by matrix products if they fit.
    None if the queries are more than may be broadcast."""
    if (asked.agg(F.sum(F.size("ids")).alias("n")).first()["n"] or 0) > MOST_QUERIES:
        return None
    block = query_block(asked, 1, timed)
    if block is None:
        return None
    sent = base.sparkSession.sparkContext.broadcast((block.ids, block.tokens, block.times))

    def run(batches):
        block = QueryBlock(*sent.value)
        n = len(block.ids)
        spaces = {c: GramSpace(block.tokens, k) for c, k in grams.items()}
        spaces = {c: s for c, s in spaces.items() if s.fits(n)}
        rest = [c for c in columns if c not in spaces]
        for batch in batches if n else ():
            _, tokens, times = _rows(batch, timed)
            ids = batch.column(batch.num_columns - 1)
            for at in range(0, len(tokens), step := max(1, _PAIRS // n)):
                b, tb = tokens[at : at + step], times[at : at + step] if timed else None
                value = {c: s.cosine(*s.compare(b)).ravel() for c, s in spaces.items()}
                q, i = np.repeat(np.arange(n), len(b)), np.tile(np.arange(len(b)), n)
                if rest:
                    value |= compute(rest, block.tokens, q, b, i, block.times, tb)
                yield pa.RecordBatch.from_arrays([pa.array(block.ids[q]), ids.take(pa.array(at + i)), *(pa.array(value[c]) for c in columns)], names=["query_id", "ids", *columns])

    # in order of length, so that pairs of equal lengths meet
    rows = _spread(base.select("seq_id", "tokens", *(["times"] if timed else []), "ids"), True).sortWithinPartitions(F.size("tokens"), "seq_id")
    return rows.mapInArrow(run, ", ".join(["query_id bigint, ids array<bigint>", *(f"`{c}` double" for c in columns)]))


#: Windows that are compared with a sequence at once.
_WINDOWS = 32_768


def _cut(tokens: list[np.ndarray], window: int, hop: int) -> tuple[np.ndarray, np.ndarray]:
    """(row, start) of the windows of every row, in order: those of ``retrieve.segments``."""
    starts = [np.arange(0, max(0, len(t) - window) + 1, hop) for t in tokens]
    starts = [x if x[-1] == max(0, len(t) - window) else np.append(x, len(t) - window) for x, t in zip(starts, tokens, strict=True)]
    return np.repeat(np.arange(len(tokens)), list(map(len, starts))), np.concatenate(starts)


def best_segments(asked: DataFrame, base: DataFrame, window: int, hop: int, k: int, weights: dict[str, float], params: MetricParams, timed: bool = False) -> DataFrame | None:
    """(query_id, cand_id, start, score): of every partition the k sequences of the base with the best segments, the first of the
    equal ones, for each query.  Every segment is scored; sequences are cut where they are, so neither segments nor pairs are sent.

    Both sides are rows of :func:`copies`.  Common subsequences alone, of windows of 64 at most, go by :class:`wavefront.Windows`;
    others by all similarities of the pairs.  None if the queries are more than may be broadcast."""
    block = query_block(asked, k, timed)
    if block is None:
        return None
    sent = base.sparkSession.sparkContext.broadcast((block.ids, block.tokens, block.times))
    kinds = np.unique(_flat(block.tokens)[1])
    bits = list(weights) == ["lcss"] and not params.lcss_eps and params.lcss_delta is None and window <= 64 and len(kinds) * _WINDOWS <= 64 * _CELLS

    def by_bits(block, codes, tokens, row, start, size):
        """For each query the common items of all windows; those of one sequence are of one size, so they order its scores."""
        rows = np.zeros((len(row), window), np.int64)
        flat_at, flat = np.arange(window) < size[:, None], [tokens[r][s : s + window] for r, s in zip(row, start, strict=True)]
        rows[flat_at] = np.concatenate([*flat, np.zeros(0, np.int64)])
        windows = wavefront.Windows(rows, size, kinds)
        return map(windows.common, codes)

    def by_pairs(block, codes, tokens, row, start, size, times):
        parts = [tokens[r][s : s + window] for r, s in zip(row, start, strict=True)]
        clock = [times[r][s : s + window] for r, s in zip(row, start, strict=True)] if timed else None
        for q, own in enumerate(block.tokens):
            found = batch_similarities(list(weights), [own] * len(parts), parts, [block.times[q]] * len(parts) if timed else None, clock, params)
            yield sum(w * found[m] for m, w in weights.items())

    def run(batches):
        block = QueryBlock(*sent.value)
        codes = [np.searchsorted(kinds, t).tolist() for t in block.tokens] if bits else None
        best, step = Best(len(block.ids), k), 16  # few at first, which leave out most of the others
        for batch in batches if len(block.ids) else ():
            ids, tokens, times = _rows(batch, timed)
            at = 0
            while at < len(ids):
                some = slice(at, at + step)
                row, start = _cut(tokens[some], window, hop)
                n = max(1, int(row[_WINDOWS])) if len(row) > _WINDOWS else int(row[-1]) + 1  # whole sequences
                row, start = row[row < n], start[row < n]
                size = np.minimum(window, np.fromiter(map(len, tokens[at : at + n]), np.int64, n))[row]
                begin = np.searchsorted(row, np.arange(n))
                scores = by_bits(block, codes, tokens[at : at + n], row, start, size) if bits else by_pairs(block, codes, tokens[at : at + n], row, start, size, times[at : at + n] if timed else None)
                found = []
                for q, score in enumerate(scores):
                    score = score if bits else np.round(score, 9)
                    top = np.maximum.reduceat(score, begin)
                    if bits:
                        mean = (len(codes[q]) + size[begin]) / 2
                        top = np.round(weights["lcss"] * np.where(mean > 0, top / np.maximum(mean, 0.5), 1.0), 9)
                    near = np.flatnonzero(top > best.kth[q])  # ids are in order, so later ones of the k-th score are behind it
                    if len(near) > k:
                        near = near[np.argsort(-top[near], kind="stable")[:k]]
                    for r in near:
                        first = begin[r] + int(score[begin[r] : begin[r + 1] if r + 1 < n else None].argmax())
                        found.append((q, ids[at + r], top[r], start[first]))
                if found:
                    q, c, v, x = (np.array(col) for col in zip(*found, strict=True))
                    best.add(q, c, v, x)
                at, step = at + n, min(2 * step, 65_536)
        yield pa.RecordBatch.from_arrays([pa.array(block.ids[best.query], pa.int64()), pa.array(best.cand, pa.int64()), pa.array(best.extra, pa.int32()), pa.array(best.value)], names=["query_id", "cand_id", "start", "score"])

    tasks = 4 * base.sparkSession.sparkContext.defaultParallelism  # a step is over many windows, so no more tasks than keep the cores busy
    rows = base.select("seq_id", "tokens", *(["times"] if timed else [])).repartition(tasks).sortWithinPartitions("seq_id")
    return rows.mapInArrow(run, "query_id bigint, cand_id bigint, start int, score double")


def each_copy(pairs: DataFrame, asked: DataFrame, exclude_self: bool = True) -> DataFrame:
    """Pairs of rows of copies to (query_id, cand_id, ...) of every pair; the queries are at most ``MOST_QUERIES``."""
    rest = [c for c in pairs.columns if c not in ("query_id", "ids")]
    members = asked.select(F.col("seq_id").alias("query_id"), F.col("ids").alias("members"))
    rows = pairs.join(F.broadcast(members), "query_id").select(F.explode("members").alias("query_id"), "ids", *rest)
    rows = rows.select("query_id", F.explode("ids").alias("cand_id"), *rest)
    return rows.where("query_id <> cand_id") if exclude_self else rows


def scan(block: QueryBlock, base: DataFrame, k: int, weights: dict[str, float], params: MetricParams, timed: bool, exclude_self: bool, prune: bool, counters: bool = False, reached: np.ndarray | None = None) -> DataFrame | None:
    """(query_id, cand_id, score): the best k of each query in every partition of the base, by the weighted similarities; with
    ``counters`` instead (pairs, aligned, cells, all_cells) of each partition.  ``reached``: for each query a score that k
    candidates are known to have.  None if the queries have too many n-grams."""
    if not Scorer(block, k, weights, params, exclude_self, prune).fits():
        return None
    sent = base.sparkSession.sparkContext.broadcast((block.ids, block.tokens, block.times))

    def run(batches):
        scorer = Scorer(QueryBlock(*sent.value), k, weights, params, exclude_self, prune, reached)
        for batch in batches:
            scorer.feed(*_rows(batch, timed))
        if counters:
            yield pa.RecordBatch.from_pydict({c: pa.array([getattr(scorer, c)], pa.int64()) for c in ("pairs", "aligned", "cells", "all_cells")})
        else:
            yield scorer.best.table(scorer.block.ids, ("query_id", "cand_id", "score"))

    rows = _spread(base.select("seq_id", "tokens", *(["times"] if timed else [])), True)
    kind = "pairs bigint, aligned bigint, cells bigint, all_cells bigint" if counters else "query_id bigint, cand_id bigint, score double"
    return rows.mapInArrow(run, kind)
