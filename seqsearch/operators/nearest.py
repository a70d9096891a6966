"""The most similar histograms of many queries, without a shuffle: tasks take queries, and each has the histograms of the whole base.

Histograms over few words are far smaller than sequences, so both sides may be broadcast up to a bound.  Rows of the base are
cut into groups of near vectors; a group is looked at only if, by the distance from its centre and its radius, one of its
vectors may still be among the best k.  So the answer is that of comparing all pairs.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .histogram import runs
from .onepass import _CELLS, MOST_WORDS, Best

#: Rows of a group.
GROUP = 128
#: Most ids of sequences that are broadcast.
MOST_IDS = 4_000_000
#: More than any rounding error of a bound.
_SLACK = 1e-7


def dense(rows: int, at: np.ndarray, word: np.ndarray, count: np.ndarray, words: np.ndarray) -> np.ndarray:
    """Counts as a matrix over ``words``, which are sorted and hold all words."""
    out = np.zeros((rows, max(1, len(words))))
    out[at, np.searchsorted(words, word)] = count
    return out


def _unit(counts: np.ndarray) -> np.ndarray:
    return counts / np.sqrt(np.maximum(1, (counts * counts).sum(1, keepdims=True)))


def groups(counts: np.ndarray, size: int = GROUP) -> tuple[np.ndarray, np.ndarray]:
    """(order of the rows, where each group begins and the last ends): halves by the widest direction, again and again."""
    unit = _unit(counts)
    todo, done = [np.arange(len(unit))], []
    while todo:
        rows = todo.pop()
        if len(rows) <= size:
            done.append(rows)
            continue
        part = unit[rows]
        axis = part[:, int(np.ptp(part, axis=0).argmax())]
        order, half = np.argpartition(axis, len(rows) // 2), len(rows) // 2
        todo += [rows[order[half:]], rows[order[:half]]]
    return np.concatenate(done), np.cumsum([0, *map(len, done)])


class Grouped:
    """The base's histograms in groups, with the centre and radius of each."""

    def __init__(self, ids: np.ndarray, counts: np.ndarray, order: np.ndarray, begin: np.ndarray) -> None:
        self.ids, self.counts, self.begin = ids[order], counts[order], begin
        self.norm2 = (self.counts * self.counts).sum(1)
        unit, sizes = _unit(self.counts), np.diff(begin)
        self.centre = np.add.reduceat(unit, begin[:-1]) / sizes[:, None]
        away = np.sqrt(((unit - np.repeat(self.centre, sizes, axis=0)) ** 2).sum(1))
        self.radius = np.maximum.reduceat(away, begin[:-1])

    def cosine(self, counts: np.ndarray, norm2: np.ndarray, rows: np.ndarray | slice) -> np.ndarray:
        """Integers until the last division; 0 where either is empty."""
        dot = counts @ self.counts[rows].T
        return dot / np.sqrt(np.maximum(1, np.outer(norm2, self.norm2[rows])))

    def most(self, counts: np.ndarray) -> np.ndarray:
        """For each query and group the cosine that no vector of the group exceeds: 1 - d * d / 2 at distance d of unit vectors."""
        unit = _unit(counts)
        square = (unit * unit).sum(1)[:, None] + (self.centre * self.centre).sum(1) - 2 * unit @ self.centre.T
        gap = np.maximum(0, np.sqrt(np.maximum(0, square)) - self.radius)
        return np.maximum(0, 1 - gap * gap / 2)

    def best(self, ids: np.ndarray, counts: np.ndarray, k: int, exclude_self: bool) -> Best:
        """The best k of each query; the most promising groups first."""
        best, norm2 = Best(len(ids), k), (counts * counts).sum(1)
        most = np.where(norm2[:, None] > 0, self.most(counts), 0.0)
        left, step = np.argsort(-most.max(0), kind="stable"), 1 + 2 * k // GROUP
        while len(left):
            left = left[(most[:, left] >= best.kth[:, None] - _SLACK).any(0)]
            now, left = left[:step], left[step:]
            if not len(now):
                break
            rows = np.concatenate([np.arange(self.begin[g], self.begin[g + 1]) for g in now])
            cos = self.cosine(counts, norm2, rows)
            near = cos >= best.kth[:, None] - 2e-9  # rounding follows for these only
            if exclude_self:
                near &= ids[:, None] != self.ids[rows]
            if len(rows) > 4 * k:  # what the k best of these alone leave out
                kth = np.partition(np.where(near, cos, -1.0), len(rows) - k, axis=1)[:, len(rows) - k]
                near &= cos >= kth[:, None] - 2e-9
            q, i = np.nonzero(near)
            best.add(q, self.ids[rows][i], cos[q, i])
            step = min(2 * step, max(1, _CELLS // (len(ids) * GROUP)))
        return best


def _everything(base: Grouped, counts: np.ndarray, k: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(query's row, ids, cosines) where k is a large part of the base, whose rows are in order of their ids: one sort a query."""
    for row, cos in enumerate(base.cosine(counts, (counts * counts).sum(1), slice(None))):
        order = np.argsort(-np.round(cos, 9), kind="stable")[:k]
        yield row, base.ids[order], cos[order]


def _each_member(members: np.ndarray, cand: np.ndarray, value: np.ndarray, k: int, exclude_self: bool) -> pa.RecordBatch:
    """The k best of each query of one histogram, from the best of that histogram, one more where a query itself may be among them."""
    cands, values = np.broadcast_to(cand, (len(members), len(cand))), np.broadcast_to(value, (len(members), len(cand)))
    keep = cands != members[:, None] if exclude_self else np.ones(cands.shape, bool)
    rank = np.cumsum(keep, axis=1)
    keep &= rank <= k
    ids = np.repeat(members, keep.sum(1))
    return pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(cands[keep], pa.int64()), pa.array(values[keep]), pa.array(rank[keep], pa.int32())], names=["query_id", "cand_id", "cosine", "rank"])


@dataclass
class Kinds:
    """Different histograms, (kind, word, count) of each word, and the sequences of each: ids[begin[kind]:begin[kind + 1]], in order."""

    at: np.ndarray
    word: np.ndarray
    count: np.ndarray
    ids: np.ndarray
    begin: np.ndarray

    def first(self, keep: int) -> tuple[np.ndarray, np.ndarray]:
        """(kind, id) of at most ``keep`` sequences of each, those of the smallest ids; in order of the ids."""
        kind = np.repeat(np.arange(len(self.begin) - 1), np.diff(self.begin))
        chosen = np.arange(len(kind)) - self.begin[kind] < keep
        kind, ids = kind[chosen], self.ids[chosen]
        order = np.argsort(ids, kind="stable")
        return kind[order], ids[order]


def kinds(sequences: DataFrame) -> Kinds | None:
    """The histograms on the driver, equal ones once; None if they are more than may be sent.  The sequences are read once."""
    rows = sequences.select("seq_id", runs("tokens").alias("runs")).groupBy("runs").agg(F.array_sort(F.collect_list("seq_id")).alias("ids"))
    rows = rows.select(F.col("runs.word").alias("w"), F.col("runs.cnt").alias("c"), "ids").persist()
    try:
        size = rows.agg(F.sum(F.size("w")).alias("t"), F.sum(F.size("ids")).alias("n")).first()
        if (size["t"] or 0) > MOST_WORDS or (size["n"] or 0) > MOST_IDS:
            return None
        got = rows.toArrow()
    finally:
        rows.unpersist()
    w, c, ids = (got.column(k).combine_chunks() for k in range(3))
    begin, at = (np.concatenate([[0], np.cumsum(pc.list_value_length(x).to_numpy(zero_copy_only=False))]).astype(np.int64) for x in (ids, w))
    word, count, ids = (x.flatten().to_numpy(zero_copy_only=False).astype(np.int64) for x in (w, c, ids))
    return Kinds(np.repeat(np.arange(len(begin) - 1), np.diff(at)), word, count, ids, begin)


def nearest(queries: DataFrame, base: DataFrame, k: int, exclude_self: bool = True) -> DataFrame | None:
    """(query_id, cand_id, cosine, rank): the k most similar of each query, also those of cosine 0, ties by id.
    None if the histograms of either side are more than may be broadcast.

    Equal histograms have equal cosines, so they are compared once, and only the k sequences of a histogram with the smallest ids,
    one more where the query itself is left out after, can be among the best k of any query."""
    asked = kinds(queries)
    found = asked and (asked if base is queries else kinds(base))
    if asked is None or found is None:
        return None
    words, most = np.union1d(asked.word, found.word), k + exclude_self
    kind, ids = found.first(most)
    if max(len(asked.begin) - 1, len(ids)) * max(1, len(words)) > 4 * _CELLS:
        return None
    spark = base.sparkSession
    if not len(asked.ids) or not len(ids):
        return spark.createDataFrame([], "query_id bigint, cand_id bigint, cosine double, rank int")
    matrix = lambda b: dense(len(b.begin) - 1, b.at, b.word, b.count, words)
    arrays = lambda b: (len(b.begin) - 1, b.at, b.word, b.count)
    whole = 4 * k > len(ids)
    size = max(1, min(GROUP, _CELLS // len(ids))) if whole else GROUP
    mine = groups(matrix(asked), size)
    theirs = (np.arange(len(ids)), np.array([0, len(ids)])) if whole else groups(matrix(found)[kind])
    sent = spark.sparkContext.broadcast((arrays(asked), asked.ids, asked.begin, None if found is asked else arrays(found), kind, ids, words, mine, theirs))  # arrays only: executors have no copy of this package

    def run(batches):
        a, members, of, b, kind, ids, words, (order, begin), (rows, at) = sent.value
        mine = dense(*a, words)
        base = Grouped(ids, (mine if b is None else dense(*b, words))[kind], rows, at)
        for batch in batches:
            for g in batch.column(0).to_pylist():
                these = order[begin[g] : begin[g + 1]]
                if whole:
                    best = _everything(base, mine[these], most)
                else:
                    top = base.best(np.full(len(these), -1), mine[these], most, False)
                    ends = np.searchsorted(top.query, np.arange(len(these) + 1))
                    best = ((row, top.cand[x:y], top.value[x:y]) for row, (x, y) in enumerate(zip(ends[:-1], ends[1:], strict=True)))
                held: list[pa.RecordBatch] = []
                for row, cand, cos in best:
                    every = members[of[these[row]] : of[these[row] + 1]]
                    step = max(1, _CELLS // max(1, len(cand)))
                    for x in range(0, len(every), step):
                        held.append(_each_member(every[x : x + step], cand, cos, k, exclude_self))
                        if sum(h.num_rows for h in held) > 50_000:
                            yield from pa.Table.from_batches(held).combine_chunks().to_batches()
                            held = []
                if held:
                    yield from pa.Table.from_batches(held).combine_chunks().to_batches()

    # as many rows as there are answers, of which one a group is kept: Spark takes the size of the answers from it, and broadcasts
    # them in no join unless they are few
    n, each = len(mine[1]) - 1, max(1, len(asked.ids) * min(k, len(found.ids)) // (len(mine[1]) - 1))
    tasks = spark.range(0, n * each, 1, min(n, 4 * spark.sparkContext.defaultParallelism)).where(F.col("id") % each == 0).select(F.floor(F.col("id") / each).alias("id"))
    return tasks.mapInArrow(run, "query_id bigint, cand_id bigint, cosine double, rank int")
