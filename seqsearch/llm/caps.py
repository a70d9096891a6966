"""Embedding near-duplicates by spherical-cap filters.

A filter is a direction; a vector belongs to it when their inner product reaches a threshold.  The directions form a
structured random product code: after a random rotation the space is cut into two halves, each half has its own random
unit vectors, and every pair of one from each half is a direction.  The pairs that a vector exceeds are listed without
trying all: only code words of one half that can still reach the threshold with the best of the other are combined.
A vector that few directions reach, or none, has its best ones as filters, so that no vector is left without.
Vectors are joined on (label, filter), and each candidate pair is verified by its cosine in double precision.

In few dimensions product directions leave wide gaps.  There the directions are plain random ones, and a vector belongs to
all that are not further from it than its own best one and the wanted angle together: of two linked vectors the one nearer to
its best direction then always meets the other there, so no link is lost.

Equal vectors are joined into one before the search.  Several independent product codes are used: a pair that one misses,
another finds.
"""

from __future__ import annotations

import itertools
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import connected_components, finished, materialise

#: Inner products of vectors and code words that are held at a time.
_PRODUCTS = 2_000_000
#: Vectors of fewer dimensions than this have plain directions.
FEW_DIMENSIONS = 16


def cap_height(size: int, share: float) -> float:
    """The product that a share of the sphere's directions reach with a fixed unit vector: the height of that cap."""
    t = np.linspace(-1.0, 1.0, 200_001)
    density = np.maximum(1 - t * t, 1e-300) ** ((size - 3) / 2)
    tail = np.cumsum(density[::-1])[::-1] / density.sum()
    return float(t[min(np.searchsorted(-tail, -share), len(t) - 1)])


class ProductCode:
    """``words`` unit vectors in each half; a direction is the pair (i, j), numbered i * words + j."""

    def __init__(self, size: int, words: int, hits: float, seed: int) -> None:
        rng = np.random.default_rng([seed, size, words])
        q, r = np.linalg.qr(rng.standard_normal((size, size)))
        self.rotation = q * np.sign(np.diag(r))
        self.cut = (size + 1) // 2
        halves = [rng.standard_normal((words, n)) for n in (self.cut, size - self.cut)]
        self.halves = [h / np.maximum(np.linalg.norm(h, axis=1, keepdims=True), 1e-300) for h in halves]
        self.words = words
        self.threshold = cap_height(size, min(0.5, hits / words**2))

    def decode(self, x: np.ndarray, least: int = 0) -> tuple[np.ndarray, np.ndarray]:
        """(row, direction) of all directions that the rows of ``x``, unit vectors, exceed; of a row that exceeds fewer than
        ``least``, its ``least`` best directions."""
        y = x @ self.rotation.T
        a, b = y[:, : self.cut] @ self.halves[0].T, y[:, self.cut :] @ self.halves[1].T
        need = self.threshold * math.sqrt(2)
        rows_a, words_a = np.nonzero(a >= need - b.max(1, keepdims=True))
        rows_b, words_b = np.nonzero(b >= need - a.max(1, keepdims=True))
        count_b = np.bincount(rows_b, minlength=len(x))
        first_b = np.concatenate(([0], np.cumsum(count_b)))
        each = count_b[rows_a]
        left = np.repeat(np.arange(len(rows_a)), each)
        right = np.arange(len(left)) - np.repeat(np.cumsum(each) - each, each) + np.repeat(first_b[rows_a], each)
        row, i, j = rows_a[left], words_a[left], words_b[right]
        over = a[row, i] + b[row, j] >= need
        row, direction = row[over], (i[over] * self.words + j[over]).astype(np.int64)
        short = np.nonzero(np.bincount(row, minlength=len(x)) < least)[0]
        if not len(short):
            return row, direction
        best = self._best(a[short], b[short], least)
        longer = ~np.isin(row, short)
        return np.concatenate((row[longer], np.repeat(short, best.shape[1]))), np.concatenate((direction[longer], best.ravel()))

    def _best(self, a: np.ndarray, b: np.ndarray, m: int) -> np.ndarray:
        """The ``m`` directions of the largest sums, row by row; those of ranks r and s have (r + 1) * (s + 1) - 1 before them."""
        m = min(m, self.words**2)
        n = min(m, self.words)
        r, s = (k.ravel() for k in np.meshgrid(np.arange(n), np.arange(n), indexing="ij"))
        r, s = r[(r + 1) * (s + 1) <= m], s[(r + 1) * (s + 1) <= m]
        tops = []
        for half in (a, b):
            top = np.argpartition(-half, n - 1, axis=1)[:, :n]
            tops.append(np.take_along_axis(top, np.argsort(-np.take_along_axis(half, top, 1), axis=1, kind="stable"), 1))
        i, j = tops[0][:, r], tops[1][:, s]
        total = np.take_along_axis(a, i, 1) + np.take_along_axis(b, j, 1)
        first = np.argpartition(-total, m - 1, axis=1)[:, :m]
        return np.take_along_axis(i * self.words + j, first, 1).astype(np.int64)


class PlainCode:
    """Random unit vectors for few dimensions, so many that a vector belongs to about ``hits`` of them."""

    def __init__(self, size: int, cosine: float, hits: float, seed: int, most: int = 16384) -> None:
        rng = np.random.default_rng([seed, size])
        self.angle = math.acos(min(1.0, max(-1.0, cosine))) + 1e-7
        probe, words = self._units(rng, 256, size), 32
        while True:
            self.directions = self._units(rng, words, size)
            if words >= most or len(self.decode(probe)[0]) >= hits * len(probe):
                break
            words *= 2
        self.words = words

    @staticmethod
    def _units(rng: np.random.Generator, n: int, size: int) -> np.ndarray:
        x = rng.standard_normal((n, size))
        return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-300)

    def decode(self, x: np.ndarray, least: int = 0) -> tuple[np.ndarray, np.ndarray]:
        """(row, direction) of all directions within the wanted angle beyond each row's best one."""
        y = np.clip(x @ self.directions.T, -1.0, 1.0)
        reach = np.minimum(np.arccos(y.max(1)) + self.angle, math.pi)
        row, direction = np.nonzero(y >= np.cos(reach)[:, None] - 1e-12)
        return row, direction.astype(np.int64)


def code_words(n: int, least: int = 256, most: int = 65536) -> int:
    """Words of each half so that a filter holds a few of n vectors that are not near each other."""
    return int(min(most, max(least, 2 ** math.ceil(math.log2(max(2.0, math.sqrt(4.0 * n)))))))


def clean_vectors(table: DataFrame, vec_id: str, embedding: str, label: str) -> DataFrame:
    """(vec_id, label, v, ok): v is the vector in doubles, ok says that it can link."""
    v = F.transform(F.col(embedding), lambda x: x.cast("double"))
    own = table.select(F.col(vec_id).alias("vec_id"), F.col(label).alias("label"), v.alias("v"))
    finite = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    some = F.exists("v", lambda x: x != 0.0)
    return own.withColumn("ok", F.coalesce(F.col("label").isNotNull() & F.col("vec_id").isNotNull() & finite & some, F.lit(False)))


def _unit(rows: pa.Array) -> np.ndarray:
    x = np.stack(rows.to_numpy(zero_copy_only=False)).astype(np.float64)
    x = x / np.abs(x).max(axis=1, keepdims=True)  # no overflow in the squares
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def candidate_pairs(reps: DataFrame, words: int, hits: float, codes: int, seed: int, cosine: float = 0.98) -> DataFrame:
    """(a, b), a < b, of representatives (rep, label, v) that share a filter of any code."""

    def filters(batches):
        made: dict[int, list] = {}
        for batch in batches:
            reps_, labels, vectors = batch.column(0), batch.column(1), batch.column(2)
            sizes = np.array([len(v) for v in vectors], np.int64)
            for size in np.unique(sizes).tolist():
                at = np.nonzero(sizes == size)[0]
                x = _unit(vectors.take(pa.array(at)))
                if size not in made:
                    made[size] = [PlainCode(size, cosine, hits, seed)] if size < FEW_DIMENSIONS else [ProductCode(size, words, hits, seed + k) for k in range(codes)]
                rows = max(1, _PRODUCTS // max(c.words for c in made[size]))
                for first, (k, code) in itertools.product(range(0, len(x), rows), enumerate(made[size])):
                    row, direction = code.decode(x[first : first + rows], math.ceil(hits))
                    where = pa.array(at[first + row])
                    key = (direction * codes + k) * 65536 + size % 65536
                    yield pa.RecordBatch.from_arrays([reps_.take(where), labels.take(where), pa.array(key, pa.int64())], names=["rep", "label", "filter"])

    kinds = {f.name: f.dataType.simpleString() for f in reps.schema}
    in_filter = reps.select("rep", "label", "v").mapInArrow(filters, f"rep {kinds['rep']}, label {kinds['label']}, filter bigint")
    left = in_filter.select(F.col("rep").alias("a"), "label", "filter")
    right = in_filter.select(F.col("rep").alias("b"), "label", "filter")
    return left.join(right, ["label", "filter"]).where("a < b").select("a", "b").distinct()


def verified_pairs(pairs: DataFrame, reps: DataFrame, cosine: float) -> DataFrame:
    """(a, b) of the candidates whose cosine in doubles reaches the threshold."""

    def check(batches):
        for batch in batches:
            a, b = batch.column(2), batch.column(3)
            same = np.array([len(x) == len(y) for x, y in zip(a, b, strict=True)], bool)
            keep = np.zeros(len(same), bool)
            sizes = np.array([len(x) for x in a], np.int64)
            for size in np.unique(sizes[same]).tolist():
                at = np.nonzero(same & (sizes == size))[0]
                x, y = (np.stack(c.take(pa.array(at)).to_numpy(zero_copy_only=False)).astype(np.float64) for c in (a, b))
                x, y = x / np.abs(x).max(1, keepdims=True), y / np.abs(y).max(1, keepdims=True)
                dot = np.einsum("ij,ij->i", x, y)
                keep[at] = dot / np.sqrt(np.einsum("ij,ij->i", x, x) * np.einsum("ij,ij->i", y, y)) >= cosine
            yield pa.RecordBatch.from_arrays([c.filter(pa.array(keep)) for c in (batch.column(0), batch.column(1))], names=["a", "b"])

    kind = reps.schema["rep"].dataType.simpleString()
    left, right = reps.select(F.col("rep").alias("a"), F.col("v").alias("va")), reps.select(F.col("rep").alias("b"), F.col("v").alias("vb"))
    both = pairs.join(left, "a").join(right, "b").select("a", "b", "va", "vb")
    return both.mapInArrow(check, f"a {kind}, b {kind}")


def near_duplicates(table: DataFrame, cosine: float = 0.98, hits: float = 24.0, codes: int = 2, seed: int = 7, words: int | None = None, vec_id: str = "vec_id", embedding: str = "embedding", label: str = "label") -> DataFrame:
    """(vec_id, n_links, component_id, kept), one row for each row of ``table``.

    Vectors link when their labels are equal and not null and their cosine reaches ``cosine``.  A vector that is null, zero,
    or has a null or non-finite component, or a null id or label, links with nothing and is its own component.  Vectors of
    different length never link.  Repeated rows count as other vectors, and so do other vectors of the same id: links are
    between rows, and a row's component is named by the smallest id that its own links reach.  ``hits`` is the mean number of
    directions that a vector reaches in each of ``codes`` codes, and the least number of its filters there; recall rises with
    both (README has figures).  Below ``FEW_DIMENSIONS`` no link is lost.  An empty table has no rows.
    """
    own = materialise(clean_vectors(table, vec_id, embedding, label), "caps-vectors")
    alone = own.where("not ok").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    good = own.where("ok")
    numbered = F.monotonically_increasing_id().alias("rep")  # fixed by writing it; ids may repeat
    reps = materialise(good.groupBy("label", "v").agg(F.min("vec_id").alias("first_id"), F.count("*").alias("copies")).select(numbered, "*"), "caps-distinct")
    words = words or code_words(reps.count())
    found = materialise(verified_pairs(candidate_pairs(reps, words, hits, codes, seed, cosine), reps, cosine), "caps-links")
    sized = reps.select("rep", "copies")
    both = found.unionAll(found.select(F.col("b").alias("a"), F.col("a").alias("b")))
    degree = both.join(sized.select(F.col("rep").alias("b"), "copies"), "b").groupBy("a").agg(F.sum("copies").alias("others"))
    roots = connected_components(found)
    placed = reps.join(roots.select(F.col("node").alias("rep"), "root"), "rep", "left").withColumn("root", F.coalesce("root", "rep"))
    names = placed.groupBy("root").agg(F.min("first_id").alias("component_id"))
    of_rep = (
        placed.join(degree.select(F.col("a").alias("rep"), "others"), "rep", "left")
        .join(names, "root")
        .select("label", "v", (F.col("copies") - 1 + F.coalesce("others", F.lit(0))).alias("n_links"), "component_id")
    )
    linked = good.join(of_rep, ["label", "v"]).select("vec_id", "n_links", "component_id")
    out = linked.unionAll(alone).withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))
    return finished(out, "caps", own, reps, found, roots)
