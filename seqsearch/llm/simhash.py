"""SimHash near-duplicates by the generalised pigeonhole principle.

A fingerprint has 64 bits; two documents link when at most ``radius`` bits differ.  The bits are cut into parts, and
part i gets its own threshold t_i with sum(t_i + 1) = radius + 1: a linked pair then differs in at most t_i bits of at
least one part i.  Bits that go together share a part, so that the other parts are close to uniform; thresholds come from
a dynamic program over the estimated number of candidates and of probes.  Candidates are found by an equi-join on the
part's value, where the probing side also asks for the values within t_i bits, and are verified on all 64 bits.

Equal fingerprints are joined into one before the search, so a large group of copies costs one row.  No bucket is cut.
"""

from __future__ import annotations

import functools
import itertools
import math

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import connected_components, discard, finished, materialise, text_function

BITS = 64
_CHUNK = 1 << 16


def fingerprint(text: str | None, shingle: int = 4, seed: int = 42) -> int:
    """Majority bits of the XXH64 of all word shingles, as a signed 64-bit number; no words: 0."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    joined = b" ".join(words)
    if len(words) <= shingle:
        spans = [joined]
    else:
        ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
        starts = np.concatenate(([0], ends[:-1]))[: len(words) - shingle + 1].tolist()
        spans = [joined[i:j] for i, j in zip(starts, (ends[shingle - 1 :] - 1).tolist(), strict=True)]
    digest = xxhash.xxh64_intdigest
    ones = np.zeros(BITS, np.int64)
    for at in range(0, len(spans), _CHUNK):
        part = spans[at : at + _CHUNK]
        h = np.fromiter((digest(s, seed) for s in part), np.uint64, len(part))
        ones += np.unpackbits(h.astype(">u8").view(np.uint8).reshape(-1, 8), axis=1).sum(0, dtype=np.int64)
    value = int.from_bytes(np.packbits(2 * ones > len(spans)).tobytes(), "big")
    return value - (1 << BITS) if value >> (BITS - 1) else value


def fingerprints(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", shingle: int = 4, seed: int = 42) -> DataFrame:
    """(doc_id, fp); a null or empty text has fp 0."""
    of = text_function(lambda texts: [fingerprint(t, shingle, seed) for t in texts], "bigint")
    return docs.select(F.col(doc_id).alias("doc_id"), of(F.col(text)).alias("fp"))


def bit_statistics(fps: DataFrame) -> tuple[int, np.ndarray]:
    """Number of fingerprints, and of those that have bits i and j both set; every row counts."""

    def count(batches):
        both, n = np.zeros((BITS, BITS), np.int64), 0
        for batch in batches:
            v = batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64)
            for at in range(0, len(v), _CHUNK):
                bits = ((v[at : at + _CHUNK, None] >> np.arange(BITS, dtype=np.uint64)) & np.uint64(1)).astype(np.float32)
                both += np.rint(bits.T @ bits).astype(np.int64)
            n += len(v)
        yield pa.RecordBatch.from_pydict(
            {"at": pa.array(np.arange(BITS * BITS + 1), pa.int32()), "n": pa.array(np.append(both.ravel(), n), pa.int64())}
        )

    rows = fps.select("fp").mapInArrow(count, "at int, n long").groupBy("at").agg(F.sum("n").alias("n")).collect()
    flat = np.zeros(BITS * BITS + 1)
    for r in rows:
        flat[r["at"]] = r["n"]
    return int(flat[-1]), flat[:-1].reshape(BITS, BITS)


def group_bits(n: int, both: np.ndarray, parts: int) -> list[list[int]]:
    """Cut the bits into ``parts`` groups of nearly equal size; a group takes the bits most correlated with those it has."""
    if n == 0:
        return [list(range(i, BITS, parts)) for i in range(parts)]
    p = np.diag(both) / n
    sd = np.sqrt(np.maximum(p * (1 - p), 1e-12))
    corr = np.abs((both / n - np.outer(p, p)) / np.outer(sd, sd))
    np.fill_diagonal(corr, 0)
    free, out = list(range(BITS)), []
    for k in range(parts):
        size = (BITS - sum(map(len, out))) // (parts - k)
        group = [max(free, key=lambda b: (corr[b, free].max(), -b))]
        free.remove(group[0])
        while len(group) < size:
            best = max(free, key=lambda b: (corr[b, group].mean(), -b))
            group.append(best)
            free.remove(best)
        out.append(sorted(group))
    return out


def allocate(n: int, p: np.ndarray, groups: list[list[int]], radius: int, probe_cost: float = 1.0, check_cost: float = 0.2):
    """(cost, thresholds) with sum(t + 1) = radius + 1, by dynamic programming; -1 means that the part is not probed."""
    costs = []
    for group in groups:
        dist = np.array([1.0])  # of the number of differing bits between two fingerprints, bit by bit
        for b in group:
            differ = 2 * p[b] * (1 - p[b])
            dist = np.convolve(dist, [1 - differ, differ])
        row = [0.0]
        for t in range(radius + 1):
            probes = sum(math.comb(len(group), d) for d in range(min(t, len(group)) + 1))
            row.append(probe_cost * n * (probes + 1) + check_cost * n * n / 2 * dist[: t + 1].sum())
        costs.append(row)
    best = {0: (0.0, ())}
    for row in costs:
        step: dict[int, tuple[float, tuple]] = {}
        for used, (cost, plan) in best.items():
            for spent in range(radius + 2 - used):
                found = (cost + row[spent], (*plan, spent - 1))
                if used + spent not in step or found < step[used + spent]:
                    step[used + spent] = found
        best = step
    return best[radius + 1]


def plan_parts(n: int, both: np.ndarray, radius: int) -> list[tuple[int, list[int]]]:
    """[(mask, flips)] of the parts that are probed; flips are the differences that the probing side tries."""
    p = np.diag(both) / max(n, 1)
    options = [(allocate(n, p, g := group_bits(n, both, m), radius), g) for m in range(1, radius + 2) if m != 1 or radius == 0]
    (_, thresholds), groups = min(options, key=lambda x: x[0][0])
    out = []
    for t, group in zip(thresholds, groups, strict=True):
        if t >= 0:
            mask = sum(1 << b for b in group)
            flips = [sum(1 << b for b in c) for d in range(t + 1) for c in itertools.combinations(group, d)]
            out.append((mask, flips))
    return out


def _signed(v: int) -> int:
    return v - (1 << BITS) if v >> (BITS - 1) else v


def linked_pairs(fps: DataFrame, radius: int = 4) -> DataFrame:
    """(a, b), a < b, for all pairs of distinct fingerprints with at most ``radius`` differing bits."""
    if radius == 0:
        return fps.select(F.col("fp").alias("a"), F.col("fp").alias("b")).limit(0)
    n, both = bit_statistics(fps)
    parts = plan_parts(n, both, radius)

    def part(i: int) -> Column:
        return F.col("fp").bitwiseAND(F.lit(_signed(parts[i][0])))

    def near_values(i: int) -> Column:
        flips = F.array(*[F.lit(_signed(f)) for f in parts[i][1]])
        return F.transform(flips, lambda f: F.struct(F.lit(i).alias("part"), part(i).bitwiseXOR(f).alias("value")))

    index = fps.select(F.col("fp").alias("a"), F.explode(F.array(*[F.struct(F.lit(i).alias("part"), part(i).alias("value")) for i in range(len(parts))])).alias("k"))
    probe = fps.select(F.col("fp").alias("b"), F.explode(F.flatten(F.array(*map(near_values, range(len(parts)))))).alias("k"))
    index, probe = index.select("a", "k.part", "k.value"), probe.select("b", "k.part", "k.value")
    near = F.expr(f"a < b and bit_count(a ^ b) <= {radius}")
    return index.join(probe, ["part", "value"]).where(near).select("a", "b").distinct()


def near_duplicates(
    docs: DataFrame, doc_id: str = "doc_id", text: str = "text", radius: int = 4, shingle: int = 4, seed: int = 42
) -> DataFrame:
    """(doc_id, fp, component_id): one row for each row of ``docs``; component_id is the smallest doc_id reachable.

    Null and empty texts have fingerprint 0 and link like any other; repeated rows stay repeated; a null doc_id is
    carried but never names a component (unless no other id is there).  Other columns of ``docs`` are not read.
    """
    own = materialise(fingerprints(docs, doc_id, text, shingle, seed), "simhash")
    distinct = materialise(own.groupBy("fp").agg(F.min("doc_id").alias("first_id")), "simhash-distinct")
    roots = connected_components(linked_pairs(distinct, radius))
    member = distinct.join(roots, distinct["fp"] == roots["node"], "left").select("fp", "first_id", F.coalesce("root", "fp").alias("root"))
    names = member.groupBy("root").agg(F.min("first_id").alias("component_id"))
    out = own.join(member.join(names, "root").select("fp", "component_id"), "fp").select("doc_id", "fp", "component_id")
    return finished(out, "simhash-components", own, distinct, roots)


def _digest(text: str) -> Column:
    """A text's own number of 128 bits; null counts as empty."""
    return F.md5(F.coalesce(F.col(text), F.lit("")))


def _once(docs: DataFrame, doc_id: str, text: str) -> DataFrame:
    """The rows with an id, rows equal in id and text once, with the text's digest as ``__digest``.  Repeats are dropped before the
    shuffle already, so an id that very many rows share costs one row a partition."""
    return docs.where(F.col(doc_id).isNotNull()).withColumn("__digest", _digest(text)).dropDuplicates([doc_id, "__digest"])


def _only(docs: DataFrame, kept: DataFrame, doc_id: str, text: str) -> DataFrame:
    """The rows of ``docs`` whose (id, text's digest) is in ``kept``, equal rows once, and all rows without an id."""
    names = kept.select(F.col("doc_id").alias(doc_id), F.col("digest").alias("__digest"))
    found = _once(docs, doc_id, text).join(names, [doc_id, "__digest"], "left_semi")
    return found.select(*docs.columns).unionByName(docs.where(F.col(doc_id).isNull()))


def keep_first(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", radius: int = 4, shingle: int = 4, seed: int = 42) -> DataFrame:
    """The rows of ``docs``, all columns, that name their group: of each group the one of the smallest id, of equal ids that
    of the smallest digest of the text.

    Rows equal in id and text are reduced to one; rows of one id with texts that don't link all stay.  A row without an id
    can't name a group and stays.  Null and empty texts are one group.
    """
    of = text_function(lambda texts: [fingerprint(t, shingle, seed) for t in texts], "bigint")
    own = materialise(docs.select(F.col(doc_id).alias("doc_id"), of(F.col(text)).alias("fp"), _digest(text).alias("digest")).where("doc_id is not null"), "simhash")
    distinct = materialise(own.groupBy("fp").agg(F.min(F.struct("doc_id", "digest")).alias("first")), "simhash-distinct")
    roots = connected_components(linked_pairs(distinct.select("fp"), radius))
    member = distinct.join(roots, distinct["fp"] == roots["node"], "left").select(F.coalesce("root", "fp").alias("root"), "first")
    kept = finished(member.groupBy("root").agg(F.min("first").alias("k")).select("k.*"), "simhash-kept", own, distinct, roots)
    return _only(docs, kept, doc_id, text)


# --- documents by their sets of word shingles -------------------------------------------------------------------------
def shingle_hashes(text: str | None, shingle: int = 5, seed: int = 42) -> np.ndarray:
    """The distinct XXH64 of all word shingles, in order; a text of fewer words is one shingle, and no words give none."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    n = max(1, len(words) - shingle + 1)
    digest = xxhash.xxh64_intdigest
    return np.unique(np.fromiter((digest(b" ".join(words[i : i + shingle]), seed) for i in range(n)), np.uint64, n))


def majority(hashes: np.ndarray) -> int:
    """The SimHash of a set of hashes: a bit is 1 if it is set in over half of them; as a signed 64-bit number, no hashes give 0."""
    ones = np.zeros(BITS, np.int64)
    for at in range(0, len(hashes), _CHUNK):
        ones += np.unpackbits(hashes[at : at + _CHUNK].astype(">u8").view(np.uint8).reshape(-1, 8), axis=1).sum(0, dtype=np.int64)
    return _signed(int.from_bytes(np.packbits(2 * ones > len(hashes)).tobytes(), "big"))


def fingerprint_candidates(distinct: DataFrame, radius: int) -> DataFrame:
    """(a, b), a < b, of ``rep``: each with the least of its fingerprint, and the least ones of fingerprints within ``radius`` bits."""
    least = materialise(distinct.groupBy("fp").agg(F.min("rep").alias("hub")), "similar-fingerprints")
    equal = distinct.join(least, "fp").where("hub < rep").select(F.col("hub").alias("a"), F.col("rep").alias("b"))
    one, two = (least.select(F.col("fp").alias(c), F.col("hub").alias(f"h{c}")) for c in "ab")
    near = linked_pairs(least.select("fp"), radius).join(one, "a").join(two, "b").select(F.least("ha", "hb").alias("a"), F.greatest("ha", "hb").alias("b"))
    return finished(equal.unionAll(near), "similar-candidates", least)


def band_keys(hashes: np.ndarray, bands: int, rows: int, seed: int) -> np.ndarray:
    """One key a band of ``rows`` minima each; sets of Jaccard similarity s share one with probability 1 - (1 - s**rows)**bands."""
    rng = np.random.default_rng(seed)
    factor, shift = rng.integers(0, 2**63, (2, bands * rows), dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    least = np.full(bands * rows, np.iinfo(np.uint64).max)
    for at in range(0, len(hashes), 1024):
        x = hashes[at : at + 1024, None] * factor + shift
        x ^= x >> np.uint64(32)
        x *= np.uint64(0x9E3779B97F4A7C15)
        least = np.minimum(least, x.min(0))
    parts = least.reshape(bands, rows)
    return np.array([xxhash.xxh64_intdigest(b.tobytes(), k) for k, b in enumerate(parts)], np.uint64).view(np.int64)


def similar_pairs(pairs: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """(a, b) of the pairs of ``rep`` whose ``hashes`` have Jaccard similarity ``similarity`` or more."""
    left, right = (sets.select(F.col("rep").alias(c), F.col("hashes").alias(f"h{c}")) for c in "ab")
    shared = F.size(F.array_intersect("ha", "hb"))
    wanted = shared >= F.lit(similarity) * (F.size("ha") + F.size("hb") - shared) - 1e-9
    return pairs.join(left, "a").join(right, "b").where(wanted).select("a", "b")


#: Documents of a band whose pairs are joined as rows, and documents in a block of a more crowded band.  A band of n documents
#: sends about n * n whole sets as pairs and 2 * n as a block, whose cost is one call for each block: so only small bands go by pairs.
CROWD, BLOCK = 16, 512


def _crowded_links(open_: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """(a, b) of all links in crowded bands between documents that are not yet joined.

    The documents outside a band's largest group meet all of the band, block by block: a task compares two blocks by counting
    common shingles in a matrix product, and only links come out, never pairs.
    """
    docs = open_.select("key", "rep", "root", "main", F.ceil((F.col("n") - F.col("most")) / BLOCK).cast("int").alias("nu"), F.ceil(F.col("n") / BLOCK).cast("int").alias("nv")).join(sets, "rep")
    each = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    place = lambda n, salt: F.pmod(F.xxhash64("rep", F.lit(salt)), F.col(n)).cast("int")
    asked = docs.where("root <> main").select("key", place("nu", 1).alias("u"), each("nv").alias("v"), F.lit(True).alias("asked"), "rep", "root", "hashes")
    every = docs.select("key", each("nu").alias("u"), place("nv", 2).alias("v"), F.lit(False).alias("asked"), "rep", "root", "hashes")

    def compare(rows: pa.Table) -> pa.Table:
        rep, root, side = (rows.column(c).to_numpy() for c in ("rep", "root", "asked"))
        column = rows.column("hashes").combine_chunks()
        sizes = np.diff(column.offsets.to_numpy()).astype(np.int64)
        token = column.flatten().to_numpy()
        at = np.repeat(np.arange(len(rep)), sizes)
        order = np.argsort(token, kind="stable")
        token, at = token[order], at[order]
        number = np.cumsum(np.concatenate(([0], token[1:] != token[:-1]))) if len(token) else token
        x, y = np.flatnonzero(side), np.flatnonzero(~side)
        place_x, place_y = np.full(len(rep), -1), np.full(len(rep), -1)
        place_x[x], place_y[y] = np.arange(len(x)), np.arange(len(y))
        common = np.zeros((len(x), len(y)), np.float32)
        step = max(1, 4_000_000 // max(1, len(rep)))
        last = int(number[-1]) + 1 if len(number) else 0
        for first in range(0, last, step):  # so many shingles at a time
            a, b = np.searchsorted(number, [first, first + step])
            px, py, col = place_x[at[a:b]], place_y[at[a:b]], number[a:b] - first
            mx, my = np.zeros((len(x), step), np.float32), np.zeros((len(y), step), np.float32)
            mx[px[px >= 0], col[px >= 0]] = 1
            my[py[py >= 0], col[py >= 0]] = 1
            common += mx @ my.T
        union = sizes[x][:, None] + sizes[y] - common
        i, j = np.nonzero((common >= similarity * union - 1e-9) & (root[x][:, None] != root[y]))
        return pa.table({"a": pa.array(np.minimum(rep[x][i], rep[y][j]), pa.int64()), "b": pa.array(np.maximum(rep[x][i], rep[y][j]), pa.int64())})

    return asked.unionAll(every).groupBy("key", "u", "v").applyInArrow(compare, "a bigint, b bigint").distinct()


def keep_first_similar(
    docs: DataFrame, similarity: float = 0.8, doc_id: str = "doc_id", text: str = "text", shingle: int = 5, bands: int = 30, rows: int = 5, seed: int = 42, radius: int = 4
) -> DataFrame:
    """The rows of ``docs``, all columns, that name their group, as :func:`keep_first`; texts link when the Jaccard
    similarity of their sets of word shingles is ``similarity`` or more.

    Candidates have SimHash fingerprints of their shingles within ``radius`` bits, found by the generalised pigeonhole principle,
    or share a band of minima, since pairs near ``similarity`` differ in more bits than a fingerprint can be searched by; all are
    verified on whole sets.  Of a band each is first compared with the least only, and, while that leaves more pairs than there are rows, with two more that are drawn from the band; of bands whose
    documents these links do not all join, all pairs not yet joined follow.  Texts without words
    (null, empty) link with each other.  Rows equal in id and text are reduced to one, rows without an id all stay.
    """
    def lists(rows: list[np.ndarray]) -> pa.Array:
        ends = np.concatenate(([0], np.cumsum([len(r) for r in rows]))).astype(np.int32)
        return pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([*rows, np.zeros(0, np.int64)]).astype(np.int64)))

    def sketch(texts: list[str | None]) -> pa.Array:
        sets = [shingle_hashes(t, shingle, seed) for t in texts]
        same = pa.array([xxhash.xxh3_128_digest(h.tobytes()) for h in sets], pa.binary())
        keys = lists([band_keys(h, bands, rows, seed) if len(h) else np.zeros(0, np.int64) for h in sets])
        return pa.StructArray.from_arrays([same, pa.array([majority(h) for h in sets], pa.int64()), keys], names=["same", "fp", "keys"])

    def hashes(texts: list[str | None]) -> pa.Array:
        return lists([shingle_hashes(t, shingle, seed).view(np.int64) for t in texts])

    sketched = text_function(sketch, "struct<same:binary,fp:bigint,keys:array<bigint>>")(F.col(text))
    named = docs.where(F.col(doc_id).isNotNull()).select(F.col(doc_id).alias("doc_id"), _digest(text).alias("digest"), sketched.alias("s"))
    own = materialise(named.select("doc_id", "digest", "s.*"), "sketches")
    numbered = F.monotonically_increasing_id().alias("rep")  # fixed by writing it
    firsts = own.groupBy("same").agg(F.min(F.struct("doc_id", "digest")).alias("first"), F.first("fp").alias("fp"), F.first("keys").alias("keys"))  # equal sets have equal keys
    distinct = finished(firsts.select(numbered, "first", "fp", "keys"), "sketches-distinct", own)
    close = fingerprint_candidates(distinct.select("rep", "fp"), radius)
    every = distinct.select("rep", F.explode("keys").alias("key"))
    crowded = every.groupBy("key").agg(F.min("rep").alias("hub"), F.count("*").alias("n")).where("n > 1").select("key", "hub")
    band = materialise(every.join(crowded, "key"), "bands")
    spokes = band.where("hub < rep").select(F.col("hub").alias("a"), F.col("rep").alias("b")).distinct()
    # whole sets only of the documents that share a band with another or are near it by fingerprint
    met = band.select("rep").unionAll(close.select(F.explode(F.array("a", "b")).alias("rep"))).distinct()
    wanted = distinct.join(met, "rep").select("rep", F.col("first.doc_id").alias(doc_id), F.col("first.digest").alias("__digest"))
    texts = _once(docs.select(doc_id, text), doc_id, text).join(wanted, [doc_id, "__digest"])
    small = materialise(texts.select("rep", text_function(hashes, "array<bigint>")(F.col(text)).alias("hashes")), "band-sets")
    links = [materialise(similar_pairs(close.unionAll(spokes).distinct(), small, similarity), "similar-first")]
    discard(close)
    size, before = band.count(), math.inf
    for turn in itertools.count():
        roots = connected_components(functools.reduce(DataFrame.unionAll, links))
        placed = band.join(roots.withColumnRenamed("node", "rep"), "rep", "left").select("key", "rep", "hub", F.coalesce("root", "rep").alias("root"))
        parts = placed.groupBy("key", "root").agg(F.count("*").alias("n")).groupBy("key").agg(F.sum("n").alias("n"), F.sum(F.col("n") * F.col("n")).alias("q"), F.max("n").alias("most"), F.max_by("root", "n").alias("main"))
        mixed = parts.where("n * n > q").select("key", "n", "most", "main", ((F.col("n") * F.col("n") - F.col("q")) / 2).alias("pairs"))
        open_ = materialise(placed.join(mixed, "key"), "bands-open")
        left_over = open_.select("key", "pairs").distinct().agg(F.sum("pairs")).first()[0] or 0
        discard(roots)
        if left_over <= size or left_over > before / 2:
            break
        # far more pairs than rows: first each against a few drawn from its band, which joins most groups of near copies
        before = left_over
        drawn = [F.min_by(F.struct("rep", "root"), F.xxhash64("rep", F.lit(2 * turn + k))).alias(f"d{k}") for k in range(2)]
        few = open_.groupBy("key").agg(*drawn).select("key", F.explode(F.array("d0", "d1")).alias("d"))
        tried = open_.join(few, "key").where(F.col("root") != F.col("d.root")).select(F.least("rep", "d.rep").alias("a"), F.greatest("rep", "d.rep").alias("b")).distinct()
        links.append(materialise(similar_pairs(tried, small, similarity), "similar-drawn"))
        discard(open_)
    # what is not yet joined: small bands by pairs (what their least was compared with is settled), crowded ones block by block
    left, right = (open_.where(F.col("n") <= CROWD).select("key", "hub", F.col("rep").alias(c), F.col("root").alias(f"r{c}")) for c in "ab")
    rest = left.join(right, ["key", "hub"]).where("a < b and ra <> rb and a <> hub").select("a", "b").distinct()
    links.append(materialise(similar_pairs(rest, small, similarity), "similar-rest"))
    links.append(materialise(_crowded_links(open_.where(F.col("n") > CROWD), small, similarity), "similar-crowded"))
    member = connected_components(functools.reduce(DataFrame.unionAll, links))
    group = distinct.join(member, F.col("rep") == F.col("node"), "left").groupBy(F.coalesce("root", "rep").alias("root")).agg(F.min("first").alias("k"))
    kept = finished(group.select("k.*"), "similar-kept", distinct, band, small, open_, member, *links)
    return _only(docs, kept, doc_id, text)
