"""Vector quantisation: patches, nearest codes, moving-average updates, revival, and the measures of a codebook."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..config import CodebookParams
from ..schemas import CODEBOOK


def patchify(latents: DataFrame, length: int, tail: str = "drop", stride: int | None = None) -> DataFrame:
    """LATENT to PATCH: ``length`` frames in a row, end to end.  A short tail is dropped, or (pad_last) filled with its last
    frame.  A stride below the length gives overlapping patches."""
    stride = stride or length
    reach = (length - 1) // stride + 1
    if stride == length:
        rows = latents.withColumn("patch_idx", F.floor(F.col("t") / length).cast("int"))
    else:
        # a frame is in the patches that start at most length - 1 before it
        back = F.transform(F.sequence(F.lit(0), F.lit(reach - 1)), lambda k: F.floor(F.col("t") / stride).cast("int") - k)
        rows = latents.withColumn("patch_idx", F.explode(back)).where((F.col("patch_idx") >= 0) & (F.col("t") < F.col("patch_idx") * stride + length))
    grouped = rows.groupBy("clip_id", "patch_idx").agg(F.array_sort(F.collect_list(F.struct("t", "latent"))).alias("f"))
    parts = F.transform("f", lambda x: F.transform(x["latent"], lambda v: v.cast("double")))
    if tail == "drop":
        grouped = grouped.where(F.size("f") == length)
    else:
        parts = F.concat(parts, F.array_repeat(F.element_at(parts, -1), F.lit(length) - F.size("f")))
    return grouped.select("clip_id", "patch_idx", F.flatten(parts).alias("vec"))


def squared_distance(a: str | Column, b: str | Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)


def codebook_rows(codebook: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """(codes, centroids) on the driver: K rows, K is a parameter."""
    rows = sorted(codebook.select("code", "centroid").collect())
    return np.array([r[0] for r in rows], np.int32), np.array([r[1] for r in rows], float)


def assign(patches: DataFrame, codebook: DataFrame, how: str = "native", decimals: int = 9) -> DataFrame:
    """ASSIGNED: the nearest code of each patch, the lowest of equal ones (distances rounded to ``decimals``).

    native: the codebook, K rows, is broadcast and the best code taken row by row.  arrow: one matrix product a batch.
    """
    if how == "native":
        codes = codebook.agg(F.array_sort(F.collect_list(F.struct("code", "centroid"))).alias("book"))
        rows = patches.join(F.broadcast(codes), F.lit(True))  # a single row with K codes
        near = F.array_min(F.transform("book", lambda c: F.struct(F.round(squared_distance(F.col("vec"), c["centroid"]), decimals).alias("d"), c["code"].alias("code"))))
        return rows.withColumn("n", near).select("clip_id", "patch_idx", F.col("n.code").alias("code"), F.col("n.d").alias("dist2"))
    numbers, centroids = codebook_rows(codebook)

    def nearest(batches):
        for batch in batches:
            x = np.stack(batch.column(2).to_numpy(zero_copy_only=False)) if batch.num_rows else np.zeros((0, centroids.shape[1]))
            d = np.round(np.maximum((x * x).sum(1)[:, None] - 2 * x @ centroids.T + (centroids * centroids).sum(1), 0), decimals)
            best = d.argmin(1)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(numbers[best], pa.int32()), pa.array(d[np.arange(len(d)), best])], names=["clip_id", "patch_idx", "code", "dist2"])

    return patches.select("clip_id", "patch_idx", "vec").mapInArrow(nearest, "clip_id bigint, patch_idx int, code int, dist2 double")


def straight_through(p: str, q: str) -> Column:
    """The value that goes forward: p plus the difference, so q; its gradient with respect to p is the identity."""
    return F.zip_with(p, q, lambda x, y: x + (y - x))


def code_sums(patches: DataFrame, assigned: DataFrame) -> DataFrame:
    """(code, hits, total): counts and vector sums of an epoch, added within partitions before K rows of each are shuffled."""
    rows = patches.join(assigned.select("clip_id", "patch_idx", "code"), ["clip_id", "patch_idx"]).select("code", F.posexplode("vec").alias("i", "x"))
    sums = rows.groupBy("code", "i").agg(F.sum("x").alias("x"), F.count("*").alias("c"))
    return sums.groupBy("code").agg(F.max("c").alias("hits"), F.transform(F.array_sort(F.collect_list(F.struct("i", "x"))), lambda s: s["x"]).alias("total"))


def ema_step(codebook: DataFrame, sums: DataFrame, alpha: float = 0.5, eps: float = 1e-5) -> DataFrame:
    """CODEBOOK after one epoch: moving averages of counts and sums; a centroid is their quotient."""
    rows = codebook.join(sums, "code", "left")
    n = alpha * F.col("ema_n") + (1 - alpha) * F.coalesce("hits", F.lit(0))
    m = F.when(F.col("total").isNull(), F.transform("ema_m", lambda x: alpha * x)).otherwise(F.zip_with("ema_m", "total", lambda x, y: alpha * x + (1 - alpha) * y))
    rows = rows.select("code", n.alias("n"), m.alias("m"), (F.col("epoch") + 1).alias("epoch"))
    return rows.select("code", F.transform("m", lambda x: x / F.greatest("n", F.lit(eps))).alias("centroid"), F.col("n").alias("ema_n"), F.col("m").alias("ema_m"), "epoch")


def revive(codebook: DataFrame, assigned: DataFrame, patches: DataFrame, seed: int = 7) -> DataFrame:
    """CODEBOOK whose codes without a hit in the epoch are patches of the batch, drawn by a hash; count 1, sum the patch."""
    dead = codebook.join(assigned.select("code").distinct(), "code", "left_anti")
    dead = dead.select("code", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy("code")).alias("k"))  # at most K rows
    taken = _drawn(patches, seed, codebook.count()).select("vec", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy("h", "clip_id", "patch_idx")).alias("k"))  # K rows
    new = dead.join(taken, "k").select("code", "vec")
    rows = codebook.join(F.broadcast(new), "code", "left")
    return rows.select("code", F.coalesce("vec", "centroid").alias("centroid"), F.when(F.col("vec").isNotNull(), 1.0).otherwise(F.col("ema_n")).alias("ema_n"), F.coalesce("vec", "ema_m").alias("ema_m"), "epoch")


def _drawn(patches: DataFrame, seed: int, most: int) -> DataFrame:
    """``most`` patches drawn by a hash, in its order."""
    h = F.md5(F.concat_ws("|", F.lit(str(seed)), F.col("clip_id").cast("string"), F.col("patch_idx").cast("string")))
    return patches.select(h.alias("h"), "clip_id", "patch_idx", "vec").orderBy("h", "clip_id", "patch_idx").limit(most)


def usage(assigned: DataFrame, codes: int, codebook: DataFrame | None = None, threshold: float = 0.0) -> DataFrame:
    """(usage): percent of the codes with a hit; with a codebook, of those whose moving count exceeds the threshold."""
    if codebook is not None:
        return codebook.agg((F.sum((F.col("ema_n") > threshold).cast("int")) / codes * 100).alias("usage"))
    return assigned.agg((F.count_distinct("code") / codes * 100).alias("usage"))


def code_entropy(assigned: DataFrame) -> DataFrame:
    """(entropy, perplexity) of the use of codes, natural logarithm."""
    counts = assigned.groupBy("code").agg(F.count("*").alias("c"))
    total = counts.agg(F.sum("c").alias("n"), F.sum(F.col("c") * F.log("c")).alias("s"))
    entropy = F.log("n") - F.col("s") / F.col("n")
    return total.select(entropy.alias("entropy"), F.exp(entropy).alias("perplexity"))


def commitment_loss(assigned: DataFrame) -> DataFrame:
    """(loss): mean over patches of the squared distance to their code.  The codebook loss has the same value; only the side
    that the gradient moves differs."""
    return assigned.agg(F.avg("dist2").alias("loss"))


codebook_loss = commitment_loss


def interjoint_distances(frames: DataFrame) -> DataFrame:
    """(clip_id, t, i, j, dist), i < j, between the joints of each frame."""
    pairs = F.flatten(F.transform("pose", lambda p, i: F.transform(F.slice("pose", i + 2, F.size("pose")), lambda q, k: F.struct(i.alias("i"), (i + k + 1).alias("j"), F.sqrt(squared_distance(p, q)).alias("dist")))))
    return frames.select("clip_id", "t", F.explode(pairs).alias("p")).where("p.dist is not null").select("clip_id", "t", "p.i", "p.j", "p.dist")


def interjoint_loss(x: DataFrame, y: DataFrame, p: int = 1) -> DataFrame:
    """(loss): mean difference (p = 1) or squared difference (p = 2) of all inter-joint distances of two pose tables.

    It does not change under rotation, translation or reflection of either pose.
    """
    def of(df: DataFrame, name: str) -> DataFrame:
        return interjoint_distances(df).withColumnRenamed("dist", name)

    both = of(x, "u").join(of(y, "v"), ["clip_id", "t", "i", "j"])
    gap = F.abs(F.col("u") - F.col("v"))
    return both.agg(F.avg(gap if p == 1 else gap * gap).alias("loss"))


def total_loss(reconstruction: float, commit: float, codebook: float, entropy: float, lam: float = 1.0, beta: float = 0.25, gamma: float = 0.01) -> float:
    return lam * reconstruction + commit + beta * codebook - gamma * entropy


def initial_codebook(patches: DataFrame, codes: int, seed: int = 7, collapsed: bool = False) -> DataFrame:
    """CODEBOOK of patches drawn by a hash; collapsed: all codes near the
    mean patch, in directions of no patch (reversed ones), so that a fit without revival never uses some."""
    h = F.md5(F.concat_ws("|", F.lit(f"start{seed}"), F.col("clip_id").cast("string"), F.col("patch_idx").cast("string")))
    top = patches.select(h.alias("h"), "clip_id", "patch_idx", "vec").orderBy("h", "clip_id", "patch_idx").limit(codes)
    w = Window.partitionBy(F.lit(0)).orderBy("h", "clip_id", "patch_idx")  # K rows
    rows = top.select((F.row_number().over(w) - 1).alias("code"), "vec")
    if collapsed:
        mean = patches.select(F.posexplode("vec").alias("i", "x")).groupBy("i").agg(F.avg("x").alias("x")).agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "x"))), lambda s: s["x"]).alias("mean"))
        rows = rows.crossJoin(mean).select("code", F.zip_with(F.reverse("vec"), "mean", lambda v, m: m + 0.01 * (v - m)).alias("vec"))  # a single row
    return rows.select(F.col("code").cast("int"), F.col("vec").alias("centroid"), F.lit(1.0).alias("ema_n"), F.col("vec").alias("ema_m"), F.lit(0).alias("epoch"))


def epoch_sums(patches: DataFrame, codebook: DataFrame, decimals: int = 9) -> DataFrame:
    """(code, hits, error, total): one epoch in one pass.  Every partition assigns its patches by matrix products and sums them by
    code; a partition's row for each code that it hit is all that is shuffled."""
    return _epoch(patches, *codebook_rows(codebook), decimals)


def _epoch(patches: DataFrame, numbers: np.ndarray, centroids: np.ndarray, decimals: int = 9) -> DataFrame:
    def run(batches):
        hits, error, total = np.zeros(len(numbers), np.int64), np.zeros(len(numbers)), np.zeros(centroids.shape)
        square = (centroids * centroids).sum(1)
        for batch in batches:
            if not batch.num_rows:
                continue
            x = np.stack(batch.column(0).to_numpy(zero_copy_only=False)).astype(float)
            d = np.round(np.maximum((x * x).sum(1)[:, None] - 2 * x @ centroids.T + square, 0), decimals)
            best = d.argmin(1)
            hits += np.bincount(best, minlength=len(numbers))
            error += np.bincount(best, weights=d[np.arange(len(d)), best], minlength=len(numbers))
            np.add.at(total, best, x)
        hit = np.flatnonzero(hits)
        yield pa.RecordBatch.from_arrays([pa.array(numbers[hit], pa.int32()), pa.array(hits[hit]), pa.array(error[hit]), pa.array(list(total[hit]), pa.list_(pa.float64()))], names=["code", "hits", "error", "total"])

    parts = patches.select("vec").mapInArrow(run, "code int, hits bigint, error double, total array<double>")

    def add(key: tuple, rows: pa.Table) -> pa.Table:
        total = np.stack(rows.column("total").to_numpy(zero_copy_only=False)).sum(0)
        return pa.table({"code": pa.array([key[0].as_py()], pa.int32()), "hits": [sum(rows.column("hits").to_pylist())], "error": [float(sum(rows.column("error").to_pylist()))], "total": pa.array([total.tolist()], pa.list_(pa.float64()))})

    return parts.groupBy("code").applyInArrow(add, "code int, hits bigint, error double, total array<double>")


def fit_codebook(patches: DataFrame, params: CodebookParams = CodebookParams(), start: DataFrame | None = None) -> tuple[DataFrame, list[dict]]:
    """(CODEBOOK, history): epochs of assignment, moving averages and revival.

    Each epoch is one pass over the patches (or a hashed share of them), which are kept between epochs; a second one draws
    patches for revival only if codes are dead.  What returns to the driver is K rows of a bounded length.
    """
    spark = patches.sparkSession
    own = not patches.storageLevel.useMemory
    if own:
        patches = patches.persist()
    book = sorted((start if start is not None else initial_codebook(patches, params.codes, params.seed)).collect())
    codes = np.array([r["code"] for r in book], np.int32)
    place = {int(c): i for i, c in enumerate(codes)}
    centroid, n, m = (np.array([r[c] for r in book], float) for c in ("centroid", "ema_n", "ema_m"))
    age, history = (book[0]["epoch"] if book else 0), []
    for epoch in range(params.epochs):
        batch = patches
        if params.batch_fraction < 1:
            draw = F.pmod(F.xxhash64(F.lit(params.seed), F.lit(epoch), "clip_id", "patch_idx"), F.lit(1_000_000))
            batch = patches.where(draw < int(params.batch_fraction * 1_000_000))
        sums = _epoch(batch, codes, centroid).collect()  # K rows at most
        hits, total = np.zeros(len(codes)), np.zeros(centroid.shape)
        for r in sums:
            hits[place[r["code"]]], total[place[r["code"]]] = r["hits"], r["total"]
        n, m = params.alpha * n + (1 - params.alpha) * hits, params.alpha * m + (1 - params.alpha) * total  # as ema_step
        centroid = m / np.maximum(n, params.eps)[:, None]
        dead = np.flatnonzero(hits == 0)
        if params.revive and len(dead):  # as revive
            taken = _drawn(batch, params.seed + epoch, len(dead)).select("vec").collect()
            dead = dead[: len(taken)]
            if len(dead):
                centroid[dead] = m[dead] = np.array([r["vec"] for r in taken], float)
                n[dead] = 1.0
        seen = float(hits.sum())
        history.append({"epoch": epoch, "usage": len(sums) / params.codes * 100, "error": sum(r["error"] for r in sums) / seen if seen else None})
    if own:
        patches.unpersist()
    rows = [(int(c), centroid[i].tolist(), float(n[i]), m[i].tolist(), age + params.epochs) for i, c in enumerate(codes)]
    return spark.createDataFrame(rows, CODEBOOK), history


def codebook_sweep(patches: DataFrame, base: CodebookParams = CodebookParams(), codes: tuple[int, ...] = (8, 16, 32, 64)) -> list[dict]:
    """The last line of the history for each number of codes, with and without revival."""
    return [{"codes": k, "revive": r, **fit_codebook(patches, replace(base, codes=k, revive=r))[1][-1]} for k in codes for r in (False, True)]


def quantiser_report(history: list[dict]) -> dict:
    return {"epochs": len(history), "first_usage": history[0]["usage"], "last_usage": history[-1]["usage"], "first_error": history[0]["error"], "last_error": history[-1]["error"]} if history else {}


def token_sequences(assigned: DataFrame) -> DataFrame:
    """SEQ of a clip's codes in the order of its patches."""
    from ..sources.tokens import as_sequences

    return as_sequences(assigned, "clip_id", [F.col("patch_idx")], F.col("code"))


def reconstruct(sequences: DataFrame, codebook: DataFrame) -> DataFrame:
    """PATCH of sequences of codes: each code's centroid."""
    rows = sequences.select(F.col("seq_id").alias("clip_id"), F.posexplode("tokens").alias("patch_idx", "code"))
    return rows.join(F.broadcast(codebook.select("code", F.col("centroid").alias("vec"))), "code").select("clip_id", "patch_idx", "vec")


def embedding_tokens(embeddings: DataFrame, codebook: DataFrame, frames: int = 20, length: int = 2) -> DataFrame:
    """SEQ of vectors read as latents: a clip is so many consecutive ids, a token the nearest code of a patch."""
    lat = embeddings.select(F.floor(F.col("vec_id") / frames).alias("clip_id"), (F.col("vec_id") % frames).cast("int").alias("t"), F.transform("embedding", lambda x: x.cast("double")).alias("latent"))
    return token_sequences(assign(patchify(lat, length), codebook, "arrow"))


def compression(assigned: DataFrame, width: int, length: int) -> DataFrame:
    """(patches, floats_before, tokens_after, tokens_per_frame)."""
    return assigned.agg(F.count("*").alias("patches")).select("patches", (F.col("patches") * width * length).alias("floats_before"), F.col("patches").alias("tokens_after"), F.lit(1 / length).alias("tokens_per_frame"))
