"""Fitting the whole quantiser: gradients on the executors, Adam and moving averages on the driver."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark import RDD, inheritable_thread_target
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import CodebookParams, ModelParams
from ..functions.autodiff import Node
from .encoder import Weights, clip_loss, clips, init_weights, tensor


def clip_by_norm(g: np.ndarray, most: float) -> np.ndarray:
    n = float(np.sqrt((g * g).sum()))
    return g * (most / n) if n > most else g


@dataclass
class Adam:
    rate: float = 1e-4
    beta1: float = 0.9
    beta2: float = 0.999
    eps: float = 1e-8
    step: int = 0
    m: np.ndarray | float = 0.0
    v: np.ndarray | float = 0.0

    def move(self, w: np.ndarray, g: np.ndarray) -> np.ndarray:
        self.step += 1
        self.m = self.beta1 * self.m + (1 - self.beta1) * g
        self.v = self.beta2 * self.v + (1 - self.beta2) * g * g
        return w - self.rate * (self.m / (1 - self.beta1**self.step)) / (np.sqrt(self.v / (1 - self.beta2**self.step)) + self.eps)


def pack(w: Weights) -> np.ndarray:
    return np.concatenate([w[k].ravel() for k in sorted(w)])


def unpack(flat: np.ndarray, like: Weights) -> Weights:
    out, at = {}, 0
    for k in sorted(like):
        out[k] = flat[at : at + like[k].size].reshape(like[k].shape)
        at += like[k].size
    return out


@dataclass
class Fitted:
    weights: Weights
    codes: np.ndarray
    history: list[dict]


def _by_step(rows: DataFrame, seed: int, steps: int) -> tuple[RDD, dict[int, list[int]], DataFrame]:
    """(the clips of an epoch; the partitions that have those of each step; what is kept, to be let go after the epoch).

    Clips of a step are in one partition, so a step is one small task, which reads a few steps' clips and not the whole table."""

    def pack(batches):
        for b in batches:
            values = [np.asarray(v, float).tobytes() for v in b.column(3).to_numpy(zero_copy_only=False)]
            yield pa.RecordBatch.from_arrays([*(b.column(k) for k in range(3)), pa.array(values, pa.binary())], names=["step", "clip_id", "n", "frames"])

    step = F.pmod(F.xxhash64(F.lit(seed), "clip_id"), F.lit(steps)).cast("int")
    parts = min(steps, max(2 * rows.sparkSession.sparkContext.defaultParallelism, steps // 8))
    dealt = rows.select(step.alias("step"), "clip_id", "n", "frames").repartition(parts, "step")
    kind = dict(rows.dtypes)["clip_id"]
    kept = dealt.mapInArrow(pack, f"step int, clip_id {kind}, n int, frames binary").persist()
    rdd = kept.rdd
    places: dict[int, list[int]] = {}
    for at, s in rdd.mapPartitionsWithIndex(lambda at, it: [(at, s) for s in {r[0] for r in it}]).collect():  # a pair a step
        places.setdefault(s, []).append(at)
    return rdd, places, kept


def _sums(clip_rows: RDD, step: int, at: list[int], weights: Weights, codes: np.ndarray | None, p: ModelParams, share: float, commit: float, n_codes: int, width: int) -> np.ndarray:
    """One vector: gradient, then rec, commit, entropy, total, clips; then hits and sums of the codes; then the patch of the
    smallest hash for revival is asked for apart.  Executors add their clips, in order of the ids."""

    def run(it):
        w = {k: Node(v) for k, v in weights.items()}
        total = None
        for _, _, n, values in sorted((r for r in it if r[0] == step), key=lambda r: r[1]):
            for node in w.values():
                node.grad = None
            if n < p.patch:
                continue
            loss, parts, hit, patches = clip_loss(tensor(np.frombuffer(values), n, p), w, codes, p, share, commit)
            loss.backward()
            g = np.concatenate([(w[k].grad if w[k].grad is not None else np.zeros_like(w[k].value)).ravel() for k in sorted(w)])
            counts, sums = np.zeros(n_codes), np.zeros((n_codes, width))
            np.add.at(counts, hit, 1)
            np.add.at(sums, hit, patches if len(hit) else patches[:0])
            row = np.concatenate([g, [parts["rec"], parts["commit"], parts["entropy"], parts["total"], 1.0], counts, sums.ravel()])
            total = row if total is None else total + row
        return [] if total is None else [total]

    size = sum(v.size for v in weights.values()) + 5 + n_codes * (1 + width)
    return sum(clip_rows.context.runJob(clip_rows, run, at), np.zeros(size))


def _some_patches(clip_rows: DataFrame, weights: Weights, p: ModelParams, n: int, seed: int) -> np.ndarray:
    """About n latent patches, drawn by a hash of the clip: the codebook's start, and what revives codes."""
    from .encoder import encode_clip, to_patches

    def run(batches):
        w = {k: Node(v) for k, v in weights.items()}
        for b in batches:
            rows = []
            for m, values in zip(b.column(1).to_pylist(), b.column(2).to_numpy(zero_copy_only=False), strict=True):
                rows += list(to_patches(encode_clip(tensor(values, m, p), w, p), p).value)
            yield pa.RecordBatch.from_arrays([pa.array(rows, pa.list_(pa.float64()))], names=["vec"])

    chosen = clip_rows.where(F.col("n") >= p.patch).orderBy(F.xxhash64(F.lit(seed), "clip_id"), "clip_id").limit(n)
    rows = chosen.mapInArrow(run, "vec array<double>").limit(4 * n).collect()
    x = np.array([r["vec"] for r in rows], float)
    return x[np.random.default_rng(seed).permutation(len(x))[:n]]


def _measured(clip_rows: DataFrame, weights: Weights, codes: np.ndarray | None, p: ModelParams) -> tuple[np.ndarray, np.ndarray]:
    """(rec, commit, entropy, total, clips; hits of each code) of a model over all clips: one forward pass, a row a partition."""
    k = 0 if codes is None else len(codes)

    def run(batches):
        w, found = {name: Node(v) for name, v in weights.items()}, []
        for b in batches:
            for clip, n, values in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_numpy(zero_copy_only=False), strict=True):
                if n >= p.patch:
                    _, parts, hit, _ = clip_loss(tensor(values, n, p), w, codes, p)
                    found.append((clip, np.concatenate([[parts["rec"], parts["commit"], parts["entropy"], parts["total"], 1.0], np.bincount(hit, minlength=k)[:k]])))
        if found:
            yield pa.RecordBatch.from_arrays([pa.array([sum(row for _, row in sorted(found, key=lambda f: f[0]))], pa.list_(pa.float64()))], names=["sums"])

    total = np.zeros(5 + k)
    for r in clip_rows.select("clip_id", "n", "frames").mapInArrow(run, "sums array<double>").collect():
        total = total + np.array(r["sums"])
    return total[:5], total[5:]


def _line(epoch: int, report: np.ndarray, hits: np.ndarray) -> dict:
    """A line of the history, from sums over clips and the hits of the codes."""
    seen = max(1.0, report[4])
    return {"epoch": epoch, "rec": report[0] / seen, "commit": report[1] / seen, "entropy": report[2] / seen, "total": report[3] / seen, "usage": 100 * float((hits > 0).mean()) if len(hits) else 0.0}


def fit(frames: DataFrame, p: ModelParams = ModelParams(), seed: int = 7) -> Fitted:
    """Warm-up epochs without the bottleneck (or, ramp, with a growing share of it), then epochs with it: each step takes a
    hashed part of the clips of about ``batch`` clips, moves the weights by Adam, and the codes by moving averages and revival.
    The last line of the history is what the fitted model, with the codes that the last epoch revived, gives over all clips."""
    rows = clips(frames).persist()
    try:
        return fit_clips(rows, p, seed)
    finally:
        rows.unpersist()


def fit_clips(rows: DataFrame, p: ModelParams = ModelParams(), seed: int = 7) -> Fitted:
    """The same over the rows of :func:`clips`, which are read in every step and so better kept."""
    n = rows.count()
    steps = max(1, n // p.batch)
    weights = init_weights(p, seed)
    width = p.patch * p.joints * p.dim
    k = p.codebook.codes
    codes: np.ndarray | None = None
    ema_n = ema_m = np.zeros(0)
    adam, history = Adam(p.learning_rate), []
    size = sum(v.size for v in weights.values())
    for epoch in range(p.epochs):
        warm = epoch < p.warmup_epochs
        if codes is None and (not warm or p.ramp):
            start = _some_patches(rows, weights, p, k, seed)
            codes = np.vstack([start] * (k // max(1, len(start)) + 1))[:k]
            ema_n, ema_m = np.ones(k), codes.copy()
        share = (epoch + 1) / (p.warmup_epochs + 1) if warm and p.ramp else 1.0
        epoch_hits, report = np.zeros(k), np.zeros(5)
        dealt, places, kept = _by_step(rows, seed + epoch, steps)
        for step in sorted(places):
            commit = 1.0 if p.commit_schedule == "const" or not epoch_hits.any() else float((epoch_hits > 0).mean())
            got = _sums(dealt, step, places[step], weights, codes, p, share, commit, k, width)
            clips_seen = got[size + 4]
            if not clips_seen:
                continue
            report += got[size : size + 5]
            flat = adam.move(pack(weights), clip_by_norm(got[:size] / clips_seen, p.clip))
            weights = unpack(flat, weights)
            if codes is not None and not (warm and not p.ramp):
                hits, sums = got[size + 5 : size + 5 + k], got[size + 5 + k :].reshape(k, width)
                a = p.codebook.alpha
                ema_n, ema_m = a * ema_n + (1 - a) * hits, a * ema_m + (1 - a) * sums
                codes = ema_m / np.maximum(ema_n, p.codebook.eps)[:, None]
                epoch_hits += hits
        kept.unpersist()
        if codes is not None and p.codebook.revive and (dead := np.nonzero(epoch_hits == 0)[0]).size:
            new = _some_patches(rows, weights, p, len(dead), seed + epoch + 1)
            dead = dead[: len(new)]
            codes[dead], ema_m[dead], ema_n[dead] = new[: len(dead)], new[: len(dead)], 1.0
        history.append(_line(epoch, report, epoch_hits))
    if history:  # no epoch follows the last, so its own sums don't show what its revival did
        history[-1] = _line(p.epochs - 1, *_measured(rows, weights, codes, p))
    return Fitted(weights, codes if codes is not None else np.zeros((0, width)), history)


def ablate(frames: DataFrame, base: ModelParams = ModelParams(), grid: dict[str, ModelParams] | None = None) -> list[dict]:
    """The last line of the history of each variant: no revival, no warm-up, other decay, more codes, branches in sequence."""
    c: CodebookParams = base.codebook
    grid = grid or {
        "base": base,
        "no_revival": replace(base, codebook=replace(c, revive=False)),
        "no_warmup": replace(base, warmup_epochs=0),
        "ramp": replace(base, ramp=True),
        "slow_average": replace(base, codebook=replace(c, alpha=0.99)),
        "twice_the_codes": replace(base, codebook=replace(c, codes=2 * c.codes)),
        "low_reconstruction": replace(base, lam=0.1),
        "sequential": replace(base, sequential=True),
    }
    # a step is a job of few clips that leaves most cores idle, and the variants don't depend on each other
    rows = clips(frames).persist()
    with ThreadPoolExecutor(len(grid)) as pool:
        fits = {k: pool.submit(inheritable_thread_target(rows.sparkSession)(fit_clips), rows, p) for k, p in grid.items()}
    rows.unpersist()
    return [{"variant": k, **f.result().history[-1]} for k, f in fits.items()]
