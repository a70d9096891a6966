"""The dual-branch pose transformer around the quantiser, in NumPy, and its use on tables of clips.

A clip is (T, V, C).  Each joint has its own projection to D numbers.  A temporal branch attends over the frames of each
joint, a spatial branch over the joints of each frame; both read the same input, and what they give is combined.  A per-joint
feed-forward layer and a normalisation follow.  The decoder has the same shape and ends in per-joint projections to C numbers.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import ModelParams
from ..functions.autodiff import Node, concat, straight_through

Weights = dict[str, np.ndarray]


def init_weights(p: ModelParams, seed: int = 7) -> Weights:
    rng = np.random.default_rng(seed)

    def w(*shape: int) -> np.ndarray:
        return rng.standard_normal(shape) / np.sqrt(shape[-2])

    out: Weights = {}
    d = p.dim
    for side, (a, b) in (("enc", (p.coords, d)), ("dec", (d, p.coords))):
        out[f"{side}.joint"] = w(p.joints, a, b)
        out[f"{side}.joint_b"] = np.zeros((p.joints, 1, b))
        for k in range(p.blocks):
            for branch in ("time", "space"):
                for m in ("q", "k", "v", "o"):
                    out[f"{side}.{k}.{branch}.{m}"] = w(d, d)
            if p.combine == "concat":
                out[f"{side}.{k}.mix"] = w(2 * d, d)
            out[f"{side}.{k}.ffn1"] = w(p.joints, d, 2 * d)
            out[f"{side}.{k}.ffn2"] = w(p.joints, 2 * d, d)
    return out


def attention(x: Node, w: dict[str, Node], name: str, heads: int) -> Node:
    """Multi-head self-attention over the middle axis of (batch, items, D)."""
    b, n, d = x.value.shape
    h = d // heads

    def split(m: str) -> Node:
        return (x @ w[f"{name}.{m}"]).reshape(b, n, heads, h).transpose(0, 2, 1, 3)

    q, k, v = split("q"), split("k"), split("v")
    weights = ((q @ k.transpose(0, 1, 3, 2)) * (1 / np.sqrt(h))).softmax()
    return (weights @ v).transpose(0, 2, 1, 3).reshape(b, n, d) @ w[f"{name}.o"]


def block(z: Node, w: dict[str, Node], name: str, p: ModelParams) -> Node:
    """One dual-branch block on (V, T, D)."""
    time = attention(z, w, f"{name}.time", p.heads)
    into = time if p.sequential else z
    space = attention(into.transpose(1, 0, 2), w, f"{name}.space", p.heads).transpose(1, 0, 2)
    if p.sequential:
        mixed = space
    elif p.combine == "concat":
        mixed = concat(time, space) @ w[f"{name}.mix"]
    else:
        mixed = (time + space) * (0.5 if p.combine == "mean" else 1.0)
    z = (z + mixed).normalised()
    return (z + (z @ w[f"{name}.ffn1"]).relu() @ w[f"{name}.ffn2"]).normalised()


def encode_clip(x: np.ndarray, w: dict[str, Node], p: ModelParams) -> Node:
    """(T, V, C) to latents (V, T, D)."""
    z = Node(x.transpose(1, 0, 2)) @ w["enc.joint"] + w["enc.joint_b"]
    for k in range(p.blocks):
        z = block(z, w, f"enc.{k}", p)
    return z


def decode_clip(z: Node, w: dict[str, Node], p: ModelParams) -> Node:
    """Latents (V, T, D) to poses (V, T, C)."""
    for k in range(p.blocks):
        z = block(z, w, f"dec.{k}", p)
    return z @ w["dec.joint"] + w["dec.joint_b"]


def to_patches(z: Node, p: ModelParams) -> Node:
    """(V, T, D) to (T / P, P * V * D), frame by frame, joints in order; a short tail is not quantised."""
    v, t, d = z.value.shape
    n = t // p.patch
    flat = z.transpose(1, 0, 2).reshape(t, v * d)
    if n * p.patch < t:
        whole = flat
        flat = Node(whole.value[: n * p.patch], ((whole, lambda g: np.vstack([g, np.zeros((t - n * p.patch, v * d))])),))
    return flat.reshape(n, p.patch * v * d)


def from_patches(q: Node, p: ModelParams, joints: int) -> Node:
    n, size = q.value.shape
    return q.reshape(n * p.patch, joints, size // (p.patch * joints)).transpose(1, 0, 2)


def attend_codes(patches: Node, codes: np.ndarray) -> Node:
    """Our reading of codebook-aware attention: patches plus what they attend to among the codes."""
    scale = 1 / np.sqrt(codes.shape[1])
    return (patches + (patches @ Node(codes.T) * scale).softmax() @ Node(codes)) * 0.5


def nearest(patches: np.ndarray, codes: np.ndarray) -> np.ndarray:
    d = (patches**2).sum(1)[:, None] - 2 * patches @ codes.T + (codes**2).sum(1)
    return np.round(d, 9).argmin(1)


def interjoint(x: Node) -> Node:
    """(V, T, C) to all distances between joints, (T, V, V)."""
    t = x.transpose(1, 0, 2)
    n, v, c = t.value.shape
    return (t.reshape(n, v, 1, c) - t.reshape(n, 1, v, c)).lengths()


def clip_loss(x: np.ndarray, w: dict[str, Node], codes: np.ndarray | None, p: ModelParams, share: float = 1.0, commit_weight: float = 1.0):
    """(loss node, parts, code of each patch, patches).

    ``codes`` None: the bottleneck is bypassed (warm-up).  ``share`` below 1 mixes quantised and plain patches (ramp).
    """
    z = encode_clip(x, w, p)
    patches = to_patches(z, p)
    if p.codebook_attention and codes is not None:
        patches = attend_codes(patches, codes)
    commit = Node(0.0)
    hit = np.zeros(0, int)
    through = patches
    if codes is not None:
        hit = nearest(patches.value, codes)
        q = codes[hit]
        gap = patches - Node(q)
        commit = (gap * gap).mean() * float(patches.value.shape[1])
        through = straight_through(patches, q * share + patches.value * (1 - share))
    shown = decode_clip(from_patches(through, p, x.shape[1]), w, p)
    used = x[: shown.value.shape[1]]
    rec = (interjoint(shown) - interjoint(Node(used.transpose(1, 0, 2)))).abs().mean()
    counts = np.bincount(hit) if len(hit) else np.zeros(0)
    share_of = counts[counts > 0] / max(1, counts.sum())
    entropy = float(-(share_of * np.log(share_of)).sum()) if len(share_of) else 0.0
    # the codebook term has the value of the commitment, and moves the codes only, which moving averages do here
    loss = rec * p.lam + commit * commit_weight
    parts = {"rec": float(rec.value), "commit": float(commit.value), "entropy": entropy, "total": float(rec.value) * p.lam + float(commit.value) * (1 + p.beta) - p.gamma * entropy}
    return loss, parts, hit, patches.value


def clips(frames: DataFrame) -> DataFrame:
    """FRAME to one row for each clip: (clip_id, n, frames: the poses in order, flat).  The only shuffle."""
    rows = frames.groupBy("clip_id").agg(F.array_sort(F.collect_list(F.struct("t", "pose"))).alias("f"))
    flat = F.flatten(F.transform("f", lambda x: F.flatten(x["pose"])))
    return rows.select("clip_id", F.size("f").alias("n"), F.transform(flat, lambda x: x.cast("double")).alias("frames"))


def tensor(values, n: int, p: ModelParams) -> np.ndarray:
    return np.asarray(values, float).reshape(n, p.joints, p.coords)


def _rows(batch: pa.RecordBatch, p: ModelParams):
    for clip, n, values in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).to_numpy(zero_copy_only=False), strict=True):
        yield clip, tensor(values, n, p)


def encode(frames: DataFrame, weights: Weights, p: ModelParams = ModelParams()) -> DataFrame:
    """FRAME to LATENT; one clip is one row of work."""

    def run(batches):
        w = {k: Node(v) for k, v in weights.items()}
        for batch in batches:
            out = {"clip_id": [], "t": [], "latent": []}
            for clip, x in _rows(batch, p):
                z = encode_clip(x, w, p).value.transpose(1, 0, 2).reshape(len(x), -1)
                out["clip_id"] += [clip] * len(x)
                out["t"] += range(len(x))
                out["latent"] += list(z)
            yield pa.RecordBatch.from_arrays([pa.array(out["clip_id"], pa.int64()), pa.array(out["t"], pa.int32()), pa.array(out["latent"], pa.list_(pa.float64()))], names=list(out))

    return clips(frames).mapInArrow(run, "clip_id bigint, t int, latent array<double>")


def tokenize(frames: DataFrame, weights: Weights, codes: np.ndarray, p: ModelParams = ModelParams()) -> DataFrame:
    """FRAME to (clip_id, tokens): encoder, patches and nearest codes in one pass."""

    def run(batches):
        w = {k: Node(v) for k, v in weights.items()}
        for batch in batches:
            rows = list(_rows(batch, p))
            tokens = []
            for _, x in rows:
                patches = to_patches(encode_clip(x, w, p), p)
                if p.codebook_attention:
                    patches = attend_codes(patches, codes)
                tokens.append(nearest(patches.value, codes).astype(np.int32))
            yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int64()), pa.array(tokens, pa.list_(pa.int32()))], names=["clip_id", "tokens"])

    return clips(frames).mapInArrow(run, "clip_id bigint, tokens array<int>")


def decode(tokens: DataFrame, weights: Weights, codes: np.ndarray, p: ModelParams = ModelParams()) -> DataFrame:
    """(clip_id, tokens) to FRAME: codes to latents to poses."""

    def run(batches):
        w = {k: Node(v) for k, v in weights.items()}
        for batch in batches:
            out = {"clip_id": [], "t": [], "pose": []}
            for clip, row in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if not row:
                    continue
                x = decode_clip(from_patches(Node(codes[np.array(row)]), p, p.joints), w, p).value.transpose(1, 0, 2)
                out["clip_id"] += [clip] * len(x)
                out["t"] += range(len(x))
                out["pose"] += x.tolist()
            yield pa.RecordBatch.from_arrays([pa.array(out["clip_id"], pa.int64()), pa.array(out["t"], pa.int32()), pa.array(out["pose"], pa.list_(pa.list_(pa.float64())))], names=list(out))

    return tokens.select("clip_id", "tokens").mapInArrow(run, "clip_id bigint, t int, pose array<array<double>>")
