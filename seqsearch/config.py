"""Defaults, in one place.  Values that the published description fixes are marked; the others are ours."""

from __future__ import annotations

from dataclasses import dataclass, field

#: The weights of the six similarities; they add to one.
WEIGHTS = {"hist": 0.30, "twed": 0.15, "lcss": 0.15, "edr": 0.15, "erp": 0.10, "ngram": 0.15}
#: What a first match at rank 1, 2, 3 counts.
RANK_DECAY = (1.0, 0.5, 0.25)
#: Vocabulary of the retriever, results a query, references a class in the large experiment.
VOCABULARY, TOP_K, LARGE_REFERENCES = 512, 3, 10
#: Largest shortlist, periodicity threshold and peaks.
SHORTLIST_CAP, PERIODIC_THETA, PERIODIC_PEAKS = 200, 0.6, 2
#: Frames a second of the clips; codebook use that a healthy codebook exceeds, in percent.
FRAME_RATE, HEALTHY_USAGE = 30, 80.0


@dataclass(frozen=True)
class MetricParams:
    nu: float = 0.125  # stiffness; dyadic, so that sums are exact
    lam: float = 1.0  # price of a one-sided move
    twed: str = "printed"  # or "original"
    twed_cost: str = "discrete"  # or "abs"
    lcss_eps: float = 0.0  # fixed
    lcss_delta: int | None = None  # fixed: no window
    edr_eps: float = 0.0  # fixed
    gap: float = 0.0  # fixed
    beta: float = 0.5  # fixed
    dtw_cost: str = "discrete"  # fixed; or "abs"
    dtw_band: int | None = None
    ngram: int = 2
    ngram_kind: str = "cosine"


@dataclass(frozen=True)
class CodebookParams:
    codes: int = 64
    alpha: float = 0.5  # fixed
    eps: float = 1e-5
    epochs: int = 10
    revive: bool = True
    seed: int = 7
    batch_fraction: float = 1.0


@dataclass(frozen=True)
class ModelParams:
    joints: int = 16
    coords: int = 4
    dim: int = 4
    patch: int = 2
    heads: int = 2
    blocks: int = 1
    combine: str = "sum"  # or "mean", "concat"
    sequential: bool = False  # an ablation: the spatial branch reads the temporal one's output
    lam: float = 1.0  # fixed
    beta: float = 0.25
    gamma: float = 0.01
    learning_rate: float = 1e-4  # fixed
    clip: float = 1.0  # fixed
    batch: int = 16  # fixed
    warmup_epochs: int = 2
    epochs: int = 6
    ramp: bool = False
    commit_schedule: str = "const"  # or "balanced": scaled by the codebook's use (our reading)
    codebook_attention: bool = False  # our reading: latents attend to the codes before they are cut
    codebook: CodebookParams = field(default_factory=CodebookParams)


def check_weights(weights: dict[str, float]) -> dict[str, float]:
    """The weights of a convex mix, without zeros."""
    if any(w < 0 for w in weights.values()) or abs(sum(weights.values()) - 1) > 1e-9:
        raise ValueError("weights must not be negative and must add to one")
    return {k: w for k, w in weights.items() if w}


def weight_presets() -> dict[str, dict[str, float]]:
    """Default, each similarity alone, each left out, equal parts, alignment only, and one with dynamic time warping."""
    names = list(WEIGHTS)
    out = {"default": dict(WEIGHTS)}
    for k in names:
        out[f"only_{k}"] = {k: 1.0}
        rest = 1 - WEIGHTS[k]
        out[f"without_{k}"] = {j: w / rest for j, w in WEIGHTS.items() if j != k}
    out["equal"] = {k: 1 / len(names) for k in names}
    out["alignment"] = {k: 0.25 for k in ("twed", "lcss", "edr", "erp")}
    out["with_dtw"] = {**{k: 0.9 * w for k, w in WEIGHTS.items()}, "dtw": 0.1}
    return out
