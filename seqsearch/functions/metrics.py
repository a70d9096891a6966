"""Similarities of pairs as columns: one Arrow pass for all measures, or native expressions; and metrics of users."""

from __future__ import annotations

from collections.abc import Callable, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import WEIGHTS, MetricParams, check_weights
from . import native, wavefront

#: name -> Column function of (a, b, ta, tb); see register_metric.
USER_METRICS: dict[str, Callable[..., Column]] = {}
#: Pairs that one sweep takes; longer sequences take fewer.
SWEEP_CELLS = 1 << 14


def register_metric(name: str, fn: Callable[..., Column]) -> None:
    """A similarity of one's own, in [0, 1], to be weighted like the others; ``fn`` gets the columns a, b, ta, tb."""
    USER_METRICS[name] = fn


def attach_tokens(pairs: DataFrame, queries: DataFrame, base: DataFrame, strategy: str = "auto") -> DataFrame:
    """Pairs with the token arrays a, b and times ta, tb.  strategy: auto, broadcast, merge, shuffle_hash.

    A few bytes of ids stand for much work, so pairs are dealt out by number first, not by size.
    """
    pairs = pairs.repartition(max(2 * pairs.sparkSession.sparkContext.defaultParallelism, int(pairs.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    hint = {"auto": None, "broadcast": "broadcast", "merge": "merge", "shuffle_hash": "shuffle_hash"}[strategy]
    q = queries.select(F.col("seq_id").alias("query_id"), F.col("tokens").alias("a"), F.col("times").alias("ta"))
    s = base.select(F.col("seq_id").alias("cand_id"), F.col("tokens").alias("b"), F.col("times").alias("tb"))
    if hint:
        q, s = q.hint(hint), s.hint(hint)
    return pairs.join(q, "query_id").join(s, "cand_id")


def _batches(m: np.ndarray, n: np.ndarray) -> list[np.ndarray]:
    """Row numbers in groups of like length, so that padding is small and a sweep stays in the cache."""
    order = np.argsort(m + n, kind="stable")
    out, at = [], 0
    while at < len(order):
        size = max(1, SWEEP_CELLS // max(1, int(m[order[at]] + 1)))
        group = order[at : at + size]
        while len(group) > 1 and m[group].max() > 2 * max(8, m[group[0]]):
            group = group[: len(group) // 2]
        out.append(group)
        at += len(group)
    return out


def _arrays(column: pa.ChunkedArray | pa.Array) -> list:
    return [np.zeros(0) if v is None else v for v in column.to_numpy(zero_copy_only=False)]


def batch_values(compute: Callable[..., dict[str, np.ndarray]], a, b, ta, tb, names: Sequence[str]) -> dict[str, np.ndarray]:
    """Run ``compute`` on the pairs in groups of like length."""
    m = np.fromiter(map(len, a), np.int64, len(a))
    n = np.fromiter(map(len, b), np.int64, len(b))
    out = {k: np.zeros(len(a)) for k in names}
    for g in _batches(m, n):
        pick = lambda rows: None if rows is None else [rows[i] for i in g]
        for k, v in compute(pick(a), pick(b), pick(ta), pick(tb)).items():
            out[k][g] = v
    return out


def batch_similarities(names: Sequence[str], a, b, ta, tb, params: MetricParams) -> dict[str, np.ndarray]:
    """The named similarities of the pairs: by the faster forms where they are exact, the others in groups of like length."""
    found = {k: v for k in names if (k != "twed" or ta is None) and (v := wavefront.quick_similarity(k, a, b, params)) is not None}
    rest = [k for k in names if k not in found]
    return found | (batch_values(lambda *r: wavefront.similarities(rest, *r, params), a, b, ta, tb, rest) if rest else {})


def _arrow(pairs: DataFrame, compute, names: Sequence[str], timed: bool, grouped: bool = True) -> DataFrame:
    """Append the columns ``names`` computed from a, b and, if ``timed``, ta, tb; not ``grouped``: of pairs of any lengths at once."""
    keep = [c for c in pairs.columns if c not in ("a", "b", "ta", "tb")]
    kinds = {f.name: f.dataType.simpleString() for f in pairs.schema}
    ddl = ", ".join([f"`{c}` {kinds[c]}" for c in keep] + [f"`{n}` double" for n in names])

    def run(batches):
        for batch in batches:
            at = {k: i for i, k in enumerate(batch.schema.names)}
            a, b = _arrays(batch.column(at["a"])), _arrays(batch.column(at["b"]))
            ta, tb = (_arrays(batch.column(at["ta"])), _arrays(batch.column(at["tb"]))) if timed else (None, None)
            found = batch_values(compute, a, b, ta, tb, names) if grouped else compute(a, b, ta, tb)
            yield pa.RecordBatch.from_arrays([*(batch.column(at[c]) for c in keep), *(pa.array(found[n]) for n in names)], names=[*keep, *names])

    return pairs.mapInArrow(run, ddl)


def pair_metric(pairs: DataFrame, metrics: Sequence[str], params: MetricParams = MetricParams(), how: str = "arrow", timed: bool = False) -> DataFrame:
    """Pairs (with a, b, ta, tb) to pairs with ``s_<metric>`` for each similarity; the arrays go."""
    own = [m for m in metrics if m in USER_METRICS]
    known = [m for m in metrics if m not in USER_METRICS]
    for m in own:
        pairs = pairs.withColumn(f"s_{m}", USER_METRICS[m](F.col("a"), F.col("b"), F.col("ta"), F.col("tb")))
    if how == "arrow":

        def compute(a, b, ta, tb):
            return {f"s_{k}": v for k, v in batch_similarities(known, a, b, ta, tb, params).items()}

        return _arrow(pairs, compute, [f"s_{m}" for m in known], timed, grouped=False)
    m, n = F.size("a"), F.size("b")
    mean, none = (m + n) / 2, (m + n) == 0
    times = ("ta", "tb") if timed else (None, None)
    made = {
        "twed": lambda: F.when(none, 1.0).when((m == 0) | (n == 0), 0.0).otherwise(F.exp(-native.twed("a", "b", *times, params) / (2 * mean))),
        "lcss": lambda: F.when(none, 1.0).otherwise(native.lcss("a", "b", params) / mean),
        "edr": lambda: F.when(none, 1.0).otherwise(1 - native.edr("a", "b", params) / F.greatest(m, n)),
        "erp": lambda: F.when(none, 1.0).otherwise(F.exp(-native.erp("a", "b", params) / mean)),
        "dtw": lambda: F.when(none, 1.0).otherwise(F.coalesce(1 - native.dtw("a", "b", params) / (m + n), F.lit(0.0))),
        "ngram": lambda: native.gram_similarity("a", "b", params.ngram, params.ngram_kind),
        "hist": lambda: native.gram_similarity("a", "b", 1, "cosine"),
    }
    return pairs.select("*", *[made[k]().alias(f"s_{k}") for k in known]).drop("a", "b", "ta", "tb")


def pair_distance(pairs: DataFrame, metric: str, params: MetricParams = MetricParams(), how: str = "arrow", timed: bool = False) -> DataFrame:
    """Pairs with ``value``: the distance (or, for lcss, the length) itself; infinity becomes null."""
    if how == "native":
        times = ("ta", "tb") if timed else (None, None)
        value = native.twed("a", "b", *times, params) if metric == "twed" else getattr(native, metric)("a", "b", params)
        return pairs.withColumn("value", value.cast("double")).drop("a", "b", "ta", "tb")

    def compute(a, b, ta, tb):
        return {"value": wavefront.twed(a, b, ta, tb, params) if metric == "twed" else getattr(wavefront, metric)(a, b, params)}

    out = _arrow(pairs, compute, ["value"], timed)
    return out.withColumn("value", F.when(F.abs("value") < float("inf"), F.col("value")))


def combine(scored: DataFrame, weights: dict[str, float] = WEIGHTS) -> DataFrame:
    """``score``: the convex mix of the ``s_`` columns, added in the order of the weights."""
    total: Column | None = None
    for k, w in check_weights(weights).items():
        term = F.lit(w) * F.col(f"s_{k}")
        total = term if total is None else total + term
    return scored.withColumn("score", total)
