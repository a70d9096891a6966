"""The SQL surface: measures as functions, sequences and postings as views, alignment paths and segments as table functions."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import arrow_udf, udtf

from .config import MetricParams
from .functions import wavefront
from .functions.metrics import _arrays, batch_values
from .operators.histogram import word_counts


def _function(compute, kind: str):
    def apply(a: pa.Array, b: pa.Array) -> pa.Array:
        found = batch_values(lambda x, y, *_: {"v": compute(x, y)}, _arrays(a), _arrays(b), None, None, ["v"])["v"]
        return pa.array(found.astype(np.int32) if kind == "int" else found)

    apply.__annotations__ = {"a": pa.Array, "b": pa.Array, "return": pa.Array}
    return arrow_udf(apply, kind)


def functions(p: MetricParams = MetricParams()) -> dict:
    """name -> function of two token columns: distances and similarities."""
    sim = lambda m: lambda a, b: wavefront.similarities([m], a, b, p=p)[m]
    out = {
        "seq_lcss": _function(lambda a, b: wavefront.lcss(a, b, p), "int"),
        "seq_edr": _function(lambda a, b: wavefront.edr(a, b, p), "int"),
        "seq_erp": _function(lambda a, b: wavefront.erp(a, b, p), "double"),
        "seq_twed": _function(lambda a, b: wavefront.twed(a, b, p=p), "double"),
        "seq_dtw": _function(lambda a, b: wavefront.dtw(a, b, p), "double"),
        "seq_ngram": _function(sim("ngram"), "double"),
        "seq_hist": _function(sim("hist"), "double"),
    }
    return out | {f"{n}_sim": _function(sim(n[4:]), "double") for n in ("seq_lcss", "seq_edr", "seq_erp", "seq_twed")}


def alignment_path(a, b, metric: str = "edr", p: MetricParams = MetricParams()) -> list[tuple[int, int, int, str]]:
    """(step, i, j, op): one best alignment of two sequences, 1-based; op is match, replace, drop_a or drop_b.

    Ties go to the diagonal, then to the first sequence.  Memory is the whole matrix.
    """
    m, n = len(a), len(b)
    d = np.full((m + 1, n + 1), np.inf)
    d[0, 0] = 0

    def gap(x) -> float:
        return {"edr": 1.0, "lcss": 0.5, "erp": p.beta * abs(float(x) - p.gap)}[metric]

    def pair(x, y) -> float:
        same = abs(float(x) - float(y)) <= (p.edr_eps if metric == "edr" else p.lcss_eps)
        return {"edr": float(not same), "lcss": 0.0 if same else np.inf, "erp": abs(float(x) - float(y))}[metric]

    for i in range(m + 1):
        for j in range(n + 1):
            if i and j:
                d[i, j] = min(d[i, j], d[i - 1, j - 1] + pair(a[i - 1], b[j - 1]))
            if i:
                d[i, j] = min(d[i, j], d[i - 1, j] + gap(a[i - 1]))
            if j:
                d[i, j] = min(d[i, j], d[i, j - 1] + gap(b[j - 1]))
    out, i, j = [], m, n
    while i or j:
        if i and j and d[i, j] == d[i - 1, j - 1] + pair(a[i - 1], b[j - 1]):
            out.append((i, j, "match" if a[i - 1] == b[j - 1] else "replace"))
            i, j = i - 1, j - 1
        elif i and d[i, j] == d[i - 1, j] + gap(a[i - 1]):
            out.append((i, j, "drop_a"))
            i -= 1
        else:
            out.append((i, j, "drop_b"))
            j -= 1
    return [(k + 1, *x) for k, x in enumerate(reversed(out))]


class _AlignPath:
    def eval(self, a: list[int], b: list[int], metric: str):
        yield from alignment_path(a, b, metric)


class _Segments:
    def eval(self, tokens: list[int], window: int, hop: int):
        tokens = tokens or []
        last = max(0, len(tokens) - window)
        for start in sorted({*range(0, last + 1, hop), last}):
            yield start, tokens[start : start + window]


align_path = udtf(_AlignPath, returnType="step int, i int, j int, op string")
segments = udtf(_Segments, returnType="start int, tokens array<int>")


def register(spark: SparkSession, sequences: DataFrame | None = None, p: MetricParams = MetricParams()) -> None:
    """Install seq_* functions, align_path and segments, and, of given sequences, the views ``sequences`` and ``postings``."""
    for name, fn in functions(p).items():
        spark.udf.register(name, fn)
    spark.udtf.register("align_path", align_path)
    spark.udtf.register("segments", segments)
    if sequences is not None:
        sequences.createOrReplaceTempView("sequences")
        word_counts(sequences).createOrReplaceTempView("postings")


def all_similarities(df: DataFrame, a: str, b: str, p: MetricParams = MetricParams()) -> DataFrame:
    """``df`` with ``sims``: a struct of all similarities of two token columns, from one pass."""
    names = ["hist", "twed", "lcss", "edr", "erp", "ngram", "dtw"]

    def apply(x: pa.Array, y: pa.Array) -> pa.Array:
        got = batch_values(lambda u, v, *_: wavefront.similarities(names, u, v, p=p), _arrays(x), _arrays(y), None, None, names)
        return pa.StructArray.from_arrays([pa.array(got[n]) for n in names], names=names)

    apply.__annotations__ = {"x": pa.Array, "y": pa.Array, "return": pa.Array}
    kind = "struct<" + ",".join(f"{n}:double" for n in names) + ">"
    return df.withColumn("sims", arrow_udf(apply, kind)(F.col(a), F.col(b)))
