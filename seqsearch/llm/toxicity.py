"""Toxicity by compression distance.

Two zstandard dictionaries are made from labelled text: an ordinary one, trained on windows of ordinary texts, and a toxic
one, which holds the ordinary content and after it, so with the shortest distances, the segments that are typical of toxic
texts.  Every text is cut into short overlapping windows; each is compressed with both.  Where the toxic dictionary saves
bytes, the window holds toxic segments.  A text's largest savings are turned into a probability by a logistic curve that is
calibrated on labelled texts which neither dictionary has seen.

The typical segments are words, and the stems that they share, that stand in many *different* places of toxic texts (distinct
pairs with the word before) and in few of ordinary ones; counting places rather than texts keeps copied texts from making
their words typical.  How typical they must be is chosen by cross-fitting.
"""

from __future__ import annotations

import itertools
import pickle
import re
from collections import Counter
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import held_out, pieces_of, text_function, worker_cache

_NOT_LETTERS = bytes(c if c >= 128 or 97 <= c <= 122 else 32 for c in range(256))
_WORD = re.compile(r"[^\W\d_]+")
#: Word places that wait until they are made distinct.
_WAITING = 1_000_000


@dataclass(frozen=True)
class ToxicityModel:
    ordinary: bytes
    toxic: bytes
    weights: tuple[float, ...]  # of the features, the last is the constant
    window: int = 48
    step: int = 32
    level: int = 3
    segments: tuple[str, ...] = field(default=(), compare=False)


def normal_bytes(text: str | None) -> bytes:
    """Lower case, every ASCII character but letters a blank, runs of blanks one."""
    words = (text or "").lower().encode("utf-8", "surrogatepass").translate(_NOT_LETTERS).split()
    return b" %b " % b" ".join(words) if words else b""


def _compressor(content: bytes, level: int) -> zstandard.ZstdCompressor:
    zd = zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
    zd.precompute_compress(level=level)
    return zstandard.ZstdCompressor(level=level, dict_data=zd, write_content_size=False, write_checksum=False, write_dict_id=False)


def _compressors(model: ToxicityModel):
    """Of the model in use only: a worker lives through many fits, each with a model for every fold."""
    key, cache = (model.ordinary, model.toxic, model.level), worker_cache()
    if cache.get("toxicity", ((),))[0] != key:
        cache["toxicity"] = key, (_compressor(model.ordinary, model.level).compress, _compressor(model.toxic, model.level).compress)
    return cache["toxicity"][1]


def savings(text: str | None, model: ToxicityModel) -> np.ndarray:
    """For each window of the whole text: bytes that the toxic dictionary saves against the ordinary one."""
    plain, toxic = _compressors(model)
    data = normal_bytes(text)
    if not data:
        return np.zeros(0, np.int64)
    found = [len(plain(w)) - len(toxic(w)) for w in pieces_of(data, model.window, model.step)]
    return np.array(found, np.int64)


def features(saved: np.ndarray) -> np.ndarray:
    """The four largest savings, how many windows save 2, 3, 4, 5, 6 bytes, all bytes saved and their mean, and the number of windows."""
    top, n = np.zeros(4), len(saved)
    k = min(4, n)
    if k:
        top[:k] = np.sort(np.partition(saved, n - k)[n - k :])[::-1]
    won = int(np.clip(saved, 0, None).sum())
    strong = [np.log1p((saved >= t).sum()) for t in (2, 3, 4, 5, 6)]
    long = np.log1p(n)
    return np.array([*top, *strong, np.log1p(won), won / max(1, n), long, long * long / 10, 1.0])


def score_text(text: str | None, model: ToxicityModel | None) -> float:
    """Probability of label 1; with no model 0, and for a text without letters that of one without savings."""
    if model is None:
        return 0.0
    z = float(features(savings(text, model)) @ np.array(model.weights))
    return float(1 / (1 + np.exp(-np.clip(z, -30, 30))))


def typical_segments(toxic: list[str], ordinary: list[str], stem: int = 5, least_z: float = 6.0) -> list[tuple[float, str]]:
    """(z, segment), the least typical first: words, ended by a blank, and stems of ``stem`` letters or more, with at least
    four times as many distinct places per toxic text as per ordinary one.  A stem that one longer segment is as typical as
    is left out."""

    def places(texts: list[str], among: Counter | None = None) -> Counter:
        number: dict[str, int] = {"": 0}
        pairs, fresh, waiting = np.zeros(0, np.int64), [], 0  # (word before, word) as one number: sets of string pairs took most of a worker's memory
        for t in texts:
            at = np.array([0, *(number.setdefault(w, len(number)) for w in _WORD.findall(t.lower()))], np.int64)
            fresh.append(at[:-1] << 32 | at[1:])
            waiting += len(at)
            if waiting > _WAITING:
                pairs, fresh, waiting = np.unique(np.concatenate([pairs, *fresh])), [], 0
        pairs = np.unique(np.concatenate([pairs, *fresh]))
        counts = np.bincount(pairs & 0xFFFFFFFF, minlength=len(number)).tolist()
        out: Counter = Counter()
        for w, n in zip(number, counts, strict=True):
            if n:
                for part in (w + " ", *(w[:k] for k in range(stem, len(w) + 1))):
                    if among is None or part in among:
                        out[part] += n
        return out

    a, n, m = places(toxic), len(toxic), len(ordinary)
    b = places(ordinary, a)
    found: dict[str, float] = {}
    for w, x in a.items():
        rate, plain = x / n, (b[w] + 0.5) / m
        if x >= 3 and rate >= 4 * plain:
            mean = (x + b[w] + 0.5) / (n + m)
            z = float((rate - plain) / np.sqrt(mean * (1 / n + 1 / m)))
            if z >= least_z:
                found[w] = z
    best_longer: dict[str, float] = {}
    for w, z in found.items():
        best_longer[w[:-1]] = max(z, best_longer.get(w[:-1], 0.0))
    return sorted((z, w) for w, z in found.items() if best_longer.get(w, 0.0) < z)


@dataclass(frozen=True)
class FitOptions:
    dictionary_bytes: int = 64000
    training_windows: int = 20000  # at most so many windows of 256 bytes, evenly over the ordinary texts, train their dictionary
    window: int = 48
    step: int = 32
    level: int = 3
    folds: int = 4
    min_z: tuple[float, ...] = (6.0, 9.0)  # least z of a typical segment: one is chosen


def _dictionaries(toxic: list[str], ordinary: list[str], o: FitOptions) -> dict[float, ToxicityModel]:
    """For each least z a model without weights; all share the ordinary dictionary."""
    step = max(1, sum(-(-len(normal_bytes(t)) // 256) or 1 for t in ordinary) // o.training_windows)
    samples = list(itertools.islice((w for t in ordinary for w in pieces_of(normal_bytes(t), 256, 256)), 0, None, step))
    try:
        plain = zstandard.train_dictionary(o.dictionary_bytes, samples).as_bytes()[-o.dictionary_bytes :]
    except zstandard.ZstdError:  # too few samples to train on
        plain = b"".join(samples)[-o.dictionary_bytes :]
    plain = (plain or b" ") * (8 // max(1, len(plain)) + 1)
    typical = typical_segments(toxic, ordinary, least_z=min(o.min_z))
    out = {}
    for least in o.min_z:
        words = [w for z, w in typical if z >= least]
        content = plain + b" " + b" ".join(w.encode() for w in words) + b" "  # whole words keep their blank, and one between
        out[least] = ToxicityModel(plain, content, (), o.window, o.step, o.level, tuple(w.strip() for w in words))
    return out


def _fold(toxic: list[str], ordinary: list[str], k: int, folds: int, o: FitOptions) -> tuple[list[int], dict[float, list]]:
    """Labels of the texts of one fold, and for each least z their features by dictionaries made without them."""
    out = [[x for i, x in enumerate(texts) if i % folds == k] for texts in (ordinary, toxic)]
    rest = [[x for i, x in enumerate(texts) if i % folds != k] for texts in (ordinary, toxic)] if folds > 1 else out
    models = _dictionaries(rest[1], rest[0], o)
    rows = {z: [features(savings(t, m)).tolist() for texts in out for t in texts] for z, m in models.items()}
    return [label for label, texts in enumerate(out) for _ in texts], rows


def _curve(x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, float]:
    """Weights of a logistic curve, and its loss."""
    w = np.zeros(x.shape[1])
    ridge = np.full(len(w), 0.05)
    ridge[-1] = 1e-6
    for _ in range(60):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        g = x.T @ (p - y) + ridge * w
        h = (x * (p * (1 - p))[:, None]).T @ x + np.diag(ridge)
        move = np.linalg.solve(h, g)
        w -= move
        if np.abs(move).max() < 1e-9:
            break
    z = np.clip(x @ w, -30, 30)
    return w, float(np.mean(np.log1p(np.exp(z)) - y * z))


def fit(toxic: list[str], ordinary: list[str], share_toxic: float | None = None, options: FitOptions = FitOptions(), spark: SparkSession | None = None) -> ToxicityModel | None:
    """Fit on two lists of texts.  ``share_toxic`` is the share of label 1 among all labels, if the lists don't keep it.

    The curve is calibrated by cross-fitting: the savings of a text come from dictionaries made without it.  With ``spark``
    each fold, and the final dictionaries, are a task.  With no texts of either label there is no model.
    """
    if not toxic or not ordinary:
        return None
    toxic, ordinary = sorted(set(toxic)), sorted(set(ordinary))
    folds = max(2, min(options.folds, len(toxic), len(ordinary))) if min(len(toxic), len(ordinary)) > 1 else 1
    if spark is None:
        done = [_fold(toxic, ordinary, k, folds, options) for k in range(folds)]
        models = _dictionaries(toxic, ordinary, options)
    else:
        sent = spark.sparkContext.broadcast((toxic, ordinary))

        def run(batches):
            for batch in batches:
                for k in batch.column(0).to_pylist():
                    made = _fold(*sent.value, k, folds, options) if k < folds else {z: (m.ordinary, m.toxic, m.segments) for z, m in _dictionaries(*sent.value, options).items()}
                    yield pa.RecordBatch.from_arrays([pa.array([k]), pa.array([pickle.dumps(made)], pa.binary())], names=["k", "made"])

        parts = spark.range(0, folds + 1, 1, folds + 1).mapInArrow(run, "k bigint, made binary").collect()  # a few numbers for each text of the sample
        got = {r["k"]: pickle.loads(bytes(r["made"])) for r in parts}
        sent.destroy()
        done = [got[k] for k in range(folds)]
        models = {z: ToxicityModel(a, b, (), options.window, options.step, options.level, words) for z, (a, b, words) in got[folds].items()}
    y = np.array([label for labels, _ in done for label in labels], float)
    curves = {z: _curve(np.array([x for _, rows in done for x in rows[z]]), y) for z in options.min_z}
    best = min(options.min_z, key=lambda z: (curves[z][1], z))
    w = curves[best][0]
    if share_toxic is not None and 0 < share_toxic < 1:
        w[-1] += np.log(share_toxic / (1 - share_toxic)) - np.log(len(toxic) / len(ordinary))
    return replace(models[best], weights=tuple(w.tolist()))


def labelled_sample(docs: DataFrame, labels: DataFrame, per_label: int, max_chars: int, doc_id: str, text: str, label: str):
    """Bounded lists of toxic and ordinary texts that are not held out, and the share of label 1 among all such labels."""
    marks = labels.select(F.col(doc_id).alias("__id"), F.col(label).alias("__y")).where("__id is not null and __y is not null")
    marks = marks.where(~held_out("__id")).groupBy("__id").agg(F.max((F.col("__y") > 0).cast("int")).alias("__y"))
    n = {r["__y"]: r["n"] for r in marks.groupBy("__y").agg(F.count("*").alias("n")).collect()}
    chosen = [marks.where(F.col("__y") == y).orderBy(F.xxhash64("__id"), "__id").limit(k) for y, k in ((1, per_label), (0, 2 * per_label))]
    ids = chosen[0].unionAll(chosen[1])
    own = docs.select(F.col(doc_id).alias("__id"), F.col(text).alias("__t")).where(F.length("__t") <= max_chars)
    # one text of a repeated id, so that no id can bring more than its share
    rows = own.join(F.broadcast(ids), "__id").groupBy("__id", "__y").agg(F.min("__t").alias("__t")).select("__y", "__t").collect()
    total = sum(n.values())
    return [r["__t"] for r in rows if r["__y"]], [r["__t"] for r in rows if not r["__y"]], n.get(1, 0) / total if total else None


def fit_on(docs: DataFrame, labels: DataFrame, per_label: int = 3000, max_chars: int = 20000, doc_id: str = "doc_id", text: str = "text", label: str = "toxic") -> ToxicityModel | None:
    """Fit on ``per_label`` toxic and twice as many ordinary texts, chosen by a hash of their id among the rows that are
    not held out and have at most ``max_chars`` characters: at most 9,000 texts whatever the size of the tables."""
    toxic, ordinary, share = labelled_sample(docs, labels, per_label, max_chars, doc_id, text, label)
    return fit(toxic, ordinary, share, spark=docs.sparkSession)


def toxicity(model: ToxicityModel | None):
    """Column function: text to score in 0..1.  Whole texts; null counts as empty."""
    return text_function(lambda texts: [score_text(t, model) for t in texts], "double")


def score(docs: DataFrame, model: ToxicityModel | None, doc_id: str = "doc_id", text: str = "text", threshold: float = 0.3) -> DataFrame:
    """(doc_id, held_out, score, predicted), one row for each row of ``docs``; its other columns are not read."""
    found: Column = toxicity(model)(F.col(text))
    own = docs.select(F.col(doc_id).alias("doc_id"), held_out(doc_id).alias("held_out"), found.alias("score"))
    return own.withColumn("predicted", (F.col("score") >= threshold).cast("int"))


def drop_toxic(docs: DataFrame, model: ToxicityModel | None, text: str = "text", threshold: float = 0.3) -> DataFrame:
    """The rows of ``docs``, all columns, whose score is below the threshold.

    A null or empty text has the score of a text without savings; repeated rows go or stay together; with no model all stay.
    """
    return docs.where(toxicity(model)(F.col(text)) < threshold)
