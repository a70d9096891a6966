"""Golden values, full-matrix loops, and native against Arrow."""

import math
import random

import numpy as np
import pytest

from seqsearch.config import WEIGHTS, MetricParams, check_weights, weight_presets
from seqsearch.functions import wavefront as wf
from seqsearch.functions.metrics import batch_similarities, batch_values

GOLDEN = [  # a, b, lcss, edr, erp, dtw, twed printed, twed original, cosine, bigram, score
    ([1, 2, 3, 4], [1, 2, 3, 4], 4, 0, 0, 0, 0, 0, 1, 1, 1),
    ([1, 2, 3, 4], [2, 3, 4, 5], 3, 2, 3, 2, 4.375, 5.75, 0.75, 0.666667, 0.646550),
    ([1, 2, 3, 4], [1, 3, 4], 3, 1, 1, 1, 2.25, 3.375, 0.866025, 0.408248, 0.746031),
    ([5, 5, 1], [1, 5, 5, 7], 2, 2, 4.5, 2, 3.375, 4.375, 0.912871, 0.408248, 0.616077),
    ([1], [2], 0, 1, 1, 1, 1, 1, 0, 0, 0.127768),
    ([0, 0, 7], [7], 1, 2, 0, 2, 4.375, 4.25, 0.447214, 0, 0.409408),
]


def full(a, b, kind, p=MetricParams()):
    """The textbook matrix."""
    m, n = len(a), len(b)
    d = [[math.inf] * (n + 1) for _ in range(m + 1)]
    d[0][0] = 0.0
    x, y = [None, *a], [None, *b]
    ne = lambda u, v: float(u != v)
    for i in range(m + 1):
        for j in range(n + 1):
            if kind == "lcss":
                d[i][j] = 0.0 if not i or not j else d[i - 1][j - 1] + 1 if abs(x[i] - y[j]) <= p.lcss_eps and (p.lcss_delta is None or abs(i - j) <= p.lcss_delta) else max(d[i - 1][j], d[i][j - 1])
                continue
            best = d[i][j]
            if i and j:
                c = {"edr": lambda: float(abs(x[i] - y[j]) > p.edr_eps), "erp": lambda: abs(x[i] - y[j]), "dtw": lambda: ne(x[i], y[j])}
                if kind in c:
                    best = min(best, d[i - 1][j - 1] + c[kind]())
                else:
                    s = ne(x[i], y[j]) + ne(x[i - 1], y[j - 1]) + p.nu * abs(i - j) * (1 if kind == "twed_printed" else 2)
                    best = min(best, d[i - 1][j - 1] + s)
            for di, dj in ((1, 0), (0, 1)):
                if i < di or j < dj:
                    continue
                before = d[i - di][j - dj]
                if kind == "edr":
                    best = min(best, before + 1)
                elif kind == "erp":
                    best = min(best, before + p.beta * abs((x[i] if di else y[j]) - p.gap))
                elif i and j and kind == "dtw":
                    best = min(best, before + ne(x[i], y[j]))
                elif i and j and kind == "twed_printed":
                    best = min(best, before + ne(x[i], y[j]) + p.nu * abs(i - j) + p.lam)
                elif i and j:
                    best = min(best, before + (ne(x[i], x[i - 1]) if di else ne(y[j], y[j - 1])) + p.nu + p.lam)
            d[i][j] = best
    return d[m][n]


def arrow(kind, a, b, p=MetricParams()):
    if kind.startswith("twed"):
        return wf.twed(a, b, p=MetricParams(twed=kind[5:]))
    return getattr(wf, kind)(a, b, p)


@pytest.mark.parametrize("row", GOLDEN)
def test_golden(row):
    a, b, *want = row
    got = [wf.lcss([a], [b])[0], wf.edr([a], [b])[0], wf.erp([a], [b])[0], wf.dtw([a], [b])[0], wf.twed([a], [b])[0], wf.twed([a], [b], p=MetricParams(twed="original"))[0]]
    s = wf.similarities(list(WEIGHTS), [a], [b])
    got += [s["hist"][0], s["ngram"][0], sum(w * s[k][0] for k, w in WEIGHTS.items())]
    assert np.allclose(got, want, atol=1e-6)


def test_lcss_variants():
    a, b = [[1, 2, 3, 4]], [[2, 3, 4, 5]]
    for eps, delta, want in ((1, None, 4), (0, 0, 0), (0, 1, 3), (1, 0, 4)):
        assert wf.lcss(a, b, MetricParams(lcss_eps=eps, lcss_delta=delta))[0] == want


@pytest.mark.parametrize("kind", ["lcss", "edr", "erp", "dtw", "twed_printed", "twed_original"])
def test_full_matrix(kind):
    rng = random.Random(1)
    a = [[rng.randrange(4) for _ in range(rng.randrange(0, 12))] for _ in range(120)]
    b = [[rng.randrange(4) for _ in range(rng.randrange(0, 12))] for _ in range(120)]
    assert np.array_equal(arrow(kind, a, b), [full(x, y, kind) for x, y in zip(a, b, strict=True)])


def test_bounds_and_properties():
    rng = random.Random(2)
    for _ in range(200):
        a, b = ([rng.randrange(5) for _ in range(rng.randrange(1, 15))] for _ in range(2))
        m, n = len(a), len(b)
        common = sum(min(a.count(v), b.count(v)) for v in set(a))
        s = {k: v[0] for k, v in wf.similarities(["twed", "lcss", "edr", "erp", "hist", "ngram", "dtw"], [a], [b]).items()}
        t = {k: v[0] for k, v in wf.similarities(list(s), [b], [a]).items()}
        assert all(abs(s[k] - t[k]) < 1e-12 and -1e-12 <= s[k] <= 1 + 1e-12 for k in s)
        assert s["lcss"] <= 2 * common / (m + n) + 1e-12 and s["edr"] <= common / max(m, n) + 1e-12
        assert wf.edr([a], [b])[0] >= max(m, n) - wf.lcss([a], [b])[0]
        assert wf.twed([a], [b])[0] >= abs(m - n)
        assert all(abs(v[0] - 1) < 1e-12 for v in wf.similarities(["twed", "lcss", "edr", "erp", "hist"], [a], [a]).values())


def test_early_stop():
    rng = random.Random(3)
    a = [[rng.randrange(5) for _ in range(20)] for _ in range(60)]
    b = [[rng.randrange(5) for _ in range(20)] for _ in range(60)]
    whole, cells = wf.twed(a, b, count_cells=True)
    limit = np.full(60, np.median(whole))
    some, fewer = wf.twed(a, b, stop_above=limit, count_cells=True)
    low = whole <= limit
    assert np.array_equal(some[low], whole[low]) and np.all((some == whole) | np.isinf(some)) and fewer <= cells


def test_empty():
    s = wf.similarities(["twed", "lcss", "edr", "erp", "hist", "ngram"], [[], [], [1]], [[], [1], []])
    assert [v.tolist() for k, v in s.items() if k in ("twed", "lcss", "edr")] == [[1, 0, 0]] * 3
    assert s["erp"][0] == 1 and s["hist"].tolist() == [0, 0, 0]


def test_weights():
    assert abs(sum(WEIGHTS.values()) - 1) < 1e-12
    for w in weight_presets().values():
        check_weights(w)
    with pytest.raises(ValueError):
        check_weights({"hist": 0.5})


def test_native_equals_arrow(spark):
    from seqsearch.functions.metrics import pair_distance, pair_metric

    rng = random.Random(4)
    row = lambda: [rng.randrange(5) for _ in range(rng.randrange(0, 9))]
    times = lambda n: sorted(rng.randrange(0, 40) / 4 for _ in range(n))
    rows = [(i, 0, a := row(), b := row(), times(len(a)), times(len(b))) for i in range(60)]
    df = spark.createDataFrame(rows, "query_id long, cand_id long, a array<int>, b array<int>, ta array<double>, tb array<double>")
    names = ["hist", "twed", "lcss", "edr", "erp", "ngram", "dtw"]
    x = {r["query_id"]: r for r in pair_metric(df, names, how="arrow", timed=True).collect()}
    y = {r["query_id"]: r for r in pair_metric(df, names, how="native", timed=True).collect()}
    assert all(abs(x[i][f"s_{n}"] - y[i][f"s_{n}"]) < 1e-9 for i in x for n in names)
    for m, p in (("twed", MetricParams(twed="original", twed_cost="abs")), ("dtw", MetricParams(dtw_cost="abs", dtw_band=1)), ("lcss", MetricParams(lcss_eps=1, lcss_delta=1)), ("edr", MetricParams(edr_eps=1))):
        x = {r["query_id"]: r["value"] for r in pair_distance(df, m, p, "arrow").collect()}
        y = {r["query_id"]: r["value"] for r in pair_distance(df, m, p, "native").collect()}
        assert x == y, m


@pytest.mark.parametrize("name", ["lcss", "edr"])
def test_bits_equal_the_sweep(name):
    """Whole words of 64 places, one more and one less, empty, one kind of token and many, negative ones, the same row in many pairs."""
    rng = np.random.default_rng(1)
    rows = [rng.integers(0, k, n) for n in (0, 1, 5, 63, 64, 65, 127, 128, 129, 200) for k in (1, 2, 5, 300) for _ in range(2)]
    rows += [np.array([-3, 7, -3]), [1, 2, 2]]
    a, b = [r for r in rows for _ in rows], [r for _ in rows for r in rows]
    want = batch_values(lambda x, y, *_: {"v": getattr(wf, name)(x, y)}, a, b, None, None, ["v"])["v"]
    assert np.array_equal(wf.by_bits(name, a, b), want)
    s = batch_values(lambda x, y, *_: wf.similarities([name], x, y), a, b, None, None, [name])[name]
    assert np.array_equal(wf.quick_similarity(name, a, b), s)
    assert wf.by_bits(name, a, b, MetricParams(lcss_eps=1, edr_eps=1)) is None


def test_bits_take_no_sweep(monkeypatch):
    """Pairs of whole sequences get both terms without a sweep over diagonals."""
    monkeypatch.setattr(wf, "sweep", None)
    rng = np.random.default_rng(2)
    rows = [rng.integers(0, 5, n) for n in rng.integers(45, 100, 200)]
    a, b = [r for r in rows[:100] for _ in rows], rows * 100
    s = batch_similarities(["lcss", "edr"], a, b, None, None, MetricParams())
    assert len(s["lcss"]) == 20_000 and s["edr"][0] == s["lcss"][0] == 1 and (s["edr"] <= s["lcss"] + 1e-12).all()


@pytest.mark.parametrize("p", [MetricParams(), MetricParams(nu=0.5, lam=0.25, beta=1.0, gap=2.0), MetricParams(nu=0.0625, beta=0.25, gap=-1.0)])
@pytest.mark.parametrize("name", ["twed", "erp"])
def test_short_numbers_equal_the_sweep(name, p):
    """Empty and long, few tokens and many, negative ones; where sums are too large there is no short form."""
    rng = np.random.default_rng(1)
    rows = [rng.integers(0, k, n) for n in (0, 1, 5, 31, 64, 65, 90) for k in (1, 2, 5, 30) for _ in range(2)]
    rows += [np.array([-3, 7, -3]), [1, 2, 2]]
    a, b = [r for r in rows for _ in rows], [r for _ in rows for r in rows]
    whole = lambda x, y, *_: {"v": wf.twed(x, y, p=p) if name == "twed" else wf.erp(x, y, p)}
    want = batch_values(whole, a, b, None, None, ["v"])["v"]
    got = wf.quick(name, a, b, p)
    if p.nu < 0.5:
        assert got is not None
    assert got is None or np.array_equal(got, want)
    s = batch_values(lambda x, y, *_: wf.similarities([name], x, y, p=p), a, b, None, None, [name])[name]
    assert np.array_equal(batch_similarities([name], a, b, None, None, p)[name], s)
    big = [np.array([0, 20_000]), np.array([30_000])]
    assert wf.quick("erp", big, big[::-1], p) is None and wf.quick("twed", [np.arange(600)], [np.arange(600)], p) is None
    assert wf.quick(name, [np.array([0.5])], [np.array([1.0])], p) is None
    assert wf.quick("twed", a, b, MetricParams(twed="original")) is None and wf.quick("erp", a, b, MetricParams(beta=0.3)) is None


def test_scores_take_no_sweep(monkeypatch):
    """All alignment terms of whole sequences of few tokens, by forms that are exact and need no diagonals of floats."""
    monkeypatch.setattr(wf, "sweep", None)
    rng = np.random.default_rng(2)
    rows = [rng.integers(0, 5, n) for n in rng.integers(45, 100, 50)]
    a, b = [r for r in rows for _ in rows], rows * 50
    s = batch_similarities(["twed", "lcss", "edr", "erp"], a, b, None, None, MetricParams())
    assert all(len(v) == 2_500 and v[0] == 1 and (v > 0).all() for v in s.values())
