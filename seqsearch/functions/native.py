"""The same measures as SQL expressions of higher-order functions: no Python on the executors, for short sequences.

One builder makes the sweep; a measure supplies the text of its cell and of its two edges.  In those texts ``i`` and ``j``
are 1-based positions, ``x(i)`` and ``y(j)`` the items, and DIAG, UP, LEFT the three neighbours.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..config import MetricParams


def _sweep(a: str, b: str, cell: str, edge_i: str, edge_j: str) -> str:
    m, n = f"size({a})", f"size({b})"
    cell = cell.replace("DIAG", "get(s.q, i - 1)").replace("UP", "get(s.p, i - 1)").replace("LEFT", "get(s.p, i)")
    cell, edge_i, edge_j = (t.replace("$j", "(d - i)").replace("$i", "i") for t in (cell, edge_i, edge_j))
    empty = "cast(array() as array<double>)"
    row = f"transform(sequence(0, {m}), i -> CASE WHEN i > d OR d - i > {n} THEN CAST(NULL AS DOUBLE) WHEN i = 0 THEN CAST({edge_j} AS DOUBLE) WHEN i = d THEN CAST({edge_i} AS DOUBLE) ELSE CAST({cell} AS DOUBLE) END)"
    return f"aggregate(sequence(0, {m} + {n}), named_struct('p', {empty}, 'q', {empty}), (s, d) -> named_struct('p', {row}, 'q', s.p), s -> get(s.p, {m}))"


def _x(a: str, at: str = "$i") -> str:
    return f"get({a}, {at} - 1)"


def lcss(a: str, b: str, p: MetricParams = MetricParams()) -> Column:
    same = f"abs({_x(a)} - {_x(b, '$j')}) <= {p.lcss_eps}"
    if p.lcss_delta is not None:
        same += f" AND abs($i - $j) <= {p.lcss_delta}"
    return F.expr(f"cast({_sweep(a, b, f'CASE WHEN {same} THEN DIAG + 1 ELSE greatest(UP, LEFT) END', '0', '0')} as int)")


def edr(a: str, b: str, p: MetricParams = MetricParams()) -> Column:
    differ = f"CASE WHEN abs({_x(a)} - {_x(b, '$j')}) <= {p.edr_eps} THEN 0 ELSE 1 END"
    return F.expr(f"cast({_sweep(a, b, f'least(DIAG + {differ}, UP + 1, LEFT + 1)', '$i', '$j')} as int)")


def erp(a: str, b: str, p: MetricParams = MetricParams()) -> Column:
    def gap(v: str) -> str:
        return f"{p.beta}D * abs({v} - {p.gap}D)"

    def sums(array: str, upto: str) -> str:
        return f"aggregate(slice({array}, 1, {upto}), 0D, (u, v) -> u + {gap('v')})"

    cell = f"least(DIAG + abs({_x(a)} - {_x(b, '$j')}), UP + {gap(_x(a))}, LEFT + {gap(_x(b, '$j'))})"
    return F.expr(_sweep(a, b, cell, sums(a, "$i"), sums(b, "$j")))


def dtw(a: str, b: str, p: MetricParams = MetricParams()) -> Column:
    gap = f"abs({_x(a)} - {_x(b, '$j')})"
    cost = gap if p.dtw_cost == "abs" else f"CASE WHEN {_x(a)} = {_x(b, '$j')} THEN 0 ELSE 1 END"
    cell = f"least(DIAG, UP, LEFT) + {cost}"
    if p.dtw_band is not None:
        cell = f"CASE WHEN abs($i - $j) <= greatest({p.dtw_band}, abs(size({a}) - size({b}))) THEN {cell} END"
    # the empty prefix aligns with nothing else: only the origin has a value
    return F.expr(_sweep(a, b, cell, "CASE WHEN $i = 0 THEN 0 END", "CASE WHEN $j = 0 THEN 0 END"))


def twed(a: str, b: str, ta: str | None = None, tb: str | None = None, p: MetricParams = MetricParams()) -> Column:
    def at(times: str | None, k: str) -> str:
        return f"({k})" if times is None else f"coalesce(get({times}, {k} - 1), 0)"

    def gap(u: str, v: str) -> str:
        plain = f"CASE WHEN {u} <=> {v} THEN 0 ELSE 1 END"
        return f"({plain})" if p.twed_cost == "discrete" else f"coalesce(abs({u} - {v}), {plain})"

    x, y, x0, y0 = _x(a), _x(b, "$j"), _x(a, "($i - 1)"), _x(b, "($j - 1)")
    apart = f"{p.nu}D * abs({at(ta, '$i')} - {at(tb, '$j')})"
    if p.twed == "printed":
        cell = f"least(DIAG + {gap(x, y)} + {gap(x0, y0)} + {apart}, least(UP, LEFT) + {gap(x, y)} + {apart} + {p.lam}D)"
    else:
        earlier = f"{p.nu}D * abs({at(ta, '($i - 1)')} - {at(tb, '($j - 1)')})"
        up = f"UP + {gap(x, x0)} + {p.nu}D * ({at(ta, '$i')} - {at(ta, '($i - 1)')}) + {p.lam}D"
        left = f"LEFT + {gap(y, y0)} + {p.nu}D * ({at(tb, '$j')} - {at(tb, '($j - 1)')}) + {p.lam}D"
        cell = f"least(DIAG + {gap(x, y)} + {gap(x0, y0)} + {apart} + {earlier}, {up}, {left})"
    return F.expr(_sweep(a, b, cell, "CASE WHEN $i = 0 THEN 0 END", "CASE WHEN $j = 0 THEN 0 END"))


def ngrams(tokens: str | Column, n: int) -> Column:
    """Consecutive n-grams as an array of arrays; shorter sequences have none."""
    t = F.col(tokens) if isinstance(tokens, str) else tokens
    return F.when(F.size(t) >= n, F.transform(F.sequence(F.lit(1), F.size(t) - (n - 1)), lambda i: F.slice(t, i, n))).otherwise(F.array().cast("array<array<int>>"))


def gram_similarity(a: str, b: str, n: int = 2, kind: str = "cosine") -> Column:
    """Of counts of n-grams; 0 if either sequence is shorter than n."""
    def made(t: str) -> str:
        return f"CASE WHEN size({t}) >= {n} THEN transform(sequence(1, size({t}) - {n - 1}), k -> slice({t}, k, {n})) ELSE cast(array() as array<array<int>>) END"

    ga, gb = made(a), made(b)
    def total(u: str, v: str) -> str:
        return f"aggregate(transform({u}, g -> size(filter({v}, h -> h = g))), 0, (s, c) -> s + c)"

    # sum over all places of one of the places of the other with an equal gram: the dot product of the counts
    if kind == "cosine":
        return F.expr(f"CASE WHEN size({a}) < {n} OR size({b}) < {n} THEN 0D ELSE {total(ga, gb)} / sqrt(cast({total(ga, ga)} as double) * {total(gb, gb)}) END")
    common = f"aggregate(array_distinct({ga}), 0, (s, g) -> s + least(size(filter({ga}, h -> h = g)), size(filter({gb}, h -> h = g))))"
    both = f"(size({ga}) + size({gb}))"
    share = f"{common} / ({both} - {common})" if kind == "jaccard" else f"2 * {common} / {both}"
    return F.expr(f"CASE WHEN size({a}) < {n} OR size({b}) < {n} THEN 0D ELSE cast({share} as double) END")
