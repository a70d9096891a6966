"""Alignment measures by diagonals, for batches of pairs at once (NumPy).

All five recurrences look at three neighbours, so the cells of one diagonal depend on the two before it only.  A batch of
pairs is padded to one length and each diagonal is computed for all pairs together; memory is three diagonals a pair.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable, Sequence

import numpy as np

from ..config import MetricParams

INF = np.inf


def pad(rows: Sequence, fill: float = 0.0, kind: type = float) -> tuple[np.ndarray, np.ndarray]:
    """Rows of different length as a matrix, and their lengths."""
    sizes = np.fromiter((len(r) for r in rows), np.int64, len(rows))
    out = np.full((len(rows), int(sizes.max(initial=0))), fill, kind)
    if out.size:
        out[np.arange(out.shape[1]) < sizes[:, None]] = np.concatenate([np.asarray(r, float) for r in rows if len(r)])
    return out, sizes


def number_kind(a: Sequence, b: Sequence, *prices: float) -> type:
    """Single precision where it is exact: all values are multiples of 1/16 and no sum of a path reaches 2**19."""
    if any(p * 16 != int(p * 16) for p in prices if np.isfinite(p)):
        return float
    longest = max((len(r) for r in a), default=0) + max((len(r) for r in b), default=0)
    tokens = [np.asarray(r) for r in (*a, *b) if len(r)]
    whole = all(np.issubdtype(r.dtype, np.integer) or bool((r == np.floor(r)).all()) for r in tokens)
    most = max((float(np.abs(r).max()) for r in tokens), default=0.0)
    return np.float32 if whole and most < 2**19 and longest * (1 + most) * (1 + sum(map(abs, prices))) * 2 < 2**19 else float


def sweep(m: np.ndarray, n: np.ndarray, cell: Callable, edge_i: np.ndarray, edge_j: np.ndarray, stop_above: np.ndarray | None = None, kind: type = float):
    """(value in the last cell of each pair, number of cells visited).

    ``cell(I, J, before2, up, left)`` gets 0-based slices of both sequences and the three neighbours.  ``stop_above``: a pair
    whose two latest diagonals are wholly above its bound is given up, with value infinity (right for growing recurrences).
    """
    wide, high = int(m.max(initial=0)), int(n.max(initial=0))
    count = len(m)
    before2 = np.full((count, wide + 1), INF, kind)
    before = before2.copy()
    out = np.full(count, INF)
    alive, low_before, cells = np.ones(count, bool), np.full(count, -INF), 0
    for d in range(wide + high + 1):
        now = np.full((count, wide + 1), INF, kind)
        a, b = max(1, d - high), min(wide, d - 1)
        if a <= b:
            i = slice(a, b + 1)
            # j - 1 runs down from d - a - 1 to d - b - 1
            stop = d - b - 2
            j = slice(d - a - 1, stop if stop >= 0 else None, -1)
            now[:, i] = cell(slice(a - 1, b), j, before2[:, a - 1 : b], before[:, a - 1 : b], before[:, i])
        if d <= high:
            now[:, 0] = edge_j[:, d]
        if d <= wide:
            now[:, d] = edge_i[:, d]
        cells += int((alive & (m + n >= d)).sum()) * max(0, b - a + 1)
        done = m + n == d
        if done.any():
            out[done] = now[done, m[done]]
            out[~alive] = INF
        if stop_above is not None:
            lowest = now.min(axis=1)
            alive &= ~((np.minimum(lowest, low_before) > stop_above) & (m + n > d))
            low_before = lowest
            if not alive[m + n > d].any():
                break
        before2, before = before, now
    return out, cells


def _origin(count: int, size: int) -> np.ndarray:
    out = np.full((count, size + 1), INF)
    out[:, 0] = 0
    return out


def lcss(a, b, p: MetricParams = MetricParams()) -> np.ndarray:
    """Length of the longest common subsequence, with tolerance and window."""
    kind = number_kind(a, b)
    (x, m), (y, n) = pad(a, np.nan, kind), pad(b, np.nan, kind)
    zero_i, zero_j = np.zeros((len(m), x.shape[1] + 1)), np.zeros((len(m), y.shape[1] + 1))

    def cell(i, j, diagonal, up, left):
        same = np.abs(x[:, i] - y[:, j]) <= p.lcss_eps
        if p.lcss_delta is not None:
            pos_i, pos_j = np.arange(x.shape[1])[i], np.arange(y.shape[1])[j]
            same &= np.abs(pos_i - pos_j) <= p.lcss_delta
        return np.where(same, diagonal + 1, np.maximum(up, left))

    return sweep(m, n, cell, zero_i, zero_j, kind=kind)[0]


def edr(a, b, p: MetricParams = MetricParams(), stop_above=None) -> np.ndarray:
    kind = number_kind(a, b)
    (x, m), (y, n) = pad(a, np.nan, kind), pad(b, np.nan, kind)
    edge_i = np.broadcast_to(np.arange(x.shape[1] + 1.0), (len(m), x.shape[1] + 1))
    edge_j = np.broadcast_to(np.arange(y.shape[1] + 1.0), (len(m), y.shape[1] + 1))

    def cell(i, j, diagonal, up, left):
        differ = ~(np.abs(x[:, i] - y[:, j]) <= p.edr_eps)
        return np.minimum(diagonal + differ, np.minimum(up, left) + 1)

    return sweep(m, n, cell, edge_i, edge_j, stop_above, kind)[0]


def erp(a, b, p: MetricParams = MetricParams(), stop_above=None) -> np.ndarray:
    kind = number_kind(a, b, p.beta, p.gap)
    (x, m), (y, n) = pad(a, 0.0, kind), pad(b, 0.0, kind)
    gap_x, gap_y = p.beta * np.abs(x - p.gap), p.beta * np.abs(y - p.gap)
    zero = np.zeros((len(m), 1))
    edge_i, edge_j = np.hstack([zero, np.cumsum(gap_x, 1)]), np.hstack([zero, np.cumsum(gap_y, 1)])

    def cell(i, j, diagonal, up, left):
        return np.minimum(diagonal + np.abs(x[:, i] - y[:, j]), np.minimum(up + gap_x[:, i], left + gap_y[:, j]))

    return sweep(m, n, cell, edge_i, edge_j, stop_above, kind)[0]


def dtw(a, b, p: MetricParams = MetricParams(), stop_above=None) -> np.ndarray:
    kind = number_kind(a, b)
    (x, m), (y, n) = pad(a, np.nan, kind), pad(b, np.nan, kind)
    band = None if p.dtw_band is None else np.maximum(p.dtw_band, np.abs(m - n))

    def cell(i, j, diagonal, up, left):
        gap = np.abs(x[:, i] - y[:, j])
        cost = gap if p.dtw_cost == "abs" else (gap != 0).astype(kind)
        best = np.minimum(diagonal, np.minimum(up, left)) + cost
        if band is not None:
            pos_i, pos_j = np.arange(x.shape[1])[i], np.arange(y.shape[1])[j]
            best = np.where(np.abs(pos_i - pos_j)[None, :] <= band[:, None], best, INF)
        return best

    return sweep(m, n, cell, _origin(len(m), x.shape[1]), _origin(len(m), y.shape[1]), stop_above, kind)[0]


def twed(a, b, ta=None, tb=None, p: MetricParams = MetricParams(), stop_above=None, count_cells: bool = False):
    """Time-warp edit distance; times default to positions 1, 2, ...  Before the first item stands a sentinel at time 0."""
    longest = max((len(r) for r in (*a, *b)), default=0)
    kind = number_kind(a, b, p.nu * max(1, 2 * longest), p.nu, p.lam) if ta is None and tb is None else float
    (x, m), (y, n) = pad(a, np.nan, kind), pad(b, np.nan, kind)
    wide, high = x.shape[1], y.shape[1]
    s = np.broadcast_to(np.arange(1, wide + 1, dtype=kind), x.shape) if ta is None else pad(ta)[0]
    t = np.broadcast_to(np.arange(1, high + 1, dtype=kind), y.shape) if tb is None else pad(tb)[0]
    zero, nothing = np.zeros((len(m), 1), kind), np.full((len(m), 1), INF, kind)
    x0, y0 = np.hstack([nothing, x])[:, :wide], np.hstack([nothing, y])[:, :high]
    s0, t0 = np.hstack([zero, s])[:, :wide], np.hstack([zero, t])[:, :high]

    def gap(u, v):
        differ = (u != v).astype(kind)
        if p.twed_cost == "discrete":
            return differ
        with np.errstate(invalid="ignore"):
            return np.where(np.isfinite(u) & np.isfinite(v), np.abs(u - v), differ)

    def cell(i, j, diagonal, up, left):
        here, apart = gap(x[:, i], y[:, j]), p.nu * np.abs(s[:, i] - t[:, j])
        both = diagonal + here + gap(x0[:, i], y0[:, j]) + apart
        if p.twed == "printed":
            return np.minimum(both, np.minimum(up, left) + here + apart + p.lam)
        both = both + p.nu * np.abs(s0[:, i] - t0[:, j])
        drop_x = up + gap(x[:, i], x0[:, i]) + p.nu * (s[:, i] - s0[:, i]) + p.lam
        drop_y = left + gap(y[:, j], y0[:, j]) + p.nu * (t[:, j] - t0[:, j]) + p.lam
        return np.minimum(both, np.minimum(drop_x, drop_y))

    out, cells = sweep(m, n, cell, _origin(len(m), wide), _origin(len(m), high), stop_above, kind)
    return (out, cells) if count_cells else out


#: Pairs, words of 64 places and masks of a batch by bits.
_BIT_WORDS, _MASKS = 1 << 14, 1 << 22
_ONE, _TOP = np.uint64(1), np.uint64(63)


def _distinct(rows: Sequence) -> tuple[list, np.ndarray]:
    """The different objects among the rows, and which of them each row is."""
    own = {id(r): r for r in rows}
    place = dict(zip(own, range(len(own)), strict=True))
    return list(own.values()), np.fromiter(map(place.__getitem__, map(id, rows)), np.int64, len(rows))


def _used(rows: Sequence, at: np.ndarray) -> tuple[list, np.ndarray]:
    """The rows that are referred to, and the references to them."""
    used = np.zeros(len(rows), bool)
    used[at] = True
    return [rows[k] for k in np.flatnonzero(used)], (np.cumsum(used) - 1)[at]


def by_bits(name: str, a: Sequence, b: Sequence, p: MetricParams = MetricParams()) -> np.ndarray | None:
    """``lcss`` or ``edr`` of all pairs, one number of 64 places for 64 cells of a column; the same rows are prepared once.

    A column's cells differ from their neighbours by 0 or 1, so the differences are bits, and sums of whole numbers carry them
    down the column.  None where tokens need a tolerance or window, or where there are too many different ones for masks."""
    return _by_bits(name, *_distinct(a), *_distinct(b), p)


def _codes(flat: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(the different values, which of them each is); whole numbers of a small range without a sort."""
    low = flat.min(initial=0)
    if not (np.abs(flat) < 2**31).all() or flat.max(initial=0) - low > len(flat) or (flat != np.floor(flat)).any():
        return np.unique(flat, return_inverse=True)
    at = (flat - low).astype(np.int64)
    used = np.zeros(int(at.max(initial=0)) + 1, bool)
    used[at] = True
    return np.flatnonzero(used) + low, (np.cumsum(used) - 1)[at]


def _by_bits(name: str, rows: Sequence, x: np.ndarray, cols: Sequence, y: np.ndarray, p: MetricParams) -> np.ndarray | None:
    """:func:`by_bits` of the pairs (rows[x], cols[y])."""
    if name not in ("lcss", "edr") or not len(x) or (p.lcss_eps or p.lcss_delta is not None if name == "lcss" else p.edr_eps):
        return None
    m, n = (np.fromiter(map(len, r), np.int64, len(r)) for r in (rows, cols))
    flat = np.concatenate([np.asarray(r, float) for r in (*rows, *cols)])
    if np.isnan(flat).any():
        return None
    kinds, code = _codes(flat)
    words, wide = max(1, -(-int(m.max()) // 64)), int(n.max())
    if len(rows) * (len(kinds) + 1) * words > _MASKS:
        return None
    masks = np.zeros((len(rows), len(kinds) + 1, words), np.uint64)  # the last token is in no row
    at = np.concatenate([np.arange(k) for k in m])
    np.bitwise_or.at(masks, (np.repeat(np.arange(len(m)), m), code[: m.sum()], at >> 6), _ONE << (at & 63).astype(np.uint64))
    tokens = np.full((len(cols), wide + 1), len(kinds), np.int64)
    tokens[:, :wide][np.arange(wide) < n[:, None]] = code[m.sum() :]
    masks = np.ascontiguousarray(masks.reshape(-1, words).T)
    out = np.empty(len(x))
    step = max(64, _BIT_WORDS // words)
    order = np.lexsort((x, n[y]))
    for k in range(0, len(order), step):
        g = order[k : k + step]
        column = (tokens[y[g], : int(n[y[g[-1]]])] + (x[g] * (len(kinds) + 1))[:, None]).T.copy()
        out[g] = (_common if name == "lcss" else _edits)(masks, column, m[x[g]], n[y[g]])
    return out


def _common(masks: np.ndarray, column: np.ndarray, m: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Lengths of common subsequences: how many places of the differences are 0 at the end."""
    v = np.full((len(masks), len(m)), ~np.uint64(0))
    for at in column:
        carry = None
        for w, mask in enumerate(masks):
            here, old = mask[at], v[w]
            same = old & here
            total = old + same
            over = total < old
            if carry is not None:
                total += carry
                over |= (total == 0) & carry.astype(bool)
            v[w] = total | (old & ~here)
            carry = over.astype(np.uint64)
    return (64 - np.bitwise_count(v).astype(np.int64)).sum(0)


def _edits(masks: np.ndarray, column: np.ndarray, m: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Edit distances, from the differences down the last column; pairs are in order of ``n``."""
    words = len(masks)
    plus, minus = np.full((words, len(m)), ~np.uint64(0)), np.zeros((words, len(m)), np.uint64)
    low = np.stack([np.where(m >= 64 * (w + 1), ~np.uint64(0), (_ONE << np.clip(m - 64 * w, 0, 63).astype(np.uint64)) - _ONE) for w in range(words)])
    ends = np.searchsorted(n, np.arange(len(column) + 2))
    out = np.zeros(len(m))

    def take(j: int) -> None:
        g = slice(ends[j], ends[j + 1])
        if ends[j] < ends[j + 1]:
            out[g] = n[g] + (np.bitwise_count(plus[:, g] & low[:, g]).astype(np.int64) - np.bitwise_count(minus[:, g] & low[:, g]).astype(np.int64)).sum(0)

    take(0)
    for j, at in enumerate(column, 1):
        carry, up, down = None, _ONE, np.uint64(0)  # the first row grows by one in each column
        for w, mask in enumerate(masks):
            here, p, q = mask[at], plus[w], minus[w]
            same = here & p
            total = same + p
            over = total < p
            if carry is not None:
                total += carry
                over |= (total == 0) & carry.astype(bool)
            carry = over.astype(np.uint64)
            across = (total ^ p) | here
            grow, fall = q | ~(across | p), p & across
            along = here | q
            next_up, next_down = grow >> _TOP, fall >> _TOP
            grow, fall = (grow << _ONE) | up, (fall << _ONE) | down
            plus[w], minus[w] = fall | ~(along | grow), grow & along
            up, down = next_up, next_down
        take(j)
    return out


class Windows:
    """Many short rows, at most 64 items, each a number with a bit for every item: common subsequences with one sequence at a time.

    A row's differences are one number, so a step is four operations over all rows, which lie side by side."""

    def __init__(self, rows: np.ndarray, sizes: np.ndarray, kinds: np.ndarray) -> None:
        """``rows``: items as a matrix, of which the first ``sizes`` count; ``kinds``: the items of the sequences, in order."""
        wide = rows.shape[1]
        self.kind = next(t for t in (np.uint8, np.uint16, np.uint32, np.uint64) if wide <= 8 * np.dtype(t).itemsize)
        code = np.minimum(np.searchsorted(kinds, rows), max(0, len(kinds) - 1))
        known = (np.arange(wide) < sizes[:, None]) & (kinds[code] == rows if len(kinds) else False)
        self.masks = np.zeros((len(kinds), len(rows)), self.kind)
        every = np.arange(len(rows))
        for j in range(wide):
            at = known[:, j]
            self.masks[code[at, j], every[at]] |= self.kind(1 << j)
        self.v, self.t, self.u = (np.empty(len(rows), self.kind) for _ in range(3))

    def common(self, codes: list[int]) -> np.ndarray:
        """Lengths of the common subsequences of a sequence, as places of ``kinds``, and every row."""
        v, t, u = self.v, self.t, self.u
        v.fill(~self.kind(0))
        for c in codes:
            np.bitwise_and(v, self.masks[c], t)
            np.add(v, t, u)
            np.subtract(v, t, v)
            np.bitwise_or(u, v, v)
        return np.bitwise_count(np.invert(v, t))


#: Pairs of a batch of short whole numbers.
_SHORT_PAIRS = 512


def by_shorts(name: str, a: Sequence, b: Sequence, p: MetricParams = MetricParams()) -> np.ndarray | None:
    """``twed`` (printed, discrete, by positions) or ``erp`` of all pairs, in short whole numbers where these are exact.

    Prices are multiples of 1/16 at most, so costs are whole numbers of a unit.  Pairs lie side by side, so every step is over
    contiguous memory; the same rows are prepared once.  None for other forms, other tokens or sums that are too large."""
    return _by_shorts(name, *_distinct(a), *_distinct(b), p)


def _by_shorts(name: str, rows: Sequence, x: np.ndarray, cols: Sequence, y: np.ndarray, p: MetricParams) -> np.ndarray | None:
    """:func:`by_shorts` of the pairs (rows[x], cols[y])."""
    prices = {"twed": (p.nu, p.lam, 1.0), "erp": (p.beta, p.beta * p.gap, p.gap, 1.0)}.get(name)
    if prices is None or not len(x) or not np.isfinite(prices).all() or (name == "twed" and (p.twed != "printed" or p.twed_cost != "discrete")) or min(p.nu, p.lam, p.beta) < 0:
        return None
    unit = next((u for u in (1, 2, 4, 8, 16) if all(x * u == int(x * u) for x in prices)), None)
    m, n = (np.fromiter(map(len, r), np.int64, len(r)) for r in (rows, cols))
    flat = np.concatenate([np.asarray(r, float) for r in (*rows, *cols)])
    if unit is None or not (flat == np.floor(flat)).all():
        return None
    longest = int(max(m.max(), n.max()))
    if name == "twed":
        kinds, flat = np.unique(flat, return_inverse=True)  # apart by a unit at least, so that the lesser of the two is 0 or a unit
        flat = flat * unit
        step = unit * (2 + p.lam + p.nu * longest)
        # down the diagonal, then straight on
        most = max(len(kinds) * unit * 2, unit * longest * (3 + p.lam + p.nu * longest))
    else:
        flat = flat * unit
        far = float(np.abs(flat).max(initial=0))
        step = 2 * far + p.beta * (far + unit * abs(p.gap))
        most = 2 * longest * p.beta * (far + unit * abs(p.gap))  # every item at its own price
    if most + step >= 2**15 - 2:
        return None
    inf = np.int16(2**15 - 2 - int(np.ceil(step)))
    table = [np.zeros((len(r), max(1, int(k.max(initial=0)))), np.int16) for r, k in ((rows, m), (cols, n))]
    table[0][np.arange(table[0].shape[1]) < m[:, None]] = flat[: m.sum()]
    table[1][np.arange(table[1].shape[1]) < n[:, None]] = flat[m.sum() :]
    out = np.empty(len(x))
    order = np.lexsort((m[x], m[x] + n[y]))
    for k in range(0, len(order), _SHORT_PAIRS):
        g = order[k : k + _SHORT_PAIRS]
        mg, ng = m[x[g]], n[y[g]]
        u, v = table[0][x[g], : mg.max()].T.copy(), table[1][y[g], : ng.max()].T.copy()
        out[g] = (_short_twed if name == "twed" else _short_erp)(u, v, mg, ng, unit, inf, p)
    return np.where((name == "twed") & ((m[x] == 0) != (n[y] == 0)), INF, out / unit)


def _short_diagonals(u: np.ndarray, v: np.ndarray, m: np.ndarray, n: np.ndarray, inf: np.int16, cell: Callable, edge: Callable) -> np.ndarray:
    """Values of the last cells, where places are rows and pairs columns.  ``cell(now, before, before2, d, a, b)`` fills the rows
    a to b of a diagonal, ``edge(now, d)`` its first and last."""
    wide, high, count = len(u), len(v), len(m)
    now, before, before2 = (np.full((wide + 1, count), inf, np.int16) for _ in range(3))
    ends = m + n
    last: dict[int, np.ndarray] = {int(d): np.flatnonzero(ends == d) for d in np.unique(ends)}
    out = np.zeros(count)
    for d in range(int(ends.max()) + 1):
        a, b = max(1, d - high), min(wide, d - 1)
        if a <= b:
            cell(now, before, before2, d, a, b)
        edge(now, d)
        if d in last:
            out[last[d]] = now[m[last[d]], last[d]]
        now, before, before2 = before2, now, before
    return out


def _short_twed(u, v, m, n, unit, inf, p) -> np.ndarray:
    wide, high, count = len(u), len(v), len(m)
    lam, one = np.int16(unit * p.lam), np.int16(unit)
    differ = [np.full((wide + 1, count), one, np.int16) for _ in range(3)]
    some = np.empty((wide + 1, count), np.int16)
    apart = (unit * p.nu * np.abs(np.arange(-(wide + high), wide + high + 1))).astype(np.int16)

    def cell(now, before, before2, d, a, b):
        mine, prev = differ[d % 3], differ[(d - 2) % 3]
        here, rest, i = mine[a : b + 1], some[a : b + 1], now[a : b + 1]
        stop = d - b - 2
        np.bitwise_xor(u[a - 1 : b], v[d - a - 1 : stop if stop >= 0 else None : -1], out=here)
        np.minimum(here, one, out=here)
        np.add(before2[a - 1 : b], prev[a - 1 : b], out=i)
        np.minimum(before[a - 1 : b], before[a : b + 1], out=rest)
        np.add(rest, lam, out=rest)
        np.minimum(i, rest, out=i)
        np.add(i, here, out=i)
        np.add(i, apart[2 * np.arange(a, b + 1) - d + wide + high][:, None], out=i)

    def edge(now, d):
        differ[d % 3][0] = one if d else 0  # before the first items both have the same mark
        if d <= high:
            now[0] = inf if d else 0
        if 0 < d <= wide:
            now[d], differ[d % 3][d] = inf, one

    return _short_diagonals(u, v, m, n, inf, cell, edge)


def _short_erp(u, v, m, n, unit, inf, p) -> np.ndarray:
    wide, high, count = len(u), len(v), len(m)
    gap_u, gap_v = ((p.beta * np.abs(w - np.int16(unit * p.gap))).astype(np.int16) for w in (u, v))
    edge_u, edge_v = (np.vstack([np.zeros((1, count), np.int16), np.cumsum(g, 0, dtype=np.int16)]) for g in (gap_u, gap_v))
    some = np.empty((wide + 1, count), np.int16)

    def cell(now, before, before2, d, a, b):
        stop = d - b - 2
        j = slice(d - a - 1, stop if stop >= 0 else None, -1)
        rest, i = some[a : b + 1], now[a : b + 1]
        np.add(before[a : b + 1], gap_v[j], out=rest)
        np.subtract(u[a - 1 : b], v[j], out=i)
        np.abs(i, out=i)
        np.add(i, before2[a - 1 : b], out=i)
        np.minimum(i, rest, out=i)
        np.add(before[a - 1 : b], gap_u[a - 1 : b], out=rest)
        np.minimum(i, rest, out=i)

    def edge(now, d):
        if d <= high:
            now[0] = edge_v[d]
        if d <= wide:
            now[d] = edge_u[d]

    return _short_diagonals(u, v, m, n, inf, cell, edge)


#: Pairs of a batch of single bytes.
_BYTE_PAIRS = 2_048


def by_bytes(name: str, a: Sequence, b: Sequence, p: MetricParams = MetricParams()) -> np.ndarray | None:
    """``dtw`` (discrete) of all pairs, one byte a cell; the same rows are prepared once.

    A path straight down the diagonal and then along costs one for each item of the longer sequence at most, and is within any band,
    so a byte holds every value that counts.  Pairs of equal lengths have the same cells, so only those of the band are visited.
    None for other costs, for sequences that are too long, or for too many different tokens."""
    return _by_bytes(name, *_distinct(a), *_distinct(b), p)


def _by_bytes(name: str, rows: Sequence, x: np.ndarray, cols: Sequence, y: np.ndarray, p: MetricParams) -> np.ndarray | None:
    """:func:`by_bytes` of the pairs (rows[x], cols[y])."""
    if name != "dtw" or p.dtw_cost != "discrete" or not len(x):
        return None
    m, n = (np.fromiter(map(len, r), np.int64, len(r)) for r in (rows, cols))
    if max(m.max(), n.max()) > 200 or (p.dtw_band or 0) < 0:
        return None
    flat = np.concatenate([np.asarray(r, float) for r in (*rows, *cols)])
    if np.isnan(flat).any():
        return None
    kinds, code = _codes(flat)
    if len(kinds) > 255:
        return None
    table = [np.zeros((len(r), max(1, int(k.max()))), np.uint8) for r, k in ((rows, m), (cols, n))]
    for t, k, part in ((table[0], m, code[: m.sum()]), (table[1], n, code[m.sum() :])):
        t[np.arange(t.shape[1]) < k[:, None]] = part
    out = np.empty(len(x))
    sizes = m[x] * 256 + n[y]
    order = np.argsort(sizes, kind="stable")
    ends = np.flatnonzero(np.diff(sizes[order], append=-1)) + 1
    at = 0
    for end in ends:
        for k in range(at, end, _BYTE_PAIRS):
            g = order[k : min(end, k + _BYTE_PAIRS)]
            mg, ng = int(m[x[g[0]]]), int(n[y[g[0]]])
            band = max(mg, ng) if p.dtw_band is None else max(p.dtw_band, abs(mg - ng))
            out[g] = _byte_dtw(table[0][x[g], :mg].T.copy(), table[1][y[g], :ng].T.copy(), band)
        at = end
    return out


def _byte_dtw(u: np.ndarray, v: np.ndarray, band: int) -> np.ndarray:
    """Values of the last cells; places are rows and pairs columns, and all pairs have the same lengths."""
    (m, count), n, inf = u.shape, len(v), np.uint8(254)
    if not m or not n:
        return np.full(count, INF if m or n else 0.0)
    now, before, before2 = (np.full((m + 2, count), inf, np.uint8) for _ in range(3))
    before[0] = 0  # the origin is all that diagonal 0 has
    one, cost = np.uint8(1), np.empty((m + 1, count), np.uint8)
    for d in range(1, m + n + 1):
        a, b = max(1, d - n, -((band - d) // 2)), min(m, d - 1, (d + band) // 2)
        if a <= b:
            i, differ, stop = now[a : b + 1], cost[a : b + 1], d - b - 2
            np.not_equal(u[a - 1 : b], v[d - a - 1 : stop if stop >= 0 else None : -1], out=differ.view(bool))
            np.minimum(before[a - 1 : b], before[a : b + 1], out=i)
            np.minimum(i, before2[a - 1 : b], out=i)
            np.minimum(i, inf - one, out=i)
            np.add(i, differ, out=i)
            now[a - 1], now[b + 1] = inf, inf  # what the diagonal two before left beside the band
        else:
            now[:] = inf
        now, before, before2 = before2, now, before
    return before[m].astype(float)


def quick(name: str, a: Sequence, b: Sequence, p: MetricParams = MetricParams()) -> np.ndarray | None:
    """Distances (for lcss, lengths) of all pairs by a faster exact form, or None."""
    return quick_at(name, *_distinct(a), *_distinct(b), p)


def quick_at(name: str, rows: Sequence, x: np.ndarray, cols: Sequence, y: np.ndarray, p: MetricParams = MetricParams()) -> np.ndarray | None:
    """:func:`quick` of the pairs (rows[x], cols[y])."""
    return {"lcss": _by_bits, "edr": _by_bits, "dtw": _by_bytes}.get(name, _by_shorts)(name, rows, x, cols, y, p)


def quick_similarity(name: str, a: Sequence, b: Sequence, p: MetricParams = MetricParams()) -> np.ndarray | None:
    """The similarity that :func:`similarities` gives, by :func:`quick`, or None."""
    return quick_similarity_at(name, *_distinct(a), *_distinct(b), p)


def quick_similarity_at(name: str, rows: Sequence, x: np.ndarray, cols: Sequence, y: np.ndarray, p: MetricParams = MetricParams()) -> np.ndarray | None:
    """:func:`quick_similarity` of the pairs (rows[x], cols[y]): many pairs of few rows need no lists of pairs."""
    (rows, x), (cols, y) = _used(rows, x), _used(cols, y)
    v = (_by_bits if name in ("lcss", "edr") else _by_shorts)(name, rows, x, cols, y, p)
    if v is None:
        return None
    m, n = (np.fromiter(map(len, r), float, len(r))[at] for r, at in ((rows, x), (cols, y)))
    none = m + n == 0
    mean = np.where(none, 1.0, (m + n) / 2)
    if name == "twed":
        v = np.where((m == 0) ^ (n == 0), 0.0, np.exp(-v / (2 * mean)))
    elif name == "erp":
        v = np.exp(-v / mean)
    else:
        v = v / mean if name == "lcss" else 1 - v / np.where(none, 1.0, np.maximum(m, n))
    return np.where(none, 1.0, v)


def grams(tokens, n: int) -> Counter:
    row = [int(v) for v in tokens]
    return Counter(row) if n == 1 else Counter(zip(*(row[k:] for k in range(n)), strict=False))


def gram_similarity(a: Counter, b: Counter, kind: str = "cosine") -> float:
    """Cosine, Jaccard or Dice of counts; 0 if either is empty."""
    if not a or not b:
        return 0.0
    if len(b) < len(a):
        a, b = b, a
    if kind == "cosine":
        dot = sum(c * b[k] for k, c in a.items() if k in b)
        return dot / float(np.sqrt(float(sum(c * c for c in a.values())) * float(sum(c * c for c in b.values()))))
    common = sum(min(c, b[k]) for k, c in a.items() if k in b)
    total = sum(a.values()) + sum(b.values())
    return common / (total - common) if kind == "jaccard" else 2 * common / total


def similarities(names: Sequence[str], a, b, ta=None, tb=None, p: MetricParams = MetricParams()) -> dict[str, np.ndarray]:
    """The named similarities of a batch of pairs, all in [0, 1].

    Both empty: 1 for the alignment terms; one empty: LCSS, EDR and TWED 0, ERP by its gap sums; grams and histogram 0.
    """
    m = np.fromiter((len(r) for r in a), float, len(a))
    n = np.fromiter((len(r) for r in b), float, len(b))
    mean, none = (m + n) / 2, m + n == 0
    safe = np.where(none, 1.0, mean)
    out: dict[str, np.ndarray] = {}
    for name in names:
        if name == "twed":
            v = np.exp(-twed(a, b, ta, tb, p) / (2 * safe))
        elif name == "lcss":
            v = lcss(a, b, p) / safe
        elif name == "edr":
            v = 1 - edr(a, b, p) / np.where(none, 1.0, np.maximum(m, n))
        elif name == "erp":
            v = np.exp(-erp(a, b, p) / safe)
        elif name == "dtw":
            v = 1 - dtw(a, b, p) / np.where(none, 1.0, m + n)
            v = np.where(np.isfinite(v), v, 0.0)
        else:
            size, kind = (1, "cosine") if name == "hist" else (p.ngram, p.ngram_kind)
            memory: dict[bytes, Counter] = {}

            def of(row):
                key = np.asarray(row, np.int64).tobytes()
                if key not in memory:
                    memory[key] = grams(row, size)
                return memory[key]

            out[name] = np.fromiter((gram_similarity(of(r), of(s), kind) for r, s in zip(a, b, strict=True)), float, len(a))
            continue
        out[name] = np.where(none, 1.0, v)
    return out
