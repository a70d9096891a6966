"""Autocorrelation, its peaks, and the periodicity tag, in exact integers until the last division."""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import PERIODIC_PEAKS, PERIODIC_THETA
from ..functions.times import let


def _centred(tokens: Column) -> Column:
    """M * w - sum(w): integers with the same correlation as the deviations from the mean."""
    total = F.aggregate(tokens, F.lit(0).cast("bigint"), lambda s, w: s + w)
    return F.transform(tokens, lambda w: w.cast("bigint") * F.size(tokens) - total)


def _products(u: Column, lag: Column) -> Column:
    later = F.slice(u, lag + 1, F.size(u))
    pairs = F.zip_with(F.slice(u, F.lit(1), F.size(u) - lag), later, lambda x, y: x * y)
    return F.aggregate(pairs, F.lit(0).cast("bigint"), lambda s, x: s + x)


def _sums(tokens: Column, max_lag: int | None) -> Column:
    """struct(den, nums): the sums for lag 0 and for lags 1, 2, ..."""

    def of(u: Column) -> Column:
        last = F.size(u) - 1
        last = F.least(last, F.lit(max_lag)) if max_lag is not None else last
        lags = F.when(last >= 1, F.sequence(F.lit(1), last)).otherwise(F.array().cast("array<int>"))
        return F.struct(_products(u, F.lit(0)).alias("den"), F.transform(lags, lambda t: _products(u, t)).alias("nums"))

    return let(_centred(tokens), of)


def _ratios(s: Column) -> Column:
    return F.transform(s["nums"], lambda x: F.when(s["den"] > 0, x / s["den"]))


def autocorrelation(sequences: DataFrame, max_lag: int | None = None) -> DataFrame:
    """(seq_id, den, nums, ac): ``nums[k]`` is the sum for lag k + 1, ``ac`` their ratio to ``den``; null if constant."""
    made = let(_sums(F.col("tokens"), max_lag), lambda s: F.struct(s["den"].alias("den"), s["nums"].alias("nums"), _ratios(s).alias("ac")))
    return sequences.select("seq_id", made.alias("s")).select("seq_id", "s.den", "s.nums", "s.ac")


def periodicity(sequences: DataFrame, theta: float = PERIODIC_THETA, min_peaks: int = PERIODIC_PEAKS, max_lag: int | None = None, plateau: bool = False) -> DataFrame:
    """PERIODIC: (seq_id, ac, peaks, is_periodic).

    A peak is an inner lag above both neighbours (``plateau``: not below) whose value exceeds ``theta``, compared as exact
    fractions.  Lag 1 has the neighbour 0, whose value is 1; the last lag has none to the right and is no peak.  A constant or
    empty sequence has no peaks.
    """
    t = Fraction(str(theta))

    def tagged(s: Column) -> Column:
        nums, den = s["nums"], s["den"]

        def over(i: Column) -> Column:
            here, left, right = F.get(nums, i - 1), F.when(i > 1, F.get(nums, i - 2)).otherwise(den), F.get(nums, i)
            shape = (here >= left) & (here >= right) & ((here > left) | (here > right)) if plateau else (here > left) & (here > right)
            return shape & (here * t.denominator > den * t.numerator)

        inner = F.when(F.size(nums) >= 2, F.sequence(F.lit(1), F.size(nums) - 1)).otherwise(F.array().cast("array<int>"))
        peaks = F.when(den > 0, F.filter(inner, over)).otherwise(F.array().cast("array<int>"))
        return F.struct(_ratios(s).alias("ac"), peaks.alias("peaks"))

    rows = sequences.select("seq_id", let(_sums(F.col("tokens"), max_lag), tagged).alias("s"))
    return rows.select("seq_id", "s.ac", "s.peaks", (F.size("s.peaks") >= min_peaks).alias("is_periodic"))


def dominant_period(periodic: DataFrame) -> DataFrame:
    """(seq_id, period): the peak of the largest value, the smallest of equals; null without peaks."""
    best = F.array_max(F.transform("peaks", lambda t: F.struct(F.get("ac", t - 1).alias("v"), (-t).alias("t"))))
    return periodic.select("seq_id", (-best["t"]).alias("period"))


def fold(sequences: DataFrame, periods: DataFrame) -> DataFrame:
    """Sequences cut to their first period, for normalising cyclic ones; those without a period stay whole."""
    joined = sequences.join(periods, "seq_id", "left")
    n = F.coalesce("period", F.col("len"))
    cut = joined.withColumn("tokens", F.slice("tokens", F.lit(1), n)).withColumn("times", F.when(F.col("times").isNotNull(), F.slice("times", F.lit(1), n)))
    return cut.withColumn("len", F.size("tokens")).drop("period")
