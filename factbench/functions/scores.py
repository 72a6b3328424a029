"""Scores in [-1, 1]: decisions, bins, clipping and readings of errors."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

EDGE = 1.0 / 3.0
#: Squared error of a full flip, from -1 to 1 or back.
FLIP = 4.0
VERY_HIGH, ACCEPTABLE = 0.04, 0.1


def _c(c: Column | str) -> Column:
    return F.col(c) if isinstance(c, str) else c


def decide(score: Column | str) -> Column:
    """negative below -1/3, positive above 1/3, else unknown; both bounds are strict. Null stays null."""
    s = _c(score)
    return F.when(s.isNull(), None).when(s < -EDGE, "negative").when(s > EDGE, "positive").otherwise("unknown")


def bin_index(score: Column | str, n: int) -> Column:
    """Index of the bin among ``n`` (odd) equal widths of [-1, 1], 0 in the middle; ties fall toward 0."""
    if n % 2 == 0:
        raise ValueError("the number of bins must be odd")
    s = _c(score)
    edges = [(2 * k - 1) / n for k in range(1, (n - 1) // 2 + 1)]
    return reduce(lambda a, b: a + b, [(s > e).cast("int") - (s < -e).cast("int") for e in edges], F.lit(0))


def nearest_anchor(score: Column | str, n: int) -> Column:
    """Alternative binning: the nearest of ``n`` anchors evenly spread over [-1, 1], ties toward 0."""
    half = (n - 1) // 2
    s = _c(score) * half
    return (F.signum(s) * F.ceil(F.abs(s) - 0.5)).cast("int")


def clip(score: Column | str) -> Column:
    """Within [-1, 1]; null stays null, which the two functions alone would skip."""
    s = _c(score)
    return F.when(s.isNotNull(), F.greatest(F.lit(-1.0), F.least(F.lit(1.0), s)))


def rounded(score: Column | str, places: int) -> Column:
    """The double nearest to the scaled score, ties away from 0, scaled back; unlike ``F.round`` it keeps the sign of what becomes 0, as SQL's does."""
    scaled = _c(score) * 10.0**places
    return F.signum(scaled) * F.round(F.abs(scaled)) / 10.0**places


def flip_equivalent(mse: Column | str) -> Column:
    """How many perfect ratings go with one full flip at this squared error; null for no error."""
    return F.try_divide(F.lit(FLIP), _c(mse))


def band(mse: Column | str) -> Column:
    m = _c(mse)
    return F.when(m <= VERY_HIGH, "very high agreement").when(m <= ACCEPTABLE, "acceptable").otherwise("above acceptable")


def coarse_label(score: Column | str) -> Column:
    """The single three-way label that the scores replace."""
    return F.when(_c(score) > EDGE, "true").when(_c(score) < -EDGE, "false").otherwise("not enough information")
