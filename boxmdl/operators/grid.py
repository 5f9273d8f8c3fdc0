"""Discretisation grids.

A grid holds, for each attribute, its number of intervals and its range, and
for irregular grids the inner cut points.  It is a few numbers, lives on the
driver and enters plans as literals.  Index rule of regular attributes:
``floor((v - lo) / (hi - lo) * B)``, evaluated in that order, the top value in
the last interval, values outside the range in the nearest interval; an
attribute with one value has index 0 everywhere.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from itertools import pairwise

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.codes import universal_int_bits

NOT_FINITE = "null, NaN or infinite attribute values; pass on_missing='drop' to leave these rows out"


@dataclass(frozen=True)
class Axis:
    attr: str
    n_bins: int
    lo: float
    hi: float
    cuts: tuple[float, ...] | None = None  # inner cut points, ascending; None for equal width

    def index(self, value: Column) -> Column:
        """0-based interval of a value."""
        if self.cuts is not None:
            if not self.cuts:
                return F.lit(0)
            return F.size(F.filter(F.array(*[F.lit(float(c)) for c in self.cuts]), lambda c: c <= value))
        if self.hi <= self.lo:
            return F.lit(0)
        scaled = F.floor((value - F.lit(self.lo)) / (F.lit(self.hi) - F.lit(self.lo)) * F.lit(float(self.n_bins)))
        return F.greatest(F.lit(0), F.least(F.lit(self.n_bins - 1), scaled)).cast("int")

    def edges(self) -> list[float]:
        """The n_bins + 1 interval ends."""
        if self.cuts is not None:
            return [self.lo, *self.cuts, self.hi]
        width = (self.hi - self.lo) / self.n_bins
        return [self.lo + width * j for j in range(self.n_bins)] + [self.hi]


@dataclass(frozen=True)
class Grid:
    axes: tuple[Axis, ...]
    n_rows: int = 0

    @property
    def attrs(self) -> list[str]:
        return [a.attr for a in self.axes]

    @property
    def side_bits(self) -> float:
        """Bits of the position of one box: any two ends on every side."""
        return sum(math.log2(a.n_bins * (a.n_bins + 1) / 2) for a in self.axes)

    @property
    def bits(self) -> float:
        return universal_int_bits(len(self.axes)) + sum(universal_int_bits(a.n_bins) for a in self.axes)

    def indices(self) -> list[Column]:
        return [a.index(F.col(a.attr).cast("double")).alias(f"b_{i}") for i, a in enumerate(self.axes)]

    def save_rows(self) -> list[tuple]:
        return [(i, a.attr, a.n_bins, float(a.lo), float(a.hi), None if a.cuts is None else list(map(float, a.cuts))) for i, a in enumerate(self.axes)]


GRID_SCHEMA = "axis int, attr string, n_bins int, lo double, hi double, cuts array<double>"


def to_frame(spark, grid: Grid) -> DataFrame:
    return spark.createDataFrame(grid.save_rows(), GRID_SCHEMA)


def from_frame(df: DataFrame) -> Grid:
    return Grid(tuple(Axis(r.attr, r.n_bins, r.lo, r.hi, None if r.cuts is None else tuple(r.cuts)) for r in df.orderBy("axis").collect()))


def _not_finite(attrs: list[str]) -> Column:
    bad = F.lit(False)
    for a in attrs:
        v = F.col(a).cast("double")
        bad = bad | v.isNull() | F.isnan(v) | (F.abs(v) == float("inf"))
    return bad


def finite_rows(df: DataFrame, attrs: list[str]) -> DataFrame:
    """Rows whose attributes are all finite numbers."""
    return df.filter(~_not_finite(attrs))


def check_rows(df: DataFrame, attrs: list[str]) -> None:
    """Raise if an attribute value is not a finite number; grids made from the rows have checked that already."""
    if df.filter(_not_finite(attrs)).limit(1).count():
        raise ValueError(NOT_FINITE)


def _ranges(df: DataFrame, attrs: list[str]):
    parts = [f(F.col(a).cast("double")).alias(f"{name}_{i}") for i, a in enumerate(attrs) for name, f in (("lo", F.min), ("hi", F.max))]
    row = df.agg(F.count(F.lit(1)).alias("n"), F.count_if(_not_finite(attrs)).alias("bad"), *parts).first()
    if not row.n:
        raise ValueError("no rows to make a grid from")
    if row.bad:
        raise ValueError(NOT_FINITE)
    return row.n, [(row[f"lo_{i}"], row[f"hi_{i}"]) for i in range(len(attrs))]


def bins_of(n_bins, attrs: list[str], n: int) -> list[int]:
    """Intervals of each attribute from an int, 'sqrt', a list or a dict."""
    root = max(1, math.isqrt(n))
    one = lambda b: root if b == "sqrt" else int(b)
    if isinstance(n_bins, dict):
        return [one(n_bins[a]) for a in attrs]
    if isinstance(n_bins, list | tuple):
        return [one(b) for b in n_bins]
    return [one(n_bins)] * len(attrs)


def equal_width(df: DataFrame, attrs: list[str], n_bins="sqrt") -> Grid:
    """Intervals of equal width between the least and greatest value; one scan."""
    n, ranges = _ranges(df, attrs)
    return Grid(tuple(Axis(a, b, lo, hi) for a, b, (lo, hi) in zip(attrs, bins_of(n_bins, attrs, n), ranges, strict=True)), n)


def from_cuts(df: DataFrame, cuts: dict[str, list[float]]) -> Grid:
    """Boundaries given by the user."""
    attrs = list(cuts)
    n, ranges = _ranges(df, attrs)
    return Grid(tuple(_irregular(a, lo, hi, cuts[a]) for a, (lo, hi) in zip(attrs, ranges, strict=True)), n)


def _irregular(attr: str, lo: float, hi: float, cuts) -> Axis:
    inner = tuple(sorted({float(c) for c in cuts if lo < c <= hi}))
    return Axis(attr, len(inner) + 1, lo, hi, inner)


def equal_height(df: DataFrame, attrs: list[str], n_bins="sqrt", exact: bool = False) -> Grid:
    """Quantile boundaries (approximate unless `exact`); repeated quantiles give fewer intervals."""
    n, ranges = _ranges(df, attrs)
    bins = bins_of(n_bins, attrs, n)
    parts = []
    for i, (a, b) in enumerate(zip(attrs, bins, strict=True)):
        shares = [j / b for j in range(1, b)] or [0.5]
        v = F.col(a).cast("double")
        parts.append((F.percentile(v, shares) if exact else F.percentile_approx(v, shares, max(10_000, 20 * b))).alias(f"q_{i}"))
    row = df.agg(*parts).first()
    return Grid(tuple(_irregular(a, lo, hi, row[f"q_{i}"] if bins[i] > 1 else []) for i, (a, (lo, hi)) in enumerate(zip(attrs, ranges, strict=True))), n)


def _micro(df: DataFrame, attrs: list[str], micro_bins: int) -> Grid:
    return equal_height(df, attrs, micro_bins)


def best_histogram(counts: np.ndarray, widths: np.ndarray, max_bins: int) -> list[int]:
    """Ends of the runs of micro-intervals that minimise the two-part length of a histogram.

    Length of b intervals: the integer code of b, the choice of b - 1 ends among
    the micro ends, the plug-in code of the counts and, within an interval, the
    place of each value by width.  Dynamic programme over the micro-intervals.
    """
    m, total = len(counts), float(counts.sum())
    ahead, wide = np.concatenate([[0.0], np.cumsum(counts)]), np.concatenate([[0.0], np.cumsum(widths)])

    def cost(i, j):  # of one interval over micro-intervals i..j-1
        n, w = ahead[j] - ahead[i], wide[j] - wide[i]
        share = np.where(n > 0, n / total, 1.0)
        return -n * np.log2(share) + n * np.log2(np.maximum(w, 1e-300))

    best = np.full((max_bins + 1, m + 1), np.inf)
    back = np.zeros((max_bins + 1, m + 1), int)
    best[0, 0] = 0.0
    for b in range(1, max_bins + 1):
        for j in range(b, m + 1):
            i = np.arange(b - 1, j)
            options = best[b - 1, i] + cost(i, j)
            at = int(options.argmin())
            best[b, j], back[b, j] = options[at], i[at]
    choose = lambda b: (math.lgamma(m) - math.lgamma(b) - math.lgamma(m - b + 1)) / math.log(2)
    lengths = [best[b, m] + universal_int_bits(b) + choose(b) + 0.5 * (b - 1) * math.log2(max(total, 2)) for b in range(1, min(max_bins, m) + 1)]
    b, j, ends = int(np.argmin(lengths)) + 1, m, []
    while b:
        j = int(back[b, j])
        ends.append(j)
        b -= 1
    return sorted(e for e in ends if e)


def mdl_1d(df: DataFrame, attrs: list[str], max_bins: int = 30, micro_bins: int = 200) -> Grid:
    """Boundaries chosen for each attribute alone by description length, over quantile micro-intervals."""
    micro = _micro(df, attrs, micro_bins)
    axes = []
    for axis in micro.axes:
        counts = {r.b: r.n for r in df.select(axis.index(F.col(axis.attr).cast("double")).alias("b")).groupBy("b").agg(F.count(F.lit(1)).alias("n")).collect()}
        edges = axis.edges()
        ends = best_histogram(np.array([counts.get(j, 0) for j in range(axis.n_bins)], float), np.maximum(np.diff(edges), 1e-12), min(max_bins, axis.n_bins))
        axes.append(_irregular(axis.attr, axis.lo, axis.hi, [edges[e] for e in ends]))
    return Grid(tuple(axes), micro.n_rows)


def interaction_preserving(df: DataFrame, attrs: list[str], micro_bins: int | None = None, threshold: float = 1.0 / 3.0) -> Grid:
    """Boundaries that keep what neighbouring intervals say about the other attributes.

    Our own reading of interaction-preserving discretisation: each attribute is
    cut into `micro_bins` quantile micro-intervals (by default 50, or the root
    of the number of rows where that is less); a profile (share of rows below each
    quartile of every other attribute, as an empirical distribution) is taken
    for each.  Two neighbours differ where the squared distance of their
    profiles is in the upper `threshold` share of all distances; the merge that
    minimises interval code plus the number of kept differences is found by a
    dynamic programme.
    """
    micro = _micro(df, attrs, micro_bins or min(50, bins_of("sqrt", attrs[:1], df.count())[0]))
    levels = _micro(df, attrs, 4)
    rows = df.select(*[a.index(F.col(a.attr).cast("double")).alias(f"m_{i}") for i, a in enumerate(micro.axes)], *[a.index(F.col(a.attr).cast("double")).alias(f"l_{i}") for i, a in enumerate(levels.axes)])
    axes = []
    for i, axis in enumerate(micro.axes):
        parts = [F.avg((F.col(f"l_{o}") <= q).cast("double")).alias(f"f_{o}_{q}") for o in range(len(attrs)) if o != i for q in range(levels.axes[o].n_bins - 1)]
        if not parts or axis.n_bins == 1:
            axes.append(_irregular(axis.attr, axis.lo, axis.hi, axis.cuts or ()))
            continue
        found = {r["b"]: r for r in rows.groupBy(F.col(f"m_{i}").alias("b")).agg(F.count(F.lit(1)).alias("n"), *parts).collect()}
        known = sorted(found)
        profile = np.array([[found[b][c] for c in found[b].__fields__[2:]] for b in known])
        weight = np.array([found[b]["n"] for b in known], float)
        ends = _merge_profiles(profile, weight, threshold)
        edges = axis.edges()
        axes.append(_irregular(axis.attr, axis.lo, axis.hi, [edges[known[e]] for e in ends]))
    return Grid(tuple(axes), micro.n_rows)


def _merge_profiles(profile: np.ndarray, weight: np.ndarray, threshold: float) -> list[int]:
    """Starts of the runs of micro-intervals with like profiles."""
    m = len(profile)
    if m < 2:
        return []
    gaps = ((profile[1:] - profile[:-1]) ** 2).mean(axis=1)
    # sampling noise of two empirical shares
    noise = 0.25 * (1 / weight[1:] + 1 / weight[:-1])
    limit = max(float(np.quantile(gaps, 1 - threshold)), 1e-12)
    different = (gaps >= limit) & (gaps > 2 * noise)
    ahead = np.concatenate([[0], np.cumsum(different)])
    lost = lambda i, j: ahead[j - 1] - ahead[i]  # noqa: E731  differences inside a run i..j-1
    best, back = [0.0] + [math.inf] * m, [0] * (m + 1)
    price = math.log2(m) + 1
    for j in range(1, m + 1):
        for i in range(j):
            value = best[i] + price + 2 * price * float(lost(i, j))
            if value < best[j]:
                best[j], back[j] = value, i
    ends, j = [], m
    while j:
        j = back[j]
        ends.append(j)
    return sorted(e for e in ends if e)


def interaction_cuts(values: np.ndarray, micro_bins: int | None = None, threshold: float = 1.0 / 3.0) -> list[tuple[float, ...]]:
    """`interaction_preserving` on an array of rows: the inner cut points of each attribute."""
    n, k = values.shape
    micro_bins = micro_bins or min(50, max(1, math.isqrt(n)))
    ordered = np.sort(values, axis=0)
    at = lambda i, b: tuple(sorted({float(c) for c in (ordered[max(0, math.ceil(j * n / b) - 1), i] for j in range(1, b)) if ordered[0, i] < c}))
    micro, levels = [at(i, micro_bins) for i in range(k)], [at(i, 4) for i in range(k)]
    level = np.stack([np.searchsorted(levels[i], values[:, i], side="right") for i in range(k)], axis=1)
    out = []
    for i in range(k):
        parts = [(level[:, o] <= q).astype(float) for o in range(k) if o != i for q in range(len(levels[o]))]
        if not parts or not micro[i]:
            out.append(micro[i])
            continue
        known, which, counts = np.unique(np.searchsorted(micro[i], values[:, i], side="right"), return_inverse=True, return_counts=True)
        profile = np.stack([np.bincount(which, p) / counts for p in parts], axis=1)
        edges = [ordered[0, i], *micro[i]]
        out.append(tuple(sorted({float(edges[known[e]]) for e in _merge_profiles(profile, counts.astype(float), threshold)} - {float(ordered[0, i])})))
    return out


def residual_bits(df: DataFrame, grid: Grid, precision: float = 1e-6) -> float:
    """Bits to restore the values inside their intervals; constant under equal width, which is why it is left out there."""
    parts = []
    for a in grid.axes:
        widths = [math.log2(max((y - x) / precision, 1.0)) for x, y in pairwise(a.edges())]
        parts.append(F.element_at(F.array(*[F.lit(w) for w in widths]), a.index(F.col(a.attr).cast("double")) + 1))
    return float(df.agg(F.sum(sum(parts[1:], parts[0]))).first()[0] or 0.0)
