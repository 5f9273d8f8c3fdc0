"""Boxes as pairs of integer arrays with inclusive ends, and expressions over them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .grid import Grid


def join_lo(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: F.least(x, y))


def join_hi(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: F.greatest(x, y))


def log_size(lo: Column, hi: Column) -> Column:
    """Sum over the sides of log2 of the number of intervals."""
    return F.aggregate(F.zip_with(lo, hi, lambda x, y: F.log2((y - x + 1).cast("double"))), F.lit(0.0), lambda s, x: s + x)


def contains(lo_a, hi_a, lo_b, hi_b) -> Column:
    """Whether box a holds box b."""
    return F.forall(F.zip_with(lo_a, lo_b, lambda x, y: x <= y), lambda t: t) & F.forall(F.zip_with(hi_a, hi_b, lambda x, y: x >= y), lambda t: t)


def overlaps(lo_a, hi_a, lo_b, hi_b) -> Column:
    return F.forall(F.zip_with(lo_a, hi_b, lambda x, y: x <= y), lambda t: t) & F.forall(F.zip_with(lo_b, hi_a, lambda x, y: x <= y), lambda t: t)


def contains_point(grid: Grid, lo: list[int], hi: list[int]) -> Column:
    """Predicate over the attribute columns: a conjunction of ranges that a Parquet scan can prune by."""
    out = F.lit(True)
    for axis, x, y in zip(grid.axes, lo, hi, strict=True):
        edges = axis.edges()
        out = out & (F.col(axis.attr) >= edges[x]) & (F.col(axis.attr) <= edges[y + 1] if y + 1 == axis.n_bins else F.col(axis.attr) < edges[y + 1])
    return out


def to_predicate(grid: Grid, lo: list[int], hi: list[int]) -> str:
    """The box as SQL text."""
    parts = []
    for axis, x, y in zip(grid.axes, lo, hi, strict=True):
        edges = axis.edges()
        parts.append(f"{axis.attr} >= {edges[x]!r} AND {axis.attr} {'<=' if y + 1 == axis.n_bins else '<'} {edges[y + 1]!r}")
    return " AND ".join(parts)


def with_log_size(df: DataFrame) -> DataFrame:
    return df.withColumn("log_size", log_size(F.col("lo"), F.col("hi")))
