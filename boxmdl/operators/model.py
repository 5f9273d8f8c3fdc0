"""Description lengths of pattern sets, and gains of replacing patterns by their hull.

A gain splits into a part that depends on the number of patterns only
(`kappa`) and one that depends on the replaced patterns only (`group_weight`,
`pair_weight`).  The reconstruction part uses the logarithm of box sizes.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import codes
from ..functions.codes import EPS, lgamma_bits, lgamma_bits_col, lgamma_step_bits, universal_int_bits, universal_int_bits_col
from .grid import Grid


def pattern_set_bits(k: int, grid: Grid) -> float:
    return universal_int_bits(k) + k * grid.side_bits


def model_bits(k: int, grid: Grid) -> float:
    return grid.bits + pattern_set_bits(k, grid)


def total_bits(boxes: DataFrame, grid: Grid, eps: float = EPS, encoding: str = "plugin") -> DataFrame:
    """One row with all parts of the length: ``n, k, grid, patterns, count, data, reconstruction, total``; one aggregate over the boxes (`usage`, `log_size`)."""
    usage = F.col("usage")
    data = codes.plugin_sequence_bits_agg(usage, eps) if encoding == "plugin" else codes.shannon_bits_agg(usage)
    row = boxes.agg(F.sum(usage).cast("long").alias("n"), F.count(F.lit(1)).alias("k"), data.alias("data"), F.sum(usage * F.col("log_size")).alias("reconstruction"))
    parts = row.withColumns({
        "grid": F.lit(grid.bits),
        "patterns": universal_int_bits_col(F.col("k")) + F.col("k") * F.lit(grid.side_bits),
        "count": universal_int_bits_col(F.col("n")),
    })
    return parts.withColumn("total", F.col("grid") + F.col("patterns") + F.col("count") + F.col("data") + F.col("reconstruction")).select("n", "k", "grid", "patterns", "count", "data", "reconstruction", "total")


def total_bits_local(usages: np.ndarray, log_sizes: np.ndarray, grid: Grid, eps: float = EPS, encoding: str = "plugin") -> float:
    n, k = int(usages.sum()), len(usages)
    data = codes.plugin_sequence_bits(usages.tolist(), eps) if encoding == "plugin" else codes.shannon_bits(usages.tolist())
    return model_bits(k, grid) + universal_int_bits(n) + data + float((usages * log_sizes).sum())


def kappa(k: int, n: int, grid: Grid, eps: float = EPS, merged: int = 1, encoding: str = "plugin") -> float:
    """Gain of having `merged` patterns fewer than k, apart from the patterns' own terms."""
    if k - merged < 1:
        return -math.inf
    out = universal_int_bits(k) - universal_int_bits(k - merged) + merged * grid.side_bits
    if encoding == "plugin":
        low = k - merged
        out += lgamma_step_bits(n + eps * low, eps * merged) - lgamma_step_bits(eps * low, eps * merged)
    return out


def kappa_np(k: np.ndarray, n: int, grid: Grid, eps: float = EPS, encoding: str = "plugin") -> np.ndarray:
    """`kappa` for one merge, for many numbers of patterns."""
    k = np.asarray(k, float)
    out = _universal_np(k) - _universal_np(k - 1) + grid.side_bits
    if encoding == "plugin":
        out = out + _step_np(n + eps * (k - 1), eps) - _step_np(np.maximum(eps * (k - 1), eps), eps)
    return out


def _universal_np(n: np.ndarray) -> np.ndarray:
    total, term = np.full(len(n), math.log2(codes.C0)), np.asarray(n, float)
    for _ in range(5):
        term = np.where(term > 1, np.log2(np.maximum(term, 1)), 0.0)
        total = total + term
    return np.where(n >= 1, total, 0.0)


def _step_np(x: np.ndarray, step: float) -> np.ndarray:
    """log2 of gamma(x + step) / gamma(x), without losing digits for large x."""
    y = x + step
    series = (step * np.log(x) + (y - 0.5) * np.log1p(step / x) - step + 1 / (12 * y) - 1 / (12 * x)) / codes.LN2
    return np.where(x < 1e5, lgamma_bits_np(y) - lgamma_bits_np(x), series)


def hope(k: int, n: int, grid: Grid, eps: float = EPS, encoding: str = "plugin") -> float:
    """No `kappa` of a round that starts with k patterns is above this.

    A round merges disjoint pairs, so it ends with half of the patterns or more.
    The gamma part of kappa falls with the number of patterns, and the integer
    code never takes a longer step than from 2 to 3.
    """
    low = max(2, k - k // 2)
    out = grid.side_bits + universal_int_bits(3) - universal_int_bits(2)
    if encoding == "plugin":
        out += lgamma_step_bits(n + eps * (low - 1), eps) - lgamma_step_bits(eps * (low - 1), eps)
    return out + 1e-6


def kappa_col(k: Column, n: int, grid: Grid, eps: float = EPS, encoding: str = "plugin") -> Column:
    """`kappa` for one merge, as a column; for large arguments the difference of log-gammas is a series."""
    out = universal_int_bits_col(k) - universal_int_bits_col(k - 1) + F.lit(grid.side_bits)
    if encoding == "plugin":
        def step(x):
            y = x + F.lit(eps)
            series = (F.lit(eps) * F.ln(x) + (y - 0.5) * F.log1p(F.lit(eps) / x) - F.lit(eps) + 1 / (12 * y) - 1 / (12 * x)) / F.lit(codes.LN2)
            return F.when(x < 1e5, lgamma_bits_col(y) - lgamma_bits_col(x)).otherwise(series)

        low = (k - 1).cast("double") * F.lit(eps)
        out = out + step(F.lit(float(n)) + low) - step(low)
    return out


def pair_weight(u_a: Column, u_b: Column, ls_a: Column, ls_b: Column, ls_join: Column, eps: float = EPS, encoding: str = "plugin") -> Column:
    """The part of a pair's gain that depends on the pair."""
    joint = u_a + u_b
    space = u_a * ls_a + u_b * ls_b - joint * ls_join
    if encoding == "plugin":
        return lgamma_bits_col(joint + F.lit(eps)) + F.lit(lgamma_bits(eps)) - lgamma_bits_col(u_a + F.lit(eps)) - lgamma_bits_col(u_b + F.lit(eps)) + space
    xlog = lambda u: u * F.log2(u.cast("double"))
    return xlog(joint) - xlog(u_a) - xlog(u_b) + space


def lgamma_bits_np(x: np.ndarray) -> np.ndarray:
    """The column expression's arithmetic on arrays."""
    x = np.asarray(x, float)
    z = x + codes.SHIFT
    shift = sum(np.log(x + j) for j in range(codes.SHIFT))
    inv2, tail = 1 / (z * z), np.full_like(z, codes.STIRLING[-1])
    for c in reversed(codes.STIRLING[:-1]):
        tail = tail * inv2 + c
    return ((z - 0.5) * np.log(z) - z + 0.5 * math.log(2 * math.pi) + tail / z - shift) / codes.LN2


def group_weight(usages, log_sizes, hull_log_size: float, eps: float = EPS, encoding: str = "plugin") -> float:
    """The part of the gain of replacing m patterns by their hull that depends on them."""
    usages, log_sizes = np.asarray(usages, float), np.asarray(log_sizes, float)
    joint = float(usages.sum())
    space = float((usages * log_sizes).sum()) - joint * hull_log_size
    if encoding == "plugin":
        return lgamma_bits(joint + eps) + (len(usages) - 1) * lgamma_bits(eps) - float(lgamma_bits_np(usages + eps).sum()) + space
    return joint * math.log2(joint) - float((usages * np.log2(usages)).sum()) + space


def group_gain(usages, log_sizes, hull_log_size: float, k: int, n: int, grid: Grid, eps: float = EPS, encoding: str = "plugin") -> float:
    """Fall of the total length when m of k patterns are replaced by their hull."""
    return kappa(k, n, grid, eps, len(usages) - 1, encoding) + group_weight(usages, log_sizes, hull_log_size, eps, encoding)
