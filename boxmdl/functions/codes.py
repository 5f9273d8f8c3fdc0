"""Code lengths in bits, each as a Python function and as a Column expression.

Spark has no gamma function, so `lgamma_bits` is built from arithmetic that
stays in generated code: the argument is shifted up by 8 and a Stirling series
is corrected by the logarithm of the rising product.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

# The constant of the universal integer code (quoted as about
# 2.87 in the reference), the default smoothing (the reference gives none), and
# the Stirling coefficients of 1/z, 1/z**3, ...
C0 = 2.865064
EPS = 0.5
STIRLING = (1 / 12, -1 / 360, 1 / 1260, -1 / 1680, 1 / 1188)
LN2 = math.log(2.0)
SHIFT = 8


def universal_int_bits(n: int, c0: float = C0) -> float:
    """Bits of a positive integer in the universal code; 0 counts no bits."""
    if n < 1:
        return 0.0
    total, term = math.log2(c0), float(n)
    while (term := math.log2(term)) > 0:
        total += term
    return total


def universal_int_bits_col(n: Column, c0: float = C0) -> Column:
    """As `universal_int_bits`: five nested logarithms cover every LONG."""
    total, term, zero = F.lit(math.log2(c0)), n.cast("double"), F.lit(0.0)
    for _ in range(5):
        term = F.when(term > 1, F.log2(term)).otherwise(zero)
        total = total + term
    return F.when(n >= 1, total).otherwise(zero)


def lgamma_bits(x: float) -> float:
    return math.lgamma(x) / LN2


def lgamma_bits_col(x: Column) -> Column:
    """log2 of the gamma function for x > 0."""
    z = x + F.lit(float(SHIFT))
    product = x
    for j in range(1, SHIFT):
        product = product * (x + F.lit(float(j)))
    inverse, square = F.lit(1.0) / z, F.lit(1.0) / (z * z)
    tail = F.lit(STIRLING[-1])
    for c in reversed(STIRLING[:-1]):
        tail = tail * square + F.lit(c)
    ln = (z - F.lit(0.5)) * F.ln(z) - z + F.lit(0.5 * math.log(2 * math.pi)) + tail * inverse
    # for large x the rising product overflows long before a logarithm of a sum does
    shift = F.when(x < 1e30, F.ln(product)).otherwise(F.lit(float(SHIFT)) * F.ln(x))
    return (ln - shift) / F.lit(LN2)


def lgamma_step_bits(x: float, step: float) -> float:
    """lgamma(x + step) - lgamma(x) in bits, without losing digits for large x."""
    if x < 1e5:
        return (math.lgamma(x + step) - math.lgamma(x)) / LN2
    stirling = lambda y: (y - 0.5) * math.log1p((y - x) / x) - (y - x) + 1 / (12 * y)
    return (step * math.log(x) + stirling(x + step) - 1 / (12 * x)) / LN2


def plugin_sequence_bits(usages, eps: float = EPS) -> float:
    """Prequential plug-in code of a whole sequence in which the patterns occur `usages` times."""
    usages = [u for u in usages]
    n, k = sum(usages), len(usages)
    if not k:
        return 0.0
    return lgamma_bits(n + eps * k) - lgamma_bits(eps * k) - sum(lgamma_bits(u + eps) for u in usages) + k * lgamma_bits(eps)


def plugin_sequence_bits_agg(usage: Column, eps: float = EPS) -> Column:
    """As an aggregate over a table of patterns."""
    n, k = F.sum(usage).cast("double"), F.count(usage).cast("double")
    return lgamma_bits_col(n + F.lit(eps) * k) - lgamma_bits_col(F.lit(eps) * k) - F.sum(lgamma_bits_col(usage + F.lit(eps))) + k * F.lit(lgamma_bits(eps))


def plugin_step_bits(df: DataFrame, pattern: str, order: list, n_patterns: int, eps: float = EPS) -> DataFrame:
    """`df` with ``seen`` (earlier uses of the row's pattern), ``position`` (earlier rows) and ``bits`` of its step.

    The global position needs one order over all rows: this is the code of one
    sequence; keep sequences apart by `order` and partition them beforehand.
    """
    own = Window.partitionBy(pattern).orderBy(*order)
    all_rows = Window.orderBy(*order)
    seen = F.row_number().over(own) - 1
    position = F.row_number().over(all_rows) - 1
    return df.withColumns({"seen": seen.cast("long"), "position": position.cast("long")}).withColumn("bits", -F.log2((F.col("seen") + F.lit(eps)) / (F.col("position") + F.lit(eps * n_patterns))))


def shannon_bits(usages) -> float:
    """Optimal prefix code when the usages are known: sum of u log(n/u)."""
    n = sum(usages)
    return sum(u * math.log2(n / u) for u in usages if u)


def shannon_bits_agg(usage: Column) -> Column:
    n = F.sum(usage).cast("double")
    inner = F.sum(F.when(usage > 0, usage * F.log2(usage.cast("double"))).otherwise(0.0))
    return F.when(n > 0, n * F.log2(n) - inner).otherwise(0.0)


def uniform_bits(n: int, k: int) -> float:
    """Every one of n code words costs log k."""
    return n * math.log2(k) if k else 0.0
