"""One mining round on DataFrames: greedy matching of candidates, distributed.

The greedy order is fixed by the pair weights alone, so taking every edge that
is the best edge of both its ends, again and again, takes the same edges as
going down the sorted list; the last few edges are matched on the driver, in
the same order.  The list of taken edges is then cut at the first
whose gain, with the number of patterns there, is not positive.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans import choose
from ..session import fixed
from . import kernel
from .cells import with_row_ids
from .grid import Grid
from .kernel import TIE, pair_mix
from .model import kappa_col


def _order(tie: str) -> Column:
    """Greatest for the pair to take first.

    With 'first' and 'last' chains of equal pairs are taken from one end, in as
    many rounds as they are long; with 'hash' the rounds grow with the
    logarithm of their number.
    """
    sign = 1 if tie == "last" else -1
    mix = (-pair_mix(F.col("a"), F.col("b")) if tie == "hash" else F.lit(0)).cast("long")
    return F.struct(F.round("w", TIE).alias("w"), mix.alias("m"), (sign * F.col("a")).alias("x"), (sign * F.col("b")).alias("y"))


def greedy_matching(candidates: DataFrame, tie: str = "hash") -> DataFrame:
    """Edges (``a, b, w``) that greedy matching by falling weight takes."""
    sign = 1 if tie == "last" else -1
    rest = fixed(candidates.select("a", "b", "w"))
    taken = None
    while (left := rest.count()) > choose.MATCHING_LOCAL:
        # the best edge of both its ends is the best of two ends
        ends = rest.withColumn("o", _order(tie)).select(F.explode(F.array("a", "b")).alias("v"), F.struct("o", "w").alias("o"))
        both = ends.groupBy("v").agg(F.max("o").alias("o")).groupBy("o").agg(F.count(F.lit(1)).alias("n")).filter("n = 2")
        agreed = fixed(both.select((sign * F.col("o.o.x")).alias("a"), (sign * F.col("o.o.y")).alias("b"), F.col("o.w").alias("w")))
        taken = agreed if taken is None else taken.unionByName(agreed)
        gone = agreed.select(F.explode(F.array("a", "b")).alias("v"))
        rest = fixed(rest.join(gone, F.col("a") == F.col("v"), "left_anti").join(gone, F.col("b") == F.col("v"), "left_anti"))
    if left or taken is None:
        last = _matched_here(rest, tie)
        taken = last if taken is None else taken.unionByName(last)
    return taken.withColumn("o", _order(tie))


def _matched_here(rest: DataFrame, tie: str) -> DataFrame:
    """`greedy_matching` of at most MATCHING_LOCAL edges, on the driver."""
    held = rest.toArrow()
    a, b, w = (held[c].to_numpy() for c in ("a", "b", "w"))
    ids = np.unique(np.concatenate([a, b]))
    pairs = kernel.packed(np.searchsorted(ids, a), np.searchsorted(ids, b))
    by_pair = np.argsort(pairs)
    pairs, w = pairs[by_pair], w[by_pair]
    order = kernel._preferred(w, pairs, ids, tie)
    x, y = pairs[order] >> 32, pairs[order] & kernel._LOW
    won = kernel.greedy_matching(x, y, len(ids))
    return rest.sparkSession.createDataFrame(pa.table({"a": ids[x[won]], "b": ids[y[won]], "w": w[order][won]}))


def accepted(matching: DataFrame, k: int, n: int, grid: Grid, eps: float, encoding: str, gain_mode: str, next_id: int) -> DataFrame:
    """The edges up to the first without gain: ``a, b, pid, step, k_before, gain``."""
    ordered = matching.repartitionByRange(F.col("o").desc()).sortWithinPartitions(F.col("o").desc())
    placed = with_row_ids(ordered, "step").withColumn("k_before", F.lit(k) - (F.col("step") - 1))
    at = F.col("k_before") if gain_mode == "refreshed" else F.lit(k)
    gains = placed.withColumn("gain", F.when(F.col("k_before") > 1, F.col("w") + kappa_col(at, n, grid, eps, encoding)).otherwise(F.lit(float("-inf"))))
    stop = gains.filter("gain <= 0").agg(F.min("step")).first()[0]
    kept = gains if stop is None else gains.filter(F.col("step") < stop)
    return fixed(kept.select("a", "b", (F.col("step") + (next_id - 1)).alias("pid"), "step", "k_before", "gain"))
