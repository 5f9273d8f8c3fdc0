"""Pruning: several patterns replaced at once by the hull of two of them.

The pairs whose hull holds a third pattern are looked for with bit sets
(`kernel.Holders`), by the driver for few patterns and otherwise by tasks, each
for some of the patterns as one part of the pair; only the best of every task
come back, `top_n` at least.  `candidates` finds the same pairs with joins.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.codes import EPS
from ..plans import choose
from . import boxes as B
from . import kernel, miner, model
from .grid import Grid


def candidates(boxes: DataFrame, grid: Grid, n: int, k: int, eps: float = EPS, top_n: int | None = 1000, encoding: str = "plugin") -> DataFrame:
    """``a, b, held, gain``: the pairs whose hull holds `held` other patterns, those of the largest pair gain first."""
    if k > choose.ALL_PAIRS_CELLS:
        raise ValueError(f"{k} patterns are too many to join in threes; use search")
    side = lambda s: boxes.select(F.col("pid").alias(s), *(F.col(c).alias(f"{c}_{s}") for c in ("lo", "hi", "usage", "log_size")))
    pairs = side("a").join(F.broadcast(side("b")), F.col("a") < F.col("b"))  # at most ALL_PAIRS_CELLS boxes on each side
    hulls = pairs.withColumns({"lo": B.join_lo(F.col("lo_a"), F.col("lo_b")), "hi": B.join_hi(F.col("hi_a"), F.col("hi_b"))})
    third = F.broadcast(side("c").select("c", "lo_c", "hi_c"))
    held = hulls.join(third, (F.col("c") != F.col("a")) & (F.col("c") != F.col("b")) & B.contains(F.col("lo"), F.col("hi"), F.col("lo_c"), F.col("hi_c")))
    w = model.pair_weight(F.col("usage_a"), F.col("usage_b"), F.col("log_size_a"), F.col("log_size_b"), B.log_size(F.col("lo"), F.col("hi")), eps, encoding)
    counted = held.withColumn("gain", w + F.lit(model.kappa(k, n, grid, eps, 1, encoding))).groupBy("a", "b", "gain").agg(F.count(F.lit(1)).alias("held"))
    ordered = counted.select("a", "b", "held", "gain")
    return ordered.orderBy(F.desc("gain"), "a", "b").limit(top_n) if top_n else ordered


def search(spark, eps: float = EPS, encoding: str = "plugin"):
    """The search for pairs that `kernel.prune` calls."""

    def find(few: kernel.Patterns, rows: np.ndarray, top_n: int | None, floor: tuple[float, int] | None):
        k = few.size
        if k <= choose.PRUNE_LOCAL or k * len(rows) <= choose.PRUNE_LOCAL**2:
            return kernel.prune_pairs(few, rows.tolist(), top_n and max(top_n, choose.PRUNE_PAIRS), eps, encoding, floor)
        parts = min(k * len(rows) // 500_000 + 1, len(rows), 16 * spark.sparkContext.defaultParallelism)
        most = top_n and max(top_n, choose.PRUNE_PAIRS // parts)
        shared = spark.sparkContext.broadcast((few, rows))

        def run(batches):
            few, rows = shared.value
            for b in batches:
                for part in b.column(0).to_pylist():
                    # the rows with most pairs first, so that a floor is found soon
                    pairs, w, last = kernel.prune_pairs(few, rows[::-1][part::parts].tolist(), most, eps, encoding, floor)
                    yield pa.RecordBatch.from_arrays([pa.array([pairs.tobytes()], pa.binary()), pa.array([w.tobytes()], pa.binary()), pa.array([last and last[0]], pa.float64()), pa.array([last and last[1]], pa.int64())], names=["pairs", "w", "floor", "at"])

        # top_n pairs a task; all only where no limit was asked for
        got = spark.range(0, parts, 1, parts).mapInArrow(run, "pairs binary, w binary, floor double, at long").toArrow()
        shared.destroy()
        pairs, w = (np.concatenate([np.frombuffer(x.as_buffer(), t) for x in got[c]]) for c, t in (("pairs", np.int64), ("w", np.float64)))
        for last in zip(got["floor"].to_pylist(), got["at"].to_pylist(), strict=True):
            if last[0] is not None and (floor is None or (-last[0], last[1]) < (-floor[0], floor[1])):
                floor = last
        order = np.lexsort((pairs, -np.round(w, kernel.TIE)))
        order = order[kernel._until(pairs[order], w[order], floor)]
        return pairs[order], w[order], floor

    return find


def prune(boxes: DataFrame, grid: Grid, eps: float = EPS, top_n: int | None = 1000, order: str = "id", encoding: str = "plugin") -> tuple[DataFrame, DataFrame]:
    """The pruned boxes, and ``pid, to``: where each pattern went."""
    spark = boxes.sparkSession
    if choose.PRUNE_PATTERNS is not None and choose.unpruned(boxes.limit(choose.PRUNE_PATTERNS + 1).count()):
        raise ValueError("too many patterns to prune")
    ids, lo, hi, usage = miner._arrays(boxes)
    p = kernel.Patterns.of(ids, lo, hi, usage)
    run = kernel.Run(p)
    kernel.prune(p, run, grid, eps, top_n, order, encoding, search(spark, eps, encoding))
    moved = list(zip(ids.tolist(), p.ids[run.roots()[: len(ids)]].tolist(), strict=True))
    return miner._boxes_frame(spark, p, p.live()), spark.createDataFrame(moved, "pid long, to long")
