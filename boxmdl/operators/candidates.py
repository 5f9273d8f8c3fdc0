"""Candidate pairs and their weights on DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import boxes as B
from .model import pair_weight


def weighted(pairs: DataFrame, boxes: DataFrame, eps: float, encoding: str = "plugin") -> DataFrame:
    """``a, b, lo, hi, w`` of pairs whose two parts are among `boxes`; parts gone by now drop out in the joins."""
    side = lambda s: boxes.select(F.col("pid").alias(s), *(F.col(c).alias(f"{c}_{s}") for c in ("lo", "hi", "usage", "log_size")))
    both = pairs.select("a", "b").join(side("a"), "a").join(side("b"), "b")
    joint = both.withColumns({"lo": B.join_lo(F.col("lo_a"), F.col("lo_b")), "hi": B.join_hi(F.col("hi_a"), F.col("hi_b"))})
    w = pair_weight(F.col("usage_a"), F.col("usage_b"), F.col("log_size_a"), F.col("log_size_b"), B.log_size(F.col("lo"), F.col("hi")), eps, encoding)
    return joint.select("a", "b", "lo", "hi", w.alias("w"))


def contracted(edges: DataFrame, merges: DataFrame) -> DataFrame:
    """Neighbour edges after merges: ends that were merged become their hull; loops and repeats go."""
    moved = merges.select(F.explode(F.array("a", "b")).alias("old"), "pid")
    for end in ("a", "b"):
        edges = edges.join(moved.select(F.col("old").alias(end), F.col("pid").alias(f"new_{end}")), end, "left")
    ends = edges.select(F.coalesce("new_a", "a").alias("x"), F.coalesce("new_b", "b").alias("y")).filter("x != y")
    return ends.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).dropDuplicates()


def with_new(boxes: DataFrame, first_new: int) -> DataFrame:
    """Every pair that holds a box of id `first_new` or above."""
    ids = boxes.select(F.col("pid").alias("b"))
    new = ids.filter(F.col("b") >= first_new)
    return boxes.select(F.col("pid").alias("a")).join(new, F.col("a") < F.col("b"))
