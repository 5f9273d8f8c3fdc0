"""Measures of pattern sets: lengths, redundancy, accuracy, agreement with known boxes.

Measures over objects work on cells weighted by usage; only labels need the
rows.  Pattern sets are small; where a side is broadcast it is one.
"""

from __future__ import annotations

from functools import reduce
from operator import and_

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..session import fixed
from . import boxes as B
from . import cells as C
from .grid import Grid


#: Tiles of the first side in which boxes of two sets meet.
TILES = 64


def compression_ratio(report: dict) -> float:
    """Total length over that of the cells alone; smaller is better."""
    return report["end_bits"] / report["start_bits"]


def length_ratio(baseline_bits: float, ours_bits: float) -> float:
    return baseline_bits / ours_bits


def seconds_per_pattern(report: dict) -> float:
    return report["seconds"] / max(1, report["patterns"])


def candidate_bounds(report: dict) -> dict:
    """Evaluated candidates against the bounds in the number of cells: quadratic a round, cubic in all."""
    k = report["cells"]
    return {"most_in_round": max(report["explored"], default=0), "round_bound": k * k, "all": sum(report["explored"]), "bound": k**3}


def occurrences(boxes: DataFrame, cells: DataFrame) -> DataFrame:
    """``pid, cell_id, usage`` of every cell inside a box, whether or not the box encodes it.

    Cells and boxes meet in tiles along the two sides on which the boxes are
    shortest; a tile is as wide as a box is there on average, so a box is
    written out a few times whatever the grid.
    """
    sides = boxes.select(F.posexplode(F.zip_with("hi", "lo", lambda h, low: h - low + 1)).alias("side", "span")).groupBy("side").agg(F.avg("span").alias("span")).collect()  # a row for each attribute
    chosen = sorted((r.span, r.side) for r in sides)[:2]
    tile = lambda c, side, span: F.floor(F.element_at(c, side + 1) / F.lit(max(1, round(span)))).cast("int")
    spans, at = boxes.select("pid", F.col("lo").alias("blo"), F.col("hi").alias("bhi")), cells.select("cell_id", F.col("lo").alias("clo"), F.col("hi").alias("chi"), "usage")
    for i, (span, side) in enumerate(chosen):
        spans = spans.withColumn(f"t{i}", F.explode(F.sequence(tile("blo", side, span), tile("bhi", side, span))))
        at = at.withColumn(f"t{i}", tile("clo", side, span))
    # side by side, not as functions on arrays, which Spark does not compile
    inside = reduce(and_, [(F.col("blo")[r.side] <= F.col("clo")[r.side]) & (F.col("chi")[r.side] <= F.col("bhi")[r.side]) for r in sides], F.lit(True))
    if not chosen:
        return at.limit(0).select(F.lit(0).cast("long").alias("pid"), "cell_id", "usage")
    return at.join(spans, [f"t{i}" for i in range(len(chosen))]).filter(inside).select("pid", "cell_id", "usage")


def support(boxes: DataFrame, cells: DataFrame) -> DataFrame:
    """``pid, support``: rows inside each box."""
    inside = occurrences(boxes, cells).groupBy("pid").agg(F.sum("usage").alias("support"))
    return boxes.select("pid").join(inside, "pid", "left").select("pid", F.coalesce("support", F.lit(0)).cast("long").alias("support"))


def cover_is_partition(boxes: DataFrame, lineage: DataFrame, cells: DataFrame) -> DataFrame:
    """``rows, usage, cells, encoded, outside``: every row is encoded once, by a box that holds its cell."""
    held = cells.join(lineage, "cell_id", "left")
    at = boxes.select("pid", F.col("lo").alias("blo"), F.col("hi").alias("bhi"), F.col("usage").alias("u"))
    seen = held.select("cell_id", F.col("lo").alias("clo"), F.col("hi").alias("chi"), "usage", "pid").join(at, "pid", "left")
    totals = boxes.agg(F.sum("usage").alias("usage"))
    inside = F.coalesce(B.contains(F.col("blo"), F.col("bhi"), F.col("clo"), F.col("chi")), F.lit(False))
    return seen.agg(F.sum("usage").alias("rows"), F.count(F.lit(1)).alias("cells"), F.count_distinct("cell_id").alias("encoded"), F.sum((~inside).cast("long")).alias("outside")).crossJoin(totals).select("rows", "usage", "cells", "encoded", "outside")


def jaccard_pairs(boxes: DataFrame, cells: DataFrame | None, inside: DataFrame | None = None) -> DataFrame:
    """``a, b, jaccard`` of the occurrence sets (`inside`, or those of the cells) of pairs that share rows (others have 0)."""
    inside = occurrences(boxes, cells) if inside is None else inside
    x, y = inside.select("cell_id", "usage", F.col("pid").alias("a")), inside.select("cell_id", F.col("pid").alias("b"))
    both = x.join(y, "cell_id").filter("a < b").groupBy("a", "b").agg(F.sum("usage").alias("both"))
    sizes = inside.groupBy("pid").agg(F.sum("usage").alias("size"))
    size = lambda s: sizes.select(F.col("pid").alias(s), F.col("size").alias(f"size_{s}"))
    return both.join(size("a"), "a").join(size("b"), "b").select("a", "b", (F.col("both") / (F.col("size_a") + F.col("size_b") - F.col("both"))).alias("jaccard"))


def jaccard_all(boxes: DataFrame, cells: DataFrame) -> DataFrame:
    """``pairs, mean_jaccard`` over all pairs of patterns."""
    k = boxes.agg(F.count(F.lit(1)).alias("k"))
    total = jaccard_pairs(boxes, cells).agg(F.coalesce(F.sum("jaccard"), F.lit(0.0)).alias("total"))
    pairs = F.col("k") * (F.col("k") - 1) / 2
    return k.crossJoin(total).select(pairs.cast("long").alias("pairs"), F.when(pairs > 0, F.col("total") / pairs).alias("mean_jaccard"))


def jaccard_topk(boxes: DataFrame, cells: DataFrame | None, k: int = 10, inside: DataFrame | None = None) -> DataFrame:
    """``pairs, mean_jaccard`` over each pattern's k most similar others, repeated pairs once; ties to the smaller id.

    Patterns that share no row count with 0, after those that do, by id.
    """
    # both are read several times, and are far fewer rows than what they are found among
    near = fixed(jaccard_pairs(boxes, cells, fixed(occurrences(boxes, cells)) if inside is None else inside))
    ways = near.select(F.col("a").alias("p"), F.col("b").alias("q"), "jaccard").unionByName(near.select(F.col("b").alias("p"), F.col("a").alias("q"), "jaccard"))
    # a list is filled up from the least ids: beside itself and its overlaps a pattern needs k of them at most
    most = ways.groupBy("p").count().agg(F.max("count")).first()[0] or 0
    spare = boxes.select(F.col("pid").alias("q")).orderBy("q").limit(k + 1 + most)
    others = boxes.select(F.col("pid").alias("p")).join(F.broadcast(spare), F.col("p") != F.col("q"))
    filled = ways.unionByName(others.join(ways, ["p", "q"], "left_anti").withColumn("jaccard", F.lit(0.0)))
    top = filled.withColumn("r", F.row_number().over(Window.partitionBy("p").orderBy(F.desc("jaccard"), "q"))).filter(F.col("r") <= k)
    pairs = top.select(F.least("p", "q").alias("a"), F.greatest("p", "q").alias("b"), "jaccard").dropDuplicates(["a", "b"])
    return pairs.agg(F.count(F.lit(1)).alias("pairs"), F.avg("jaccard").alias("mean_jaccard"))


def accuracy(boxes: DataFrame, disc: DataFrame, label: str, over: str = "support", lineage: DataFrame | None = None, cells: DataFrame | None = None) -> DataFrame:
    """``pid, majority, rows, accuracy``: share of the majority class among the rows in a box ('support') or encoded by it ('cover').

    `disc` holds interval indices and the label; ties go to the lesser label.
    """
    names = C._names(disc)
    at = disc.filter(F.col(label).isNotNull()).groupBy(*names, F.col(label).cast("string").alias("label")).agg(F.count(F.lit(1)).alias("usage"))
    spot = F.array(*names)
    if over == "cover":
        ours = cells.join(lineage, "cell_id").select(F.col("lo").alias("spot"), "pid")
        rows = at.select(spot.alias("spot"), "label", "usage").join(ours, "spot").select("pid", "label", "usage")
    else:
        spread = at.select(spot.alias("lo"), spot.alias("hi"), "usage", F.struct("label", spot.alias("spot")).alias("cell_id"))
        rows = occurrences(boxes, spread).select("pid", "cell_id.label", "usage")
    return majority(rows)


def majority(rows: DataFrame) -> DataFrame:
    """``pid, majority, rows, accuracy`` from ``pid, label, usage``."""
    by_label = rows.groupBy("pid", "label").agg(F.sum("usage").alias("c"))
    best = F.max(F.struct("c", F.lit(0)))["c"]
    top = by_label.withColumn("best", F.max("c").over(Window.partitionBy("pid")))
    return top.groupBy("pid").agg(F.min(F.when(F.col("c") == F.col("best"), F.col("label"))).alias("majority"), F.sum("c").alias("rows"), best.alias("top")).select("pid", "majority", "rows", (F.col("top") / F.col("rows")).alias("accuracy"))


def mean_accuracy(per_pattern: DataFrame, weight: str | None = None) -> DataFrame:
    """Plain mean over the patterns, or one weighted by `weight` (a column, e.g. ``rows``)."""
    value = F.avg("accuracy") if weight is None else F.sum(F.col("accuracy") * F.col(weight)) / F.sum(weight)
    return per_pattern.agg(F.count(F.lit(1)).alias("patterns"), value.alias("mean_accuracy"))


def confusion(boxes: DataFrame, disc: DataFrame, label: str, classes: list[str]) -> DataFrame:
    """Pattern by class counts."""
    names = C._names(disc)
    spot = F.array(*names)
    at = disc.groupBy(*names, F.col(label).cast("string").alias("label")).agg(F.count(F.lit(1)).alias("usage"))
    spread = at.select(spot.alias("lo"), spot.alias("hi"), "usage", F.struct("label", spot.alias("spot")).alias("cell_id"))
    return occurrences(boxes, spread).select("pid", "cell_id.label", "usage").groupBy("pid").pivot("label", classes).agg(F.sum("usage"))


def _product(parts: Column) -> Column:
    return F.aggregate(parts, F.lit(1.0), lambda s, x: s * x)


def box_jaccard(lo_a, hi_a, lo_b, hi_b) -> Column:
    """Area of the common part over the area of the hull (not of the union); bounds are real."""
    inner = F.zip_with(F.zip_with(hi_a, hi_b, lambda p, q: F.least(p, q)), F.zip_with(lo_a, lo_b, lambda p, q: F.greatest(p, q)), lambda h, low: F.greatest(h - low, F.lit(0.0)))
    outer = F.zip_with(F.zip_with(hi_a, hi_b, lambda p, q: F.greatest(p, q)), F.zip_with(lo_a, lo_b, lambda p, q: F.least(p, q)), lambda h, low: h - low)
    whole = _product(outer)
    return F.when(whole > 0, _product(inner) / whole).otherwise(0.0)


def _overlapping(ours: DataFrame, others: DataFrame, key: str, other_key: str, by: list[str]) -> DataFrame:
    """``by, a, b, jaccard`` of the pairs of boxes of one group that share space.

    The boxes meet in tiles of the first side, each pair in the first tile that
    both reach; pairs without a common part have 0 and are not written out.
    """
    ends = ours.select("rlo", "rhi").unionByName(others.select("rlo", "rhi")).agg(F.min(F.element_at("rlo", 1)).alias("lo"), F.max(F.element_at("rhi", 1)).alias("hi")).first()
    wide = ((ends.hi - ends.lo) / TILES if ends.lo is not None else 0.0) or 1.0
    tile = lambda v: F.least(F.lit(TILES - 1), F.floor((F.element_at(v, 1) - F.lit(ends.lo or 0.0)) / F.lit(wide))).cast("int")

    def side(df, name, s):
        placed = df.select(*by, F.col(name).alias(s), F.col("rlo").alias(f"lo_{s}"), F.col("rhi").alias(f"hi_{s}"), tile("rlo").alias(f"t_{s}"), tile("rhi").alias(f"u_{s}"))
        return placed.withColumn("t", F.explode(F.sequence(f"t_{s}", f"u_{s}")))

    both = side(ours, key, "a").join(side(others, other_key, "b"), [*by, "t"]).filter(F.col("t") == F.greatest("t_a", "t_b"))
    return both.select(*by, "a", "b", box_jaccard(F.col("lo_a"), F.col("hi_a"), F.col("lo_b"), F.col("hi_b")).alias("jaccard")).filter("jaccard > 0")


def box_jaccard_mean(real: DataFrame, key: str = "pid", by: list[str] = ()) -> DataFrame:
    """``pairs, mean_jaccard`` of the boxes (``rlo, rhi``) over all pairs, for each group of the columns `by`."""
    by = list(by)
    total = _overlapping(real, real, key, key, by).filter("a < b").groupBy(*by).agg(F.sum("jaccard").alias("total"))
    count = real.groupBy(*by).agg(F.count(F.lit(1)).alias("k"))
    joined = count.join(total, by, "left") if by else count.crossJoin(total)  # one row each
    pairs = (F.col("k") * (F.col("k") - 1) / 2).cast("long")
    return joined.select(*by, pairs.alias("pairs"), F.when(pairs > 0, F.coalesce("total", F.lit(0.0)) / pairs).alias("mean_jaccard"))


def jcd(ours: DataFrame, others: DataFrame, key: str = "pid", other_key: str = "tid", by: list[str] = ()) -> DataFrame:
    """``boxes, jcd``: mean over `ours` of the best box Jaccard with one of `others` (of the same group)."""
    by = list(by)
    best = _overlapping(ours, others, key, other_key, by).groupBy(*by, "a").agg(F.max("jaccard").alias("best"))
    every = ours.select(*by, F.col(key).alias("a")).join(best, [*by, "a"], "left")
    return every.groupBy(*by).agg(F.count(F.lit(1)).alias("boxes"), F.avg(F.coalesce("best", F.lit(0.0))).alias("jcd"))


def describe(df: DataFrame, attrs: list[str], grid: Grid, label: str | None = None) -> DataFrame:
    """``n, k, n_intervals, classes`` of a workload under a grid."""
    kinds = [F.count_distinct(a.index(F.col(a.attr).cast("double"))).alias(f"__kinds_{i}") for i, a in enumerate(grid.axes)]
    classes = F.count_distinct(label) if label else F.lit(0).cast("long")
    row = df.agg(F.count(F.lit(1)).alias("__n"), *kinds, classes.alias("__classes"))
    total = sum((F.col(f"__kinds_{i}") for i in range(1, len(kinds))), F.col("__kinds_0"))
    return row.select(F.col("__n").alias("n"), F.lit(len(attrs)).cast("long").alias("k"), total.alias("n_intervals"), F.col("__classes").alias("classes"))
