"""Non-empty cells of a discretised table, and conversions."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .grid import Grid


def discretise(df: DataFrame, grid: Grid, keep: list[str] = ()) -> DataFrame:
    """Interval indices ``b_0``, ``b_1``, ... of every row, with the columns in `keep`; a projection inside the scan."""
    return df.select(*keep, *grid.indices())


def _names(disc: DataFrame) -> list[str]:
    return sorted((c for c in disc.columns if c.startswith("b_")), key=lambda c: int(c[2:]))


def counts(disc: DataFrame) -> DataFrame:
    """Distinct index tuples with their numbers of rows: after partial counts one shuffle of at most one row per tuple and task."""
    return disc.groupBy(*_names(disc)).agg(F.count(F.lit(1)).alias("usage"))


def elementary(disc: DataFrame) -> DataFrame:
    """Cells ``cell_id, lo, hi, usage``; ids from 1 in lexicographic order of the indices.

    The ids come from a range-partitioned sort and the running totals of its
    partitions, so no step holds all cells in one task.
    """
    names = _names(disc)
    ordered = counts(disc).repartitionByRange(*names).sortWithinPartitions(*names)
    box = F.array(*names)
    return with_row_ids(ordered, "cell_id").select("cell_id", box.alias("lo"), box.alias("hi"), "usage")


def with_row_ids(ordered: DataFrame, name: str, first: int = 1) -> DataFrame:
    """Numbers the rows of a partition-wise ordered table; it is fixed by a checkpoint first, as both passes must see the same partitions."""
    from ..session import fixed

    local = fixed(ordered).withColumns({"__p": F.spark_partition_id(), "__i": F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))})
    ahead = Window.orderBy("__p").rowsBetween(Window.unboundedPreceding, -1)
    starts = local.groupBy("__p").agg(F.count(F.lit(1)).alias("__n")).select("__p", F.coalesce(F.sum("__n").over(ahead), F.lit(0)).alias("__before"))
    return local.join(F.broadcast(starts), "__p").withColumn(name, F.col("__before") + F.col("__i") + first).drop("__p", "__i", "__before")  # one row per partition


def n_intervals_nonempty(disc: DataFrame) -> DataFrame:
    """Non-empty intervals over all attributes (``n_intervals``), from the cells."""
    names = _names(disc)
    return counts(disc).agg(sum((F.count_distinct(c) for c in names[1:]), F.count_distinct(names[0])).alias("n_intervals"))


def hull(df: DataFrame, attrs: list[str], by: str) -> DataFrame:
    """The smallest box around the rows of each group: ``by, usage, lo, hi`` in attribute values."""
    los, his = ([f(F.col(a).cast("double")).alias(f"{p}{i}") for i, a in enumerate(attrs)] for p, f in (("l", F.min), ("h", F.max)))
    grouped = df.groupBy(by).agg(F.count(F.lit(1)).alias("usage"), *los, *his)
    return grouped.select(by, "usage", F.array(*[f"l{i}" for i in range(len(attrs))]).alias("lo"), F.array(*[f"h{i}" for i in range(len(attrs))]).alias("hi"))


def hull_cells(disc: DataFrame, by: str) -> DataFrame:
    """As `hull`, in interval indices: boxes ``by, usage, lo, hi``."""
    return hull(disc, _names(disc), by).withColumns({s: F.transform(s, lambda x: x.cast("int")) for s in ("lo", "hi")})


def to_real(boxes: DataFrame, grid: Grid) -> DataFrame:
    """`boxes` with ``rlo`` and ``rhi``: lower edge of the first and upper edge of the last interval of every side."""
    edges = F.array(*[F.array(*[F.lit(float(e)) for e in a.edges()]) for a in grid.axes])
    at = lambda side, shift: F.zip_with(edges, side, lambda e, i: F.element_at(e, i + shift))
    return boxes.withColumns({"rlo": at("lo", 1), "rhi": at("hi", 2)})
