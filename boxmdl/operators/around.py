"""Relational operations around mining: marginals, totals by label, forecasts, as-of joins, comparison of runs."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .cells import _names


def marginals(disc: DataFrame) -> DataFrame:
    """Cell counts of every subset of the attributes (``b_i`` null where left out), with ``subset`` as a bit mask of the attributes left out; one cube."""
    names = _names(disc)
    return disc.cube(*names).agg(F.count(F.lit(1)).alias("usage"), F.grouping_id(*names).cast("long").alias("subset"))


def label_totals(placed: DataFrame, pattern: str, label: str) -> DataFrame:
    """``pattern, label, rows`` with subtotals by pattern and the grand total (nulls), by rollup; ``level`` tells them apart."""
    return placed.rollup(pattern, label).agg(F.count(F.lit(1)).alias("rows"), F.grouping_id(pattern, label).cast("long").alias("level"))


def cell_forecast(disc: DataFrame, error: float = 0.02) -> DataFrame:
    """``cells``: about how many non-empty cells there are, by a sketch of fixed size, before any cell is counted."""
    return disc.agg(F.approx_count_distinct(F.struct(*_names(disc)), error).alias("cells"))


def as_of(events: DataFrame, versions: DataFrame, time: str, key: str | None = None, columns: tuple[str, ...] = ()) -> DataFrame:
    """Every event with the `columns` of the last version at or before its time (of the same key).

    A union ordered by time, versions first at equal times, and the last
    non-null version before each event: no join on ranges.  Without a key give
    `events` one that spreads them (a day, a shard) and repeat the versions
    under it: a frame is worked through by one task.
    """
    by = [key] if key else []
    left = events.withColumns({"__event": F.lit(1), **{f"__{c}": F.lit(None) for c in columns}})
    right = versions.select(*by, F.col(time), F.lit(0).alias("__event"), *[F.col(c).alias(f"__{c}") for c in columns])
    both = left.unionByName(right, allowMissingColumns=True)
    ahead = Window.partitionBy(*by).orderBy(time, "__event").rowsBetween(Window.unboundedPreceding, 0)
    filled = both.withColumns({c: F.last(f"__{c}", ignorenulls=True).over(ahead) for c in columns})
    return filled.filter("__event = 1").select(*events.columns, *columns)


def compare(ours: DataFrame, theirs: DataFrame) -> DataFrame:
    """``side`` (both, ours, theirs) and the rows of two runs' tables, as multisets."""
    tagged = lambda df, side: df.select(F.lit(side).alias("side"), "*")
    same = tagged(ours.intersectAll(theirs), "both")
    return same.unionByName(tagged(ours.exceptAll(theirs), "ours")).unionByName(tagged(theirs.exceptAll(ours), "theirs"))


def equal_height_rows(df: DataFrame, attr: str, n_bins: int, order: tuple[str, ...] = ()) -> DataFrame:
    """``bin, lo, hi, rows`` of intervals of equal numbers of rows (values may repeat across them).

    As `ntile`, but from a range-partitioned sort and the totals of its
    partitions, so that no task orders all rows.
    """
    from .cells import with_row_ids

    n = df.count()
    ordered = df.select(attr, *order).repartitionByRange(attr, *order).sortWithinPartitions(attr, *order)
    small, large = n // n_bins, n % n_bins  # the first `large` intervals have a row more
    place = with_row_ids(ordered, "__row", 0)
    edge = large * (small + 1)
    at = F.when(F.col("__row") < edge, F.floor(F.col("__row") / F.lit(small + 1))).otherwise(large + F.floor((F.col("__row") - edge) / F.lit(max(1, small))))
    return place.groupBy((at + 1).cast("int").alias("bin")).agg(F.min(attr).alias("lo"), F.max(attr).alias("hi"), F.count(F.lit(1)).alias("rows"))
