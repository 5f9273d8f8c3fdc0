"""Itemset baseline: a code table over binarised data that shrinks the length of data and table.

Every interval is an item; a row is as many items as attributes.  Itemsets are
grown by joining two of the table that are used together, most often first,
and kept if the total length falls.  Rows are covered greedily, longer and
more frequent itemsets first, so itemsets that cover one row never overlap.
Works on distinct cells weighted by their counts.
"""

from __future__ import annotations

import math
import pickle
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import boxes as B
from ..grid import Grid
from .limits import Limits


def offsets(grid: Grid) -> list[int]:
    out, at = [], 0
    for a in grid.axes:
        out.append(at)
        at += a.n_bins
    return out


def binarise(disc: DataFrame, grid: Grid, keep: list[str] = ()) -> DataFrame:
    """``items`` of every row: one number for each attribute's interval."""
    at = offsets(grid)
    return disc.select(*keep, F.array(*[(F.col(f"b_{i}") + F.lit(o)).cast("int") for i, o in enumerate(at)]).alias("items"))


def item_support(binary: DataFrame) -> DataFrame:
    """``item, support``."""
    return binary.select(F.explode("items").alias("item")).groupBy("item").agg(F.count(F.lit(1)).alias("support"))


def pair_support(binary: DataFrame) -> DataFrame:
    """``x, y, support`` of item pairs in one row, from the rows' own items (no join between rows)."""
    left = binary.select("items", F.posexplode("items").alias("i", "x"))
    pairs = left.select("x", F.explode(F.slice("items", F.col("i") + 2, F.size("items"))).alias("y"))
    return pairs.groupBy("x", "y").agg(F.count(F.lit(1)).alias("support"))


class CodeTable:
    """Itemsets over distinct rows, the greedy cover of every row, and usages; kept up to date row by row."""

    def __init__(self, rows: np.ndarray, weight: np.ndarray):
        self.rows, self.weight = rows, weight
        self.support: dict[frozenset, float] = {}  # of itemsets of two items and more
        self.at: dict[int, np.ndarray] = {}  # rows of each item, ascending
        counts: Counter = Counter()
        for c in range(rows.shape[1]):
            order = np.argsort(rows[:, c], kind="stable").astype(np.int32)
            items, starts = np.unique(rows[order, c], return_index=True)
            for item, own in zip(items.tolist(), np.split(order, starts[1:]), strict=True):
                self.at[item] = own
                counts[item] += float(weight[own].sum())
        total = sum(counts.values())
        self.item_bits = {i: -math.log2(n / total) for i, n in counts.items()}
        self.holders: dict[frozenset, np.ndarray] = {}
        self.single = {i: frozenset([i]) for i in counts}
        self.covers: dict[int, list[frozenset]] = {}  # of rows that are not covered by single items
        self.usage: Counter = Counter()
        self.together: Counter = Counter()
        self._count(range(len(rows)), 1)

    def rows_with(self, s: frozenset) -> np.ndarray:
        first, *rest = sorted((self.at[i] for i in s), key=len)
        for own in rest:
            first = first[np.isin(first, own, assume_unique=True)]
        return first

    def cover_of(self, r: int) -> list[frozenset]:
        return self.covers.get(r) or [self.single[i] for i in self.rows[r].tolist()]

    def _count(self, at, sign: int) -> None:
        for r in at:
            parts, w = self.cover_of(r), sign * float(self.weight[r])
            for i, a in enumerate(parts):
                self.usage[a] += w
                for b in parts[:i]:
                    self.together[frozenset((a, b))] += w

    def _cover(self, at: np.ndarray) -> dict[int, list[frozenset]]:
        """The itemsets that cover the given rows: longer and more frequent ones first."""
        items = {r: set(self.rows[r].tolist()) for r in at.tolist()}
        found: dict[int, list[frozenset]] = {r: [] for r in items}
        for s in sorted(self.support, key=lambda s: (-len(s), -self.support[s], sorted(s))):
            for r in np.intersect1d(self.holders[s], at, assume_unique=True).tolist():
                if s <= items[r]:
                    items[r] -= s
                    found[r].append(s)
        for r, rest in items.items():
            found[r] += [self.single[i] for i in sorted(rest)]
        return found

    def bits(self) -> float:
        used = [(s, u) for s, u in self.usage.items() if u > 0]
        total = sum(u for _, u in used)
        return sum(-(u + 1) * math.log2(u / total) + sum(self.item_bits[i] for i in s) for s, u in used)

    def change(self, add: frozenset | None = None, drop: frozenset | None = None):
        """Adds or drops an itemset; only rows that hold it (or use it) are covered anew.  Returns how to take it back."""
        if add is not None:
            self.holders[add] = at = self.rows_with(add)
            self.support[add] = float(self.weight[at].sum())
        else:
            at = np.array([r for r in self.holders[drop].tolist() if drop in self.covers.get(r, ())], np.int64)
            kept = self.support.pop(drop)
        old = {r: self.cover_of(r) for r in at.tolist()}
        self._count(old, -1)
        for r, parts in self._cover(at).items():
            self.covers[r] = parts
        self._count(old, 1)

        def undo():
            self._count(old, -1)
            for r, parts in old.items():
                self.covers[r] = parts
            self._count(old, 1)
            if add is not None:
                del self.support[add], self.holders[add]
            else:
                self.support[drop] = kept

        return undo


@dataclass
class ItemsetResult:
    itemsets: list[tuple[list[int], float]]  # items and usage
    start_bits: float
    end_bits: float
    evaluated: int
    status: str = "ok"
    seconds: float = 0.0


def mine_rows(rows: np.ndarray, weight: np.ndarray, prune: bool = True, limits: Limits | None = None) -> ItemsetResult:
    """Itemsets of distinct rows of items; ends when no candidate shortens the length, or at the time limit."""
    limits = limits or Limits()
    table = CodeTable(rows, weight)
    now = start = table.bits()
    evaluated, refused, won = 0, set(), True
    while won and not limits.over_time():
        won = False
        while not limits.over_time():
            options = []
            for pair, n in table.together.items():
                if n > 0 and len(pair) == 2:
                    joint = frozenset().union(*pair)
                    if joint not in refused and joint not in table.support:
                        options.append((n, sorted(joint)))
            if not options:
                break
            options.sort(key=lambda x: (-x[0], x[1]))
            for _, items in options:
                joint = frozenset(items)
                before = dict(table.usage)
                undo = table.change(add=joint)
                evaluated += 1
                if (length := table.bits()) < now:
                    now, won = length, True
                    fallen = [s for s in table.support if s != joint and table.usage[s] < before.get(s, 0)]
                    for s in sorted(fallen, key=lambda s: (table.usage[s], sorted(s))) if prune else ():
                        back = table.change(drop=s)
                        if (length := table.bits()) < now:
                            now = length
                        else:
                            back()
                    break
                undo()
                refused.add(joint)
                if limits.over_time():
                    break
            else:
                break
        refused.clear()  # what was refused may pay by now: the search ends with a whole pass without gain
    found = [(sorted(s), u) for s, u in sorted(table.usage.items(), key=lambda x: (-x[1], sorted(x[0]))) if u > 0]
    return ItemsetResult(found, start, now, evaluated, limits.status, limits.spent())


def mine(cells: DataFrame, grid: Grid, prune: bool = True, seconds: float | None = None) -> ItemsetResult:
    """Itemsets from cells (``lo, usage``), found by one task, whatever their number; `seconds` may end the search (status 'time')."""
    k = len(grid.axes)
    at = np.array(offsets(grid))

    def run(batches):
        found = pa.Table.from_batches([b for b in batches if b.num_rows])
        order = np.argsort(found["cell_id"].to_numpy())
        rows = found["lo"].combine_chunks().flatten().to_numpy().reshape(-1, k)[order] + at
        result = mine_rows(rows, found["usage"].to_numpy().astype(float)[order], prune, Limits(seconds))
        yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(result)], pa.binary())], names=["result"])

    # the search is one process's whatever the cells' number; a task has more room than the driver
    return pickle.loads(cells.select("cell_id", "lo", "usage").repartition(1).mapInArrow(run, "result binary").first().result)


def sides(result: ItemsetResult, grid: Grid) -> list[tuple[list[int], list[int], int]]:
    """(lo, hi, usage) of the itemsets as boxes: an attribute without an item spans its whole range."""
    at, out = offsets(grid), []
    for items, usage in result.itemsets:
        lo, hi = [0] * len(at), [a.n_bins - 1 for a in grid.axes]
        for item in items:
            axis = max(i for i, o in enumerate(at) if o <= item)
            lo[axis] = hi[axis] = item - at[axis]
        out.append((lo, hi, int(usage)))
    return out


def to_boxes(spark, result: ItemsetResult, grid: Grid) -> DataFrame:
    rows = [(pid, *s) for pid, s in enumerate(sides(result, grid), 1)]
    return B.with_log_size(spark.createDataFrame(rows, "pid long, lo array<int>, hi array<int>, usage long"))
