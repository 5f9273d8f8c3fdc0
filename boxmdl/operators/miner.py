"""Mining a small set of boxes: from non-empty cells, merging by description length.

Raw rows are read twice (ranges, cell counts); all else works on cells, then on
ever fewer patterns.  While there are more patterns than one process should
hold, rounds run on DataFrames (`matching`); while there are more candidates,
these stay in tasks (`intasks`); then the array kernel finishes.
"""

from __future__ import annotations

import json
import time
import warnings
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.codes import EPS
from ..plans import choose
from ..session import fixed, released
from . import boxes as B
from . import candidates, cells, intasks, kernel, matching, model, neighbors, prune
from . import grid as grids

LEDGER_SCHEMA = "round int, step int, a long, b long, pid long, k_before long, gain double, total_after double"


@dataclass
class MineResult:
    """``boxes``, ``lineage`` (cell to pattern), ``cells``, ``grid``, ``ledger`` (a row for each merge) and ``report``."""

    boxes: DataFrame
    lineage: DataFrame
    cells: DataFrame
    grid: grids.Grid
    ledger: DataFrame
    report: dict = field(default_factory=dict)

    def assign(self, df: DataFrame) -> DataFrame:
        """`df` with ``pid``, the pattern that encodes each row; null in a cell that mining did not see."""
        names = [f"__b_{i}" for i in range(len(self.grid.axes))]
        placed = df.select("*", *[a.index(F.col(a.attr).cast("double")).alias(x) for a, x in zip(self.grid.axes, names, strict=True)])
        known = self.cells.join(self.lineage, "cell_id").select(F.col("lo").alias("__cell"), "pid")
        return placed.withColumn("__cell", F.array(*names)).join(known, "__cell", "left").drop("__cell", *names)

    def describe(self, labelled: DataFrame | None = None, label: str = "label") -> DataFrame:
        """A row for each pattern: real bounds, usage, support, SQL predicate, and with labels its majority class."""
        from . import measures

        real = cells.to_real(self.boxes, self.grid)
        text = F.concat_ws(" AND ", *[F.format_string(f"{a.attr} in [%s, %s]", F.element_at("rlo", i + 1), F.element_at("rhi", i + 1)) for i, a in enumerate(self.grid.axes)])
        out = real.join(measures.support(self.boxes, self.cells), "pid").withColumn("intervals", text)
        if labelled is not None:
            out = out.join(measures.accuracy(self.boxes, cells.discretise(labelled, self.grid, [label]), label), "pid", "left")
        return out

    def save(self, path: str) -> None:
        spark = self.boxes.sparkSession
        for name in ("boxes", "lineage", "cells", "ledger"):
            getattr(self, name).write.mode("overwrite").parquet(f"{path}/{name}")
        grids.to_frame(spark, self.grid).write.mode("overwrite").parquet(f"{path}/grid")
        spark.createDataFrame([(json.dumps(self.report),)], "report string").write.mode("overwrite").text(f"{path}/report")

    @classmethod
    def load(cls, spark, path: str) -> MineResult:
        read = {name: spark.read.parquet(f"{path}/{name}") for name in ("boxes", "lineage", "cells", "ledger")}
        report = json.loads(spark.read.text(f"{path}/report").first()[0])
        return cls(read["boxes"], read["lineage"], read["cells"], grids.from_frame(spark.read.parquet(f"{path}/grid")), read["ledger"], report)


def _arrays(boxes: DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Ids (ascending), corners and usages of the boxes."""
    found = boxes.select("pid", "lo", "hi", "usage").toArrow()
    ids = found["pid"].to_numpy()
    order = np.argsort(ids)
    corner = lambda c: found[c].combine_chunks().flatten().to_numpy().reshape(len(ids), -1)[order]
    return ids[order], corner("lo"), corner("hi"), found["usage"].to_numpy()[order]


def _rows(pairs: DataFrame, ids: np.ndarray) -> np.ndarray:
    """Pairs of ids (``a, b``) as packed row pairs."""
    found = pairs.select("a", "b").toArrow()
    return kernel.packed(*(np.searchsorted(ids, found[c].to_numpy()) for c in ("a", "b")))


def _near_rows(elementary: DataFrame, ids: np.ndarray, points: np.ndarray, k: int, n_attrs: int, method: str) -> np.ndarray:
    """Packed row pairs of neighbours: found here for few cells, by tasks for more."""
    if method == "auto" and len(ids) <= choose.ALL_PAIRS_CELLS:
        found = neighbors.knn_local(points, k)
        return kernel.packed(found[:, 0], found[:, 1])
    sent: list = []
    out = kernel.different(_rows(neighbors.neighbor_pairs(elementary, k, n_attrs, method, len(ids), sent).toDF("a", "b"), ids))
    for b in sent:
        b.destroy()
    return out


def _boxes_frame(spark, p: kernel.Patterns, live: np.ndarray) -> DataFrame:
    n, d = p.lo[live].shape
    corner = lambda x: pa.ListArray.from_arrays(pa.array(np.arange(n + 1) * d, pa.int32()), pa.array(x[live].ravel(), pa.int32()))
    return spark.createDataFrame(pa.table({"pid": p.ids[live], "lo": corner(p.lo), "hi": corner(p.hi), "usage": p.usage[live].astype(np.int64), "log_size": p.log_size[live]}))


def _ledger_frame(spark, ledger: kernel.Ledger) -> DataFrame:
    kinds = {"int": pa.int32(), "long": pa.int64(), "double": pa.float64()}
    fields = [x.split() for x in LEDGER_SCHEMA.split(", ")]
    return spark.createDataFrame(pa.table({name: pa.array(c, kinds[t]) for (name, t), c in zip(fields, ledger.columns(), strict=True)}))


def starting_boxes(elementary: DataFrame) -> DataFrame:
    return B.with_log_size(elementary.select(F.col("cell_id").alias("pid"), "lo", "hi", "usage"))


def _distributed(boxes, edges, lineage, grid, n, k, eps, scope, gain_mode, tie, encoding, requeue, report, ledger):
    """Rounds on DataFrames until the patterns and candidates fit the kernel or no candidate is left.

    Returns boxes, edges, lineage, their number, the next round's pairs (None:
    over), the pairs left over for requeueing, the total length, the first id
    of the last round, the number of edges and whether a round without merges
    was the end.
    """
    pairs = edges
    left = None
    total = model.total_bits(boxes, grid, eps, encoding).first().total
    next_id = boxes.agg(F.max("pid")).first()[0] + 1
    n_edges = seen = edges.count()
    first_new = 0
    while choose.rounds_plan(k, n_edges, scope, requeue, len(grid.axes)) == "distributed":
        if requeue and left is not None:
            pairs = fixed(pairs.unionByName(left).dropDuplicates())
            seen = pairs.count()
        left = pairs if requeue else None
        if not seen:
            return boxes, edges, lineage, k, None, None, total, first_new, n_edges, False
        report["explored"].append(seen)
        # only pairs that can gain are written: most of the candidates never leave their tasks
        hopeful = fixed(candidates.weighted(pairs, boxes, eps, encoding).select("a", "b", "w").filter(F.col("w") > -model.hope(k, n, grid, eps, encoding)))
        if hopeful.isEmpty():
            return boxes, edges, lineage, k, None, None, total, first_new, n_edges, True
        merges = matching.accepted(matching.greedy_matching(hopeful, tie), k, n, grid, eps, encoding, gain_mode, next_id)
        made = merges.count()
        if not made:
            return boxes, edges, lineage, k, None, None, total, first_new, n_edges, True
        joint = candidates.weighted(merges, boxes, eps, encoding).join(merges.select("a", "b", "pid"), ["a", "b"])
        usage = merges.select("pid", F.explode(F.array("a", "b")).alias("old")).join(boxes.select(F.col("pid").alias("old"), "usage"), "old").groupBy("pid").agg(F.sum("usage").alias("usage"))
        new = B.with_log_size(joint.join(usage, "pid").select("pid", "lo", "hi", "usage"))
        moved = merges.select(F.explode(F.array("a", "b")).alias("old"), F.col("pid").alias("new"))
        kept = boxes.join(moved, F.col("pid") == F.col("old"), "left_anti")
        boxes = fixed(kept.unionByName(new))
        lineage = fixed(lineage.join(moved, F.col("pid") == F.col("old"), "left").select("cell_id", F.coalesce("new", "pid").alias("pid")))
        edges = fixed(candidates.contracted(edges, merges))
        rounds = len(report["explored"])
        before = F.sum("gain").over(_by_step())
        ledger.append(merges.select(F.lit(rounds).alias("round"), F.col("step").cast("int"), "a", "b", "pid", "k_before", "gain", (F.lit(total) - before).alias("total_after")))
        total -= merges.agg(F.sum("gain")).first()[0]
        k -= made
        first_new = next_id
        next_id += made
        pairs = edges.filter((F.col("a") >= first_new) | (F.col("b") >= first_new)) if scope == "inherited" else candidates.with_new(boxes, first_new)
        seen = pairs.count() if scope == "inherited" else made * (k - made) + made * (made - 1) // 2
        n_edges = edges.count() if scope == "inherited" else seen
        if requeue:
            gone = merges.select(F.explode(F.array("a", "b")).alias("v"))
            left = fixed(left.join(gone, F.col("a") == F.col("v"), "left_anti").join(gone, F.col("b") == F.col("v"), "left_anti"))
            n_edges += left.count()
    return boxes, edges, lineage, k, pairs, left, total, first_new, n_edges, False


def _by_step():
    from pyspark.sql import Window

    # totals along one round's ledger: one row for each merge of a round, reporting only
    return Window.orderBy("step").rowsBetween(Window.unboundedPreceding, 0)


def mine(df: DataFrame, attrs: list[str], n_bins="sqrt", k: int | None = None, grid: grids.Grid | None = None, eps: float = EPS, candidate_scope: str | None = None, gain_mode: str = "refreshed", tie: str = "hash", prune_when: str = "final", top_n: int | None = 1000, encoding: str = "plugin", on_missing: str = "error", requeue: bool = False, absorb_order: str = "id", knn_method: str = "auto") -> MineResult:
    """Boxes of `df` over `attrs`; `k` limits the neighbours (None: every pair).

    candidate_scope: 'inherited' (a new box keeps the neighbours of its parts;
    the default with a limit) or 'all' (a new box with every pattern; the
    default without).  prune_when: 'final', 'each_round' or 'never'.  tie:
    which of equal gains goes first: 'first' or 'last' by pair id, or 'hash'.
    """
    began = time.monotonic()
    spark = df.sparkSession
    if on_missing == "drop":
        df = grids.finite_rows(df, attrs)
    elif grid is not None:
        grids.check_rows(df, attrs)
    grid = grid or grids.equal_width(df, attrs, n_bins)
    elementary = fixed(cells.elementary(cells.discretise(df, grid)))
    result = mine_cells(elementary, grid, k, eps, candidate_scope, gain_mode, tie, prune_when, top_n, encoding, requeue, absorb_order, knn_method)
    result.report["seconds"] = time.monotonic() - began
    result.report["master"] = spark.sparkContext.master
    return result


def mine_cells(elementary: DataFrame, grid: grids.Grid, k=None, eps=EPS, candidate_scope=None, gain_mode="refreshed", tie="hash", prune_when="final", top_n=1000, encoding="plugin", requeue=False, absorb_order="id", knn_method="auto") -> MineResult:
    """As `mine`, from cells (``cell_id, lo, hi, usage``) that are stored or fixed."""
    spark = elementary.sparkSession
    scope = candidate_scope or ("all" if k is None else "inherited")
    size = elementary.agg(F.count(F.lit(1)).alias("k"), F.sum("usage").alias("n")).first()
    if not size.k:
        raise ValueError("no rows to mine")
    report: dict = {"n": size.n, "cells": size.k, "explored": [], "status": "ok", "scope": scope, "eps": eps}
    boxes, lineage = starting_boxes(elementary), elementary.select("cell_id", F.col("cell_id").alias("pid"))
    start = model.total_bits(boxes, grid, eps, encoding).first()
    report["start_bits"] = start.total
    ledger: list[DataFrame] = []
    n_attrs = len(grid.axes)
    n_edges = size.k * min(k, size.k - 1) if k else choose.most_pairs(size.k)
    plan = choose.rounds_plan(size.k, n_edges, scope, requeue, n_attrs)
    first_new = 0
    first, edges_df, alive, total, left, idle = None, None, size.k, None, None, False
    if prune_when == "each_round" and plan == "distributed" and scope == "all" and requeue:
        raise ValueError("prune_when='each_round' with scope 'all' and requeueing needs patterns and candidates that fit the driver")
    if plan == "distributed":
        near = neighbors.edges(neighbors.neighbor_pairs(elementary, k, n_attrs, knn_method, size.k)) if k else neighbors.every_pair(elementary, size.k)
        boxes, edges_df, lineage, alive, first, left, total, first_new, n_edges, idle = _distributed(fixed(boxes), fixed(near), lineage, grid, size.n, size.k, eps, scope, gain_mode, tie, encoding, requeue, report, ledger)
    over = plan == "distributed" and first is None
    if over and (prune_when == "never" or choose.unpruned(alive)):
        report |= {"patterns": alive, "pruned": False}
        if prune_when != "never":
            warnings.warn(f"{alive} patterns are not pruned (at most {choose.PRUNE_PATTERNS})", stacklevel=2)
        held = boxes
        if not ledger:
            ledger.append(_ledger_frame(spark, kernel.Ledger()))
    else:
        # bounded by LOCAL_PATTERNS, but for pruning what more patterns could not be merged to
        ids, lo, hi, usage = _arrays(boxes)
        # what collecting left in the JVM goes before the next step fills it
        let_go = (lambda: released(spark)) if size.k > choose.ALL_PAIRS_CELLS else (lambda: None)
        let_go()
        p = kernel.Patterns.of(ids, lo, hi, usage)
        run = kernel.Run(p, explored=report["explored"])
        pruned = lambda: kernel.prune(p, run, grid, eps, top_n, absorb_order, encoding, prune.search(spark, eps, encoding))
        each = pruned if prune_when == "each_round" else None

        def in_tasks(pairs, start, total):
            held, following, total = intasks.mine(spark, pairs, p, run, grid, eps, scope, gain_mode, tie, encoding, requeue, start, total, each)
            if following is not None:
                kernel.mine(p, held, grid, eps, scope, gain_mode, tie, encoding, requeue, run, following, after_round=each, total=total, left=held if requeue else None)

        if plan == "local":
            near = _near_rows(elementary, ids, lo, k, n_attrs, knn_method) if k else None
            let_go()
            kernel.mine(p, near, grid, eps, scope, gain_mode, tie, encoding, requeue, run, after_round=each)
        elif not over and (plan == "tasks" or choose.rounds_plan(alive, n_edges, scope, requeue, n_attrs) == "tasks"):
            pairs = None
            if plan == "tasks" and k:
                pairs = intasks.from_cells(elementary, k, n_attrs, knn_method, p, n_edges)
            elif plan == "tasks" and scope == "inherited":
                pairs = intasks.from_neighbors(neighbors.every_pair(elementary, size.k), p, n_edges)
            elif scope == "inherited":
                pairs = intasks.from_neighbors(edges_df, p, n_edges)
            elif plan == "tasks":
                neighbors.check_every_pair(size.k)
            let_go()
            in_tasks(pairs, int(np.searchsorted(ids, first_new)), total)
        elif idle and each:
            pairs = intasks.from_neighbors(edges_df, p, n_edges) if scope == "inherited" else None
            if each():
                in_tasks(pairs and intasks.contracted(pairs, p, run.roots()), len(ids), None)
        elif first is not None:
            kernel.mine(p, _rows(edges_df, ids), grid, eps, scope, gain_mode, tie, encoding, requeue, run, _rows(first, ids), after_round=each, total=total, left=_rows(left, ids) if requeue else None)
        let_go()
        left_over = len(p.live())
        report["pruned"] = prune_when != "never" and not choose.unpruned(left_over)
        if report["pruned"]:
            pruned()
        elif prune_when != "never":
            warnings.warn(f"{left_over} patterns are not pruned (at most {choose.PRUNE_PATTERNS})", stacklevel=2)
        live = p.live()
        held = _boxes_frame(spark, p, live)
        to = spark.createDataFrame(pa.table({"pid": ids, "to": p.ids[run.roots()[: len(ids)]]}))
        lineage = lineage.join(to, "pid").select("cell_id", F.col("to").alias("pid"))
        ledger.append(_ledger_frame(spark, run.ledger))
        report["patterns"] = len(live)
    end = model.total_bits(held, grid, eps, encoding).first()
    report |= {"rounds": len(report["explored"]), "candidates": int(sum(report["explored"])), "end_bits": end.total, "compression_ratio": end.total / start.total, "parts": {c: end[c] for c in ("grid", "patterns", "count", "data", "reconstruction")}}
    whole = ledger[0]
    for part in ledger[1:]:
        whole = whole.unionByName(part)
    return MineResult(held, lineage, elementary, grid, whole, report)
