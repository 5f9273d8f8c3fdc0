"""The experiment workloads as tables: ``python -m boxmdl.experiments NAME [SF_DIR]``.

layouts     planted boxes by layout, size, method and setting: patterns, overlap, agreement both ways
methods     miner, itemset and sampling baselines by workload and setting: bits, ratios, patterns, seconds, similarity, accuracy
settings    influence of scope, pruning moment, smoothing, gain mode, ties and encoding, by grid
neighbours  influence of the neighbour limit and the number of intervals
complexity  explored candidates against the bounds, by number of cells

The miner's neighbour limit is the number of intervals.  A baseline that meets
its limit of time is listed with what it had found, and its status.
"""

from __future__ import annotations

import sys
import time

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import cells, grid, kernel, measures, miner, neighbors
from .operators.baselines import itemset, sampling
from .operators.baselines.limits import Limits
from .session import fixed, released, session
from .sources import workloads as W

#: Seconds that a baseline may take in a registered experiment.
SECONDS = 8.0
GRIDS = ("5", "sqrt", "interaction")
SAMPLES = {"sqrt": "sqrt", "0.25": 0.25, "0.5": 0.5}


def make_grid(df: DataFrame, attrs: list[str], setting: str) -> grid.Grid:
    if setting == "interaction":
        return grid.interaction_preserving(df, attrs)
    return grid.equal_width(df, attrs, "sqrt" if setting == "sqrt" else int(setting))


def limit_of(g: grid.Grid) -> int:
    """As many neighbours as intervals."""
    return max(a.n_bins for a in g.axes)


# Planted layouts: every run fits one task, so all runs go out at once.

RUN = "layout string, m long, method string, setting string, pid long, rlo array<double>, rhi array<double>, status string, seconds double"


def _local_grid(values: np.ndarray, setting: str) -> grid.Grid:
    lo, hi = values.min(axis=0).tolist(), values.max(axis=0).tolist()
    if setting == "interaction":
        return grid.Grid(tuple(grid.Axis(f"a{i}", len(c) + 1, lo[i], hi[i], c) for i, c in enumerate(grid.interaction_cuts(values))), len(values))
    bins = grid.bins_of("sqrt" if setting == "sqrt" else int(setting), ["a"], len(values))[0]
    return grid.Grid(tuple(grid.Axis(f"a{i}", bins, x, y) for i, (x, y) in enumerate(zip(lo, hi, strict=True))), len(values))


def _local_cells(values: np.ndarray, g: grid.Grid) -> tuple[np.ndarray, np.ndarray]:
    spots = []
    for i, a in enumerate(g.axes):
        if a.cuts is not None:
            spots.append(np.searchsorted(a.cuts, values[:, i], side="right"))
        else:
            spots.append(np.clip(np.floor((values[:, i] - a.lo) / ((a.hi - a.lo) or 1.0) * a.n_bins), 0, a.n_bins - 1).astype(np.int64))
    return np.unique(np.stack(spots, axis=1), axis=0, return_counts=True)


def _planted_run(frame: pd.DataFrame) -> pd.DataFrame:
    """One method with one setting on one layout."""
    method, setting, limits = frame["method"].iloc[0], frame["setting"].iloc[0], Limits(SECONDS)
    values = frame[["x", "y"]].to_numpy(float)
    if method == "sampling":
        n = len(values)
        low = values.min(axis=0)
        wide = np.maximum(values.max(axis=0) - low, 1e-12)
        unit = (values - low) / wide
        chosen = np.random.default_rng(0).choice(n, sampling.size_of(SAMPLES[setting], n), replace=False)
        count = lambda batch: [int(((unit >= lo - sampling.SLACK) & (unit <= hi + sampling.SLACK)).all(axis=1).sum()) for lo, hi in batch]
        found = [((low + lo * wide).tolist(), (low + hi * wide).tolist()) for lo, hi, _, _ in sampling.grow_all(unit[np.sort(chosen)], n, count, limits=limits)[0]]
    else:
        g = _local_grid(values, setting)
        spots, usage = _local_cells(values, g)
        edges = [a.edges() for a in g.axes]
        real = lambda lo, hi: ([e[i] for e, i in zip(edges, lo, strict=True)], [e[i + 1] for e, i in zip(edges, hi, strict=True)])
        if method == "boxes":
            p = kernel.Patterns.of(np.arange(1, len(spots) + 1), spots, spots, usage)
            run = kernel.mine(p, kernel.packed(*neighbors.knn_local(spots, limit_of(g)).T), g, tie="hash")
            kernel.prune(p, run, g)
            found = [real(p.lo[r].tolist(), p.hi[r].tolist()) for r in p.live()]
        else:
            sets = itemset.mine_rows(spots + np.array(itemset.offsets(g)), usage.astype(float), limits=limits)
            found = [real(lo, hi) for lo, hi, _ in itemset.sides(sets, g)]
    rows = [(*frame[["layout", "m", "method", "setting"]].iloc[0], pid, *b, limits.status, limits.spent()) for pid, b in enumerate(found, 1)]
    empty = [] if rows else [(*frame[["layout", "m", "method", "setting"]].iloc[0], None, None, None, limits.status, limits.spent())]
    return pd.DataFrame(rows + empty, columns=[x.split()[0] for x in RUN.split(", ")])


def layouts(spark: SparkSession, sf_dir: str, sizes=W.OBJECTS, names=tuple(W.LAYOUTS)) -> DataFrame:
    """All layouts x sizes x (miner and itemsets on three grids, sampling with three sample sizes)."""
    data = truth = None
    for name in names:
        known = W.truth(spark, name).select(F.lit(name).alias("layout"), "*")
        truth = known if truth is None else truth.unionByName(known)
        for m in sizes:
            one = W.layout(spark, sf_dir, name, m).select(F.lit(name).alias("layout"), F.lit(m).cast("long").alias("m"), "x", "y")
            data = one if data is None else data.unionByName(one)
    settings = [("boxes", s) for s in GRIDS] + [("itemsets", s) for s in GRIDS] + [("sampling", s) for s in SAMPLES]
    every = fixed(data).crossJoin(F.broadcast(spark.createDataFrame(settings, "method string, setting string")))  # nine settings
    key = ["layout", "m", "method", "setting"]
    found = fixed(every.repartition(max(64, 2 * spark.sparkContext.defaultParallelism), *key).groupBy(*key).applyInPandas(_planted_run, RUN))
    boxes = found.filter("pid is not null")
    runs = found.groupBy(*key).agg(F.count("pid").alias("patterns"), F.max("status").alias("status"), F.max("seconds").alias("seconds"))
    known = runs.select(*key).join(truth, "layout")
    overlap = measures.box_jaccard_mean(boxes, by=key).select(*key, F.col("mean_jaccard").alias("overlap"))
    ours = measures.jcd(boxes, known, by=key).select(*key, F.col("jcd").alias("jcd_computed"))
    theirs = measures.jcd(known, boxes, "tid", "pid", by=key).select(*key, F.col("jcd").alias("jcd_truth"))
    whole = runs.join(overlap, key, "left").join(ours, key, "left").join(theirs, key, "left")
    return whole.select(*key, "patterns", F.coalesce("overlap", F.lit(0.0)).alias("overlap"), F.coalesce("jcd_computed", F.lit(0.0)).alias("jcd_computed"), F.coalesce("jcd_truth", F.lit(0.0)).alias("jcd_truth"), "status", "seconds")


# Workloads

METHODS = (
    "workload string, method string, setting string, cells long, patterns long, start_bits double, bits double, ratio double, itemset_length_ratio double, "
    "seconds double, seconds_per_pattern double, similarity double, accuracy_support double, accuracy_cover double, candidates long, status string"
)


def methods(spark: SparkSession, sf_dir: str, name: str, seconds: float = SECONDS) -> DataFrame:
    """One workload: the miner and the itemset baseline on three grids, the sampling baseline with three sample sizes."""
    attrs, rows = W.attrs(name), []
    df = fixed(W.load(spark, sf_dir, name))
    mean = lambda per_pattern: measures.mean_accuracy(per_pattern).first().mean_accuracy
    for setting in GRIDS:
        g = make_grid(df, attrs, setting)
        c = fixed(cells.elementary(cells.discretise(df, g)))
        disc = fixed(cells.discretise(df, g, ["label"]))
        began = time.monotonic()
        found = miner.mine_cells(c, g, limit_of(g))
        took = time.monotonic() - began
        sets = itemset.mine(c, g, seconds=seconds)
        theirs = itemset.to_boxes(spark, sets, g)
        r = found.report
        cover = mean(measures.accuracy(found.boxes, disc, "label", "cover", found.lineage, c))
        rows.append((name, "boxes", setting, r["cells"], r["patterns"], r["start_bits"], r["end_bits"], r["compression_ratio"], measures.length_ratio(sets.end_bits, r["end_bits"]), took, took / max(1, r["patterns"]), measures.jaccard_topk(found.boxes, c).first().mean_jaccard, mean(measures.accuracy(found.boxes, disc, "label")), cover, r["candidates"], "ok"))
        k = len(sets.itemsets)
        rows.append((name, "itemsets", setting, r["cells"], k, sets.start_bits, sets.end_bits, sets.end_bits / sets.start_bits, 1.0, sets.seconds, sets.seconds / max(1, k), measures.jaccard_topk(theirs, c).first().mean_jaccard, mean(measures.accuracy(theirs, disc, "label")), None, sets.evaluated, sets.status))
        released(spark)
    for setting, size in SAMPLES.items():
        grown = sampling.mine(df, attrs, size, seconds=seconds)
        k = grown.boxes.count()
        inside = fixed(sampling.occurrences(grown.boxes, df, attrs, "obj_id"))
        similar = measures.jaccard_topk(grown.boxes, None, inside=inside).first().mean_jaccard
        labelled = inside.join(df.select(F.col("obj_id").alias("cell_id"), F.col("label").cast("string").alias("label")).filter("label is not null"), "cell_id")
        rows.append((name, "sampling", setting, None, k, None, None, None, None, grown.seconds, grown.seconds / max(1, k), similar, mean(measures.majority(labelled)), None, grown.evaluated, grown.status))
        released(spark)
    return spark.createDataFrame(rows, METHODS)


SETTINGS = {
    "default": {},
    "all": {"candidate_scope": "all"},
    "no_pruning": {"prune_when": "never"},
    "prune_each_round": {"prune_when": "each_round"},
    "eps_1": {"eps": 1.0},
    "eps_0.1": {"eps": 0.1},
    "stored_gains": {"gain_mode": "stored"},
    "requeue": {"requeue": True},
    "shannon": {"encoding": "shannon"},
    "tie_first": {"tie": "first"},
    "tie_last": {"tie": "last"},
    "absorb_by_usage": {"absorb_order": "usage"},
}
REPORT = "workload string, grid string, run string, cells long, patterns long, rounds long, candidates long, start_bits double, end_bits double, ratio double"


def report_row(name: str, g: str, run: str, report: dict) -> tuple:
    return name, g, run, report["cells"], report["patterns"], report["rounds"], report["candidates"], report["start_bits"], report["end_bits"], report["compression_ratio"]


def settings(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    df, rows = fixed(W.load(spark, sf_dir, name)), []
    for setting in GRIDS:
        g = make_grid(df, W.attrs(name), setting)
        c = fixed(cells.elementary(cells.discretise(df, g)))
        for run, options in SETTINGS.items():
            rows.append(report_row(name, setting, run, miner.mine_cells(c, g, limit_of(g), **options).report))
            released(spark)
    return spark.createDataFrame(rows, REPORT)


def compression(spark: SparkSession, sf_dir: str, names=("W4", "W5", "W6", "W7", "W9")) -> DataFrame:
    """Compression, patterns and explored candidates: workloads by grid."""
    rows = []
    for name in names:
        df = fixed(W.load(spark, sf_dir, name))
        for setting in GRIDS:
            g = make_grid(df, W.attrs(name), setting)
            rows.append(report_row(name, setting, "default", miner.mine(df, W.attrs(name), grid=g, k=limit_of(g)).report))
            released(spark)
    return spark.createDataFrame(rows, REPORT)


def neighbours(spark: SparkSession, sf_dir: str, name: str = "W6") -> DataFrame:
    df, rows = fixed(W.load(spark, sf_dir, name)), []
    for bins in (3, 5, 10, 20):
        g = grid.equal_width(df, W.attrs(name), bins)
        c = fixed(cells.elementary(cells.discretise(df, g)))
        for k in (1, 2, 5, 10, 20):
            r = miner.mine_cells(c, g, k).report
            rows.append((bins, k, r["cells"], r["patterns"], r["candidates"], r["compression_ratio"]))
    return spark.createDataFrame(rows, "bins int, k int, cells long, patterns long, candidates long, ratio double")


def complexity(spark: SparkSession, sf_dir: str, name: str = "W3") -> DataFrame:
    df, rows = fixed(W.load(spark, sf_dir, name)), []
    for bins in (4, 8, 16, 32, 64):
        g = grid.equal_width(df, W.attrs(name), bins)
        c = fixed(cells.elementary(cells.discretise(df, g)))
        for scope in ("inherited", "all"):
            began = time.monotonic()
            r = miner.mine_cells(c, g, bins, candidate_scope=scope, prune_when="never").report
            b = measures.candidate_bounds(r)
            rows.append((bins, scope, r["cells"], r["rounds"], b["most_in_round"], b["round_bound"], b["all"], b["bound"], b["most_in_round"] <= b["round_bound"] and b["all"] <= b["bound"], time.monotonic() - began))
    return spark.createDataFrame(rows, "bins int, scope string, cells long, rounds long, most_in_round long, round_bound long, explored long, bound long, within boolean, seconds double")


EXPERIMENTS = {"layouts": layouts, "methods": lambda s, d: methods(s, d, sys.argv[3] if len(sys.argv) > 3 else "W7", 60.0), "settings": lambda s, d: settings(s, d, "W7"), "compression": compression, "neighbours": neighbours, "complexity": complexity}

if __name__ == "__main__":
    made = EXPERIMENTS[sys.argv[1]](session(), sys.argv[2] if len(sys.argv) > 2 else "/root/testdata/sf0.001")
    print(made.toPandas().round(4).to_string(index=False))
