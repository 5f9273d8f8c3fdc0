"""The code lengths and box functions for SQL, and mining as a table function."""

from __future__ import annotations

import math

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from . import codes

SQL_FUNCTIONS = {
    "bin_of": ("v DOUBLE, lo DOUBLE, hi DOUBLE, b INT", "INT", "CASE WHEN hi <= lo THEN 0 ELSE CAST(greatest(0, least(b - 1, floor((v - lo) / (hi - lo) * b))) AS INT) END"),
    "lnat_bits": (
        "n BIGINT",
        "DOUBLE",
        f"CASE WHEN n < 1 THEN 0.0D ELSE {math.log2(codes.C0)!r}D + "
        + " + ".join(f"CASE WHEN {c} THEN {v} ELSE 0.0D END" for c, v in (("n > 1", "log2(n)"), ("n > 2", "log2(log2(n))"), ("n > 4", "log2(log2(log2(n)))"), ("n > 16", "log2(log2(log2(log2(n))))"), ("n > 65536", "log2(log2(log2(log2(log2(n)))))")))
        + " END",
    ),
    "lgamma_bits": (
        "x DOUBLE",
        "DOUBLE",
        f"((x + 7.5D) * ln(x + 8) - (x + 8) + {0.5 * math.log(2 * math.pi)!r}D"
        + "".join(f" {'+' if c > 0 else '-'} {abs(c)!r}D / power(x + 8, {2 * j + 1})" for j, c in enumerate(codes.STIRLING))
        + f" - ln(x * (x + 1) * (x + 2) * (x + 3) * (x + 4) * (x + 5) * (x + 6) * (x + 7))) / {codes.LN2!r}D",
    ),
    "box_jaccard": (
        "lo_a ARRAY<DOUBLE>, hi_a ARRAY<DOUBLE>, lo_b ARRAY<DOUBLE>, hi_b ARRAY<DOUBLE>",
        "DOUBLE",
        "aggregate(zip_with(arrays_zip(hi_a, hi_b), arrays_zip(lo_a, lo_b), (h, l) -> greatest(least(h.hi_a, h.hi_b) - greatest(l.lo_a, l.lo_b), 0.0D)), 1.0D, (s, x) -> s * x)"
        " / aggregate(zip_with(arrays_zip(hi_a, hi_b), arrays_zip(lo_a, lo_b), (h, l) -> greatest(h.hi_a, h.hi_b) - least(l.lo_a, l.lo_b)), 1.0D, (s, x) -> s * x)",
    ),
}


def register(spark: SparkSession) -> None:
    """`bin_of`, `lnat_bits`, `lgamma_bits`, `box_jaccard` as SQL functions (inlined by the analyser), and the table function `mine_boxes`."""
    for name, (parameters, kind, body) in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({parameters}) RETURNS {kind} RETURN {body}")
    spark.udtf.register("mine_boxes", MineBoxes)


def _local_boxes(values, n_bins: int, k: int):
    import numpy as np

    from ..operators import kernel, neighbors
    from ..operators.grid import Axis, Grid

    values = np.asarray(values, float)
    lo, hi = values.min(axis=0), values.max(axis=0)
    span = np.where(hi > lo, hi - lo, 1.0)
    spot = np.minimum(n_bins - 1, np.floor((values - lo) / span * n_bins)).astype(np.int64)
    cells, usage = np.unique(spot, axis=0, return_counts=True)
    grid = Grid(tuple(Axis(f"a{i}", n_bins, x, y) for i, (x, y) in enumerate(zip(lo.tolist(), hi.tolist(), strict=True))), len(values))
    p = kernel.Patterns.of(np.arange(1, len(cells) + 1), cells, cells, usage)
    near = kernel.packed(*neighbors.knn_local(cells, k).T) if k else None
    run = kernel.mine(p, near, grid, scope="inherited" if k else "all", tie="hash")
    kernel.prune(p, run, grid)
    return grid, p


@F.udtf(returnType="pid int, lo array<double>, hi array<double>, usage bigint")
class MineBoxes:
    """``SELECT * FROM mine_boxes(TABLE(SELECT array(a, b) AS v FROM t) WITH SINGLE PARTITION, 5, 5)``: for small tables only, as one task holds them."""

    def __init__(self):
        self.rows, self.setup = [], (5, 5)

    def eval(self, row, n_bins: int, k: int):
        self.rows.append([float(x) for x in row["v"]])
        self.setup = n_bins, k

    def terminate(self):
        if self.rows:
            grid, p = _local_boxes(self.rows, *self.setup)
            for pid, r in enumerate(p.live().tolist(), 1):
                edges = [a.edges() for a in grid.axes]
                yield pid, [e[i] for e, i in zip(edges, p.lo[r].tolist(), strict=True)], [e[i + 1] for e, i in zip(edges, p.hi[r].tolist(), strict=True)], int(p.usage[r])


def mine_groups(df, group: str, attrs: list[str], n_bins: int = 5, k: int = 5):
    """Boxes for each group on its own (a group must fit one task): ``group, pid, lo, hi, usage``."""
    import pandas as pd

    kind = dict(df.dtypes)[group]

    def each(frame: pd.DataFrame) -> pd.DataFrame:
        grid, p = _local_boxes(frame[attrs].to_numpy(), n_bins, k)
        edges = [a.edges() for a in grid.axes]
        rows = [(frame[group].iloc[0], pid, [e[i] for e, i in zip(edges, p.lo[r].tolist(), strict=True)], [e[i + 1] for e, i in zip(edges, p.hi[r].tolist(), strict=True)], int(p.usage[r])) for pid, r in enumerate(p.live().tolist(), 1)]
        return pd.DataFrame(rows, columns=[group, "pid", "lo", "hi", "usage"])

    return df.select(group, *attrs).groupBy(group).applyInPandas(each, f"{group} {kind}, pid int, lo array<double>, hi array<double>, usage long")
