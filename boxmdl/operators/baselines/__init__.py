"""Methods that the miner is compared with.

The reference names their parameters, costs and behaviour but not their inner
workings; these are our own readings from the general literature, to be
compared by trend.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ...functions.codes import EPS
from .. import cells, miner, model
from ..grid import Grid


def elementary(cell_rows: DataFrame, grid: Grid, eps: float = EPS) -> DataFrame:
    """Length of the cells without mining."""
    return model.total_bits(miner.starting_boxes(cell_rows), grid, eps)


def single_box(cell_rows: DataFrame) -> DataFrame:
    """One box around everything."""
    size = cell_rows.select(F.size("lo").alias("k")).first()
    if size is None:
        raise ValueError("no cells")
    ends = lambda f, s: F.array(*[f(F.element_at(s, i + 1)) for i in range(size.k)]).alias(s)
    one = cell_rows.agg(ends(F.min, "lo"), ends(F.max, "hi"), F.sum("usage").alias("usage"))
    return miner.B.with_log_size(one.select(F.lit(1).cast("long").alias("pid"), "lo", "hi", "usage"))


def cluster_boxes(df: DataFrame, attrs: list[str], k: int, seed: int = 1) -> DataFrame:
    """k-means clusters described by their hulls: ``cluster, usage, lo, hi`` in attribute values."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.feature import StandardScaler, VectorAssembler

    vectors = VectorAssembler(inputCols=attrs, outputCol="__v").transform(df)
    scaled = StandardScaler(inputCol="__v", outputCol="__s", withMean=True).fit(vectors).transform(vectors)
    found = KMeans(k=k, seed=seed, featuresCol="__s", predictionCol="cluster").fit(scaled).transform(scaled)
    return cells.hull(found, attrs, "cluster")
