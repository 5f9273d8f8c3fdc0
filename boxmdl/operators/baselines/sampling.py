"""Sampling baseline: boxes grown without a grid from a sample, each judged alone.

From a seed pair of sampled rows a box takes in the nearest sampled rows as
long as its own gain rises; the gain is that of telling rows inside from rows
outside and coding the inside on less space, less the cost of the bounds.
Boxes that gain on the full table are kept.  Nothing looks at the set as a
whole, so similar boxes are kept side by side.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..cells import with_row_ids
from .limits import Limits

#: Candidate boxes counted in one scan of the table.
BATCH = 64
#: Tiles of the first attribute in which rows and boxes meet.
TILES = 64
#: Rows of a sample that the driver may choose from all tasks' first ones; more are numbered in order by tasks.
CHOSEN_HERE = 10_000
#: Bounds go through a scaling and back; rows this near to one are inside.
SLACK = 1e-9


@dataclass
class SamplingResult:
    boxes: DataFrame  # pid, rlo, rhi, support, gain
    evaluated: int
    sample: int
    status: str = "ok"
    seconds: float = 0.0


def sample_rows(df: DataFrame, attrs: list[str], size: int, seed: int = 0, id_col: str | None = None) -> DataFrame:
    """Exactly `size` rows (or all), chosen by a hash, the same on every run."""
    key = F.xxhash64(F.lit(seed), *([F.col(id_col)] if id_col else [F.col(a) for a in attrs]))
    return df.select(*attrs).orderBy(key, *attrs).limit(size)


def _sampled(df: DataFrame, attrs: list[str], size: int, seed: int) -> np.ndarray:
    """The rows of `sample_rows`, in its order."""
    if size <= CHOSEN_HERE:
        found = sample_rows(df, attrs, size, seed).toArrow()
    else:
        keyed = df.select(*attrs, F.xxhash64(F.lit(seed), *[F.col(a) for a in attrs]).alias("__key"))
        placed = with_row_ids(keyed.repartitionByRange("__key", *attrs).sortWithinPartitions("__key", *attrs), "__row", 0)
        found = placed.filter(F.col("__row") < size).select("__row", *attrs).toArrow().sort_by("__row")
    return np.stack([found[a].to_numpy() for a in attrs], axis=1).astype(float)


def size_of(sample_size, n: int) -> int:
    """Rows of the sample: 'sqrt', a share of the rows, or a number."""
    if sample_size == "sqrt":
        return max(2, math.isqrt(n))
    return max(2, int(sample_size * n) if isinstance(sample_size, float) else int(sample_size))


def gain_bits(inside: np.ndarray, n: int, log_share: np.ndarray, k: int, s: int) -> np.ndarray:
    """Bits saved by one box: c rows on a share 2**log_share of the space, against coding all rows on all of it."""
    p = np.clip(inside / n, 1e-12, 1 - 1e-12)
    split = n * (-p * np.log2(p) - (1 - p) * np.log2(1 - p))
    return -inside * log_share - split - 2 * k * math.log2(max(s, 2))


def grow_all(points: np.ndarray, n: int, count, perseverance: int | None = None, thoroughness: int = 100, seed: int = 0, limits: Limits | None = None) -> tuple[list[tuple], int]:
    """(lo, hi, rows inside, gain) of the kept boxes of sampled `points` in the unit cube, and the number of candidates.

    `count(boxes)` counts rows of the full table; `thoroughness` useless
    candidates in a row end the search.
    """
    limits = limits or Limits()
    s, k = points.shape
    perseverance = perseverance or max(1, s // 5)
    rng = np.random.default_rng(seed)
    kept: dict[tuple, tuple] = {}
    useless = evaluated = 0
    while useless < thoroughness and s > 1 and not limits.over_time():
        batch = [_grow(points, int(rng.integers(s)), perseverance, n, k) for _ in range(min(BATCH, thoroughness - useless))]
        for (lo, hi), inside in zip(batch, count(batch), strict=True):
            evaluated += 1
            share = float(np.log2(np.maximum(hi - lo, 1 / n)).sum())
            gain = float(gain_bits(np.array([inside], float), n, np.array([share]), k, s)[0])
            known = tuple(np.round(np.concatenate([lo, hi]), 9).tolist())
            if gain > 0 and known not in kept:
                kept[known] = (lo, hi, int(inside), gain)
                useless = 0
            else:
                useless += 1
    return list(kept.values()), evaluated


def mine(df: DataFrame, attrs: list[str], sample_size=0.5, perseverance: int | None = None, thoroughness: int = 100, seed: int = 0, seconds: float | None = None) -> SamplingResult:
    """Boxes from a sample, whatever its size; `seconds` may end the search (status 'time')."""
    spark = df.sparkSession
    limits = Limits(seconds)
    ends = df.agg(F.count(F.lit(1)).alias("n"), *[f(F.col(a).cast("double")).alias(f"{p}{i}") for i, a in enumerate(attrs) for p, f in (("l", F.min), ("h", F.max))]).first()
    n, k = ends.n, len(attrs)
    s = min(n, size_of(sample_size, n))
    low = np.array([ends[f"l{i}"] for i in range(k)])
    wide = np.maximum(np.array([ends[f"h{i}"] for i in range(k)]) - low, 1e-12)
    points = (_sampled(df, attrs, s, seed) - low) / wide
    count = lambda batch: _count(df, attrs, [(low + lo * wide, low + hi * wide) for lo, hi in batch])
    kept, evaluated = grow_all(points, n, count, perseverance, thoroughness, seed, limits)
    rows = [(i, (low + lo * wide).tolist(), (low + hi * wide).tolist(), c, g) for i, (lo, hi, c, g) in enumerate(kept, 1)]
    schema = "pid long, rlo array<double>, rhi array<double>, support long, gain double"
    return SamplingResult(spark.createDataFrame(rows, schema), evaluated, s, limits.status, limits.spent())


def _grow(points: np.ndarray, at: int, perseverance: int, n: int, k: int) -> tuple[np.ndarray, np.ndarray]:
    """The best box around the nearest sampled rows of a seed.

    The boxes grow with the rows taken in, so a point is inside from the first
    box on that reaches it on every side.
    """
    s = len(points)
    order = np.argsort(np.abs(points - points[at]).max(axis=1), kind="stable")
    lows, highs = np.minimum.accumulate(points[order]), np.maximum.accumulate(points[order])
    enters = np.zeros(s, np.int64)
    for d in range(k):
        enters = np.maximum(enters, np.searchsorted(-lows[:, d], -points[:, d]))
        enters = np.maximum(enters, np.searchsorted(highs[:, d], points[:, d]))
    inside = np.cumsum(np.bincount(enters, minlength=s)[:s]) * n / s
    share = np.log2(np.maximum(highs - lows, 1 / n)).sum(axis=1)
    gains = gain_bits(inside, n, share, k, s)[1:]
    best = np.maximum.accumulate(gains)
    rises = np.append(True, gains[1:] > best[:-1])
    last = np.maximum.accumulate(np.where(rises, np.arange(s - 1), 0))  # place of the best so far
    tired = np.flatnonzero(np.arange(s - 1) - last > perseverance)
    j = int(last[tired[0] if len(tired) else s - 2]) + 1
    return lows[j].copy(), highs[j].copy()  # a view would keep all the bounds


def _count(df: DataFrame, attrs: list[str], boxes: list) -> list[int]:
    """Rows inside each box, all boxes in one scan."""
    parts = []
    for i, (lo, hi) in enumerate(boxes):
        inside = F.lit(True)
        for a, x, y in zip(attrs, lo, hi, strict=True):
            inside = inside & F.col(a).between(float(x) - SLACK * max(1, abs(x)), float(y) + SLACK * max(1, abs(y)))
        parts.append(F.count_if(inside).alias(f"c{i}"))
    row = df.agg(*parts).first()
    return [row[f"c{i}"] for i in range(len(boxes))]


def occurrences(boxes: DataFrame, df: DataFrame, attrs: list[str], id_col: str) -> DataFrame:
    """``pid, cell_id, usage`` (a cell is a row here) of boxes with real bounds, for the Jaccard and accuracy measures.

    Rows and boxes meet in tiles of the first attribute, so a row meets only
    boxes that reach its tile.
    """
    first = F.col(attrs[0]).cast("double")
    ends = df.agg(F.min(first).alias("lo"), F.max(first).alias("hi")).first()
    wide = ((ends.hi - ends.lo) / TILES if ends.lo is not None else 0.0) or 1.0
    tile = lambda v: F.greatest(F.lit(0), F.least(F.lit(TILES), F.floor((v - F.lit(ends.lo or 0.0)) / F.lit(wide)))).cast("int")
    slack = lambda v: F.lit(SLACK) * F.greatest(F.lit(1.0), F.abs(v))
    x0, y0 = F.element_at("rlo", 1), F.element_at("rhi", 1)
    spans = boxes.select("pid", "rlo", "rhi", F.explode(F.sequence(tile(x0 - slack(x0)), tile(y0 + slack(y0)))).alias("__tile"))
    inside = F.lit(True)
    for i, a in enumerate(attrs):
        x, y = F.element_at("rlo", i + 1), F.element_at("rhi", i + 1)
        inside = inside & F.col(a).between(x - slack(x), y + slack(y))
    return df.withColumn("__tile", tile(first)).join(spans, "__tile").filter(inside).select("pid", F.col(id_col).alias("cell_id"), F.lit(1).cast("long").alias("usage"))


def as_occurrences(result: SamplingResult, df: DataFrame, attrs: list[str], id_col: str) -> DataFrame:
    return occurrences(result.boxes, df, attrs, id_col)
