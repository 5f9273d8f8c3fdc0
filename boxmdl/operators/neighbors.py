"""Nearest cells on the grid (Euclidean over indices; ties to the smaller id).

``knn`` gives ``cell_id, neighbor, d2, rank``.  Plans: all pairs with one side
broadcast (few cells); tiles: every task gets the positions of a block of
cells, sorted by tiles, and looks for each of its cells only through the
non-empty tiles that can hold a neighbour (exact in any number of attributes,
blocks of bounded size); candidate lists from sorted random projections
(approximate, by name only; its recall can be measured with `recall`).
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans import choose
from ..session import fixed
from .cells import with_row_ids

#: Attributes that tiles are cut along.
TILED = 4
#: Distances that a task works out at once.
CHUNK = 1 << 22
#: Whole numbers below this are exact as 32-bit floats.
EXACT = 1 << 24


def _d2(a, b):
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y).cast("long") * (x - y).cast("long")), F.lit(0).cast("long"), lambda s, x: s + x)


def _top(pairs: DataFrame, k: int) -> DataFrame:
    order = Window.partitionBy("cell_id").orderBy("d2", "neighbor")
    return pairs.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k)


def _all_pairs(cells: DataFrame, others: DataFrame, k: int) -> DataFrame:
    right = others.select(F.col("cell_id").alias("neighbor"), F.col("lo").alias("at"))
    pairs = cells.select("cell_id", "lo").join(F.broadcast(right), F.col("cell_id") != F.col("neighbor"))  # at most ALL_PAIRS_CELLS
    return _top(pairs.select("cell_id", "neighbor", _d2("lo", "at").alias("d2")), k)


class Tiles:
    """Points (rows of integers, with ascending ids) sorted by tiles of the grid, for exact nearest neighbours."""

    def __init__(self, ids: np.ndarray, points: np.ndarray, k: int, tile: int | None = None):
        self.width = tile or self._width(points, k)
        spot = points[:, :TILED] // self.width
        order = np.lexsort(spot.T[::-1])
        spot = spot[order]
        first = np.flatnonzero(np.append(True, (spot[1:] != spot[:-1]).any(axis=1)))
        # around the middle the numbers are small: as 32-bit floats they are exact on most grids
        self.shift = (points.min(axis=0) + points.max(axis=0)) // 2
        self.ids, self.points, self.k = ids[order], (points[order] - self.shift).astype(np.float64), k
        self.spots, self.starts, self.stops = spot[first], first, np.append(first[1:], len(order))
        self.square = (self.points * self.points).sum(axis=1)
        if 4 * self.square.max() < EXACT:
            self.points, self.square = self.points.astype(np.float32), self.square.astype(np.float32)

    @staticmethod
    def _width(points: np.ndarray, k: int) -> int:
        """Tiles of a few neighbours' size, if the points lay evenly."""
        spread = points[:, :TILED].max(axis=0) - points[:, :TILED].min(axis=0) + 1.0
        kinds = np.array([len(np.unique(points[:, d])) for d in range(min(TILED, points.shape[1]))], float)
        wide = kinds > 1
        if not wide.any():
            return max(1, int(spread.max()))
        share = max(1.0, len(points) / max(8.0, k / 4))  # tiles wanted
        return max(1, int(np.exp((np.log(spread[wide]).sum() - np.log(share)) / wide.sum())))

    def _rings(self, spot: np.ndarray, r: int) -> tuple[int, np.ndarray]:
        """The first of the tiles that are at most `r` rings from `spot` along the first attribute, and the ring of each of them."""
        # the tiles ascend along that attribute
        first, last = np.searchsorted(self.spots[:, 0], [spot[0] - r, spot[0] + r + 1])
        return first, np.abs(self.spots[first:last] - spot).max(axis=1)

    def _members(self, tiles: np.ndarray) -> np.ndarray:
        sizes = self.stops[tiles] - self.starts[tiles]
        return np.repeat(self.starts[tiles] - np.append(0, np.cumsum(sizes)[:-1]), sizes) + np.arange(sizes.sum())

    def _distances(self, queries: np.ndarray, rows: np.ndarray | slice) -> np.ndarray:
        """Squared distances; exact, as `nearest` chooses a kind of numbers that holds them."""
        points, square = (x[rows].astype(queries.dtype, copy=False) for x in (self.points, self.square))
        d = queries @ points.T
        d *= -2.0
        d += square
        d += (queries * queries).sum(axis=1)[:, None]
        return d

    @staticmethod
    def _without_own(d: np.ndarray, own: np.ndarray, ids: np.ndarray) -> np.ndarray:
        """`d`, infinite where a query meets itself; `ids` (of the columns) ascend."""
        at = np.minimum(np.searchsorted(ids, own), len(ids) - 1)
        here = np.flatnonzero(ids[at] == own)
        d[here, at[here]] = np.inf
        return d

    def nearest(self, own: np.ndarray, queries: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(query row, id, squared distance) of the k nearest points of other ids of each query, in no order."""
        spot = queries[:, :TILED].astype(np.int64) // self.width
        queries = (queries - self.shift).astype(np.float64)
        most = max(self.square.max(initial=0), (queries * queries).sum(axis=1).max(initial=0))
        queries = queries.astype(np.float32 if 4 * most < EXACT else np.float64)
        kinds, which = np.unique(spot, axis=0, return_inverse=True)
        which = which.ravel()
        order = np.argsort(which, kind="stable")
        cuts = np.append(np.flatnonzero(np.append(True, np.diff(which[order]) > 0)), len(order))
        out, far, wide = [], np.full(len(own), np.inf), []
        sizes = self.stops - self.starts
        reached = int(max(np.abs(self.spots - side).max() for side in (kinds.min(axis=0), kinds.max(axis=0))))
        for t, (s, e) in enumerate(zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True)):
            # the rings that hold enough points
            r = 1
            while True:
                begin, ring = self._rings(kinds[t], r)
                held = np.cumsum(np.bincount(ring, sizes[begin : begin + len(ring)], r + 1)[: r + 1])
                if held[-1] > self.k or r >= reached:
                    break
                r = min(2 * r, reached)
            enough = np.searchsorted(held, self.k + 1)
            first = self._members(np.flatnonzero(ring <= enough) + begin)
            first = first[np.argsort(self.ids[first])]
            if 2 * len(first) > len(self.ids):
                wide.append(order[s:e])
                continue
            step = max(1, CHUNK // max(1, len(first)))
            for at in range(s, e, step):
                q = order[at : min(e, at + step)]
                d = self._without_own(self._distances(queries[q], first), own[q], self.ids[first])
                k = min(self.k, d.shape[1])
                far[q] = np.partition(d, k - 1, axis=1)[:, k - 1] if d.shape[1] >= self.k else np.inf
            # beyond a ring of r tiles every point is more than r widths away
            reach = far[order[s:e]].max()
            r = int(np.ceil(np.sqrt(reach) / self.width)) if np.isfinite(reach) else reached
            begin, ring = self._rings(kinds[t], r)
            near = np.flatnonzero(ring <= r) + begin
            if 2 * sizes[near].sum() > len(self.ids):
                wide.append(order[s:e])
                continue
            rows = self._members(near)
            out += self._among(order[s:e], rows[np.argsort(self.ids[rows])], own, queries, far)
        if wide:
            # tiles from which most points can be neighbours are looked from together
            out += self._among(np.concatenate(wide), np.argsort(self.ids), own, queries, far)
        return tuple(np.concatenate(x) for x in zip(*out, strict=True))

    def _among(self, asking: np.ndarray, rows: np.ndarray, own: np.ndarray, queries: np.ndarray, far: np.ndarray) -> list[tuple]:
        """The nearest of the points `rows` (by ascending id) of the queries `asking`, which are not farther than `far`."""
        out, ids = [], self.ids[rows]
        k = min(self.k, len(rows))
        step = max(1, CHUNK // max(1, len(rows)))
        sample = max(4 * k, int(np.sqrt(8.0 * k * len(rows))))
        points = Tiles.__new__(Tiles)
        points.points, points.square = self.points[rows], self.square[rows]
        for at in range(0, len(asking), step):
            q = asking[at : at + step]
            d = self._without_own(points._distances(queries[q], slice(None)), own[q], ids)
            if len(rows) < 2 * sample:
                # among equal distances the smaller id, that is the earlier column, wins
                edge = np.partition(d, k - 1, axis=1)[:, k - 1 : k]
                taken = d < edge
                level = (d == edge) & np.isfinite(d)
                spare = k - taken.sum(axis=1, keepdims=True)
                taken |= level & (np.cumsum(level, axis=1) <= spare)
                r, c = np.nonzero(taken)
            else:
                # some of the points tell how far a neighbour can be; only what is as near is sorted
                some = np.partition(d[:, :: len(rows) // sample], k - 1, axis=1)[:, k - 1]
                r, c = np.nonzero(d <= np.minimum(some, far[q])[:, None])
                by = np.lexsort((d[r, c], r))
                r, c = r[by], c[by]
                starts = np.flatnonzero(np.append(True, r[1:] != r[:-1]))
                nth = np.arange(len(r)) - np.repeat(starts, np.diff(np.append(starts, len(r))))
                r, c = r[nth < k], c[nth < k]
                finite = np.isfinite(d[r, c])
                r, c = r[finite], c[finite]
            out.append((q[r], ids[c], d[r, c].astype(np.int64)))
        return out


def _with_distances(found):
    for own, near, d2 in found:
        yield pa.RecordBatch.from_arrays([pa.array(own), pa.array(near), pa.array(d2)], names=["cell_id", "neighbor", "d2"])


def _tiled(cells: DataFrame, k: int, n_cells: int, n_attrs: int, tile: int | None, finish=_with_distances, schema: str = "cell_id long, neighbor long, d2 long", sent: list | None = None) -> DataFrame:
    """Exact neighbours, a block of cells after the other (one block, unless their positions take more than NEIGHBOR_BLOCK_BYTES).

    `finish` makes a task's batches from its triples of arrays; `sent` gets the broadcasts that the frame needs.
    """
    spark = cells.sparkSession
    block = max(k + 1, choose.NEIGHBOR_BLOCK_BYTES // (8 * (n_attrs + 1)))
    least = cells.agg(F.min("cell_id")).first()[0] if n_cells else 0
    found = None
    for first in range(least, least + max(n_cells, 1), block):
        held = cells.filter(F.col("cell_id").between(first, first + block - 1)).select("cell_id", "lo").toArrow()
        if not held.num_rows:
            continue
        ids = held["cell_id"].to_numpy()
        points = held["lo"].combine_chunks().flatten().to_numpy().reshape(len(ids), -1).astype(np.int64)
        shared = spark.sparkContext.broadcast(Tiles(ids, points, k, tile))
        if sent is not None:
            sent.append(shared)

        def found_in(batches, tiles):
            for b in batches:
                if b.num_rows:
                    own = b.column(0).to_numpy()
                    row, near, d2 = tiles.nearest(own, b.column(1).flatten().to_numpy().reshape(len(own), -1))
                    yield own[row], near, d2

        def run(batches, shared=shared):
            yield from finish(found_in(batches, shared.value))

        # neighbouring ids share a task, so that few tasks look from the same tile
        n_parts = max(spark.sparkContext.defaultParallelism * 2, n_cells * k // 2_000_000)
        part = F.greatest(F.lit(0), F.least(F.lit(n_parts - 1), F.floor((F.col("cell_id") - least) * n_parts / max(n_cells, 1)))).cast("int")
        parts = cells.select("cell_id", "lo").repartitionById(n_parts, part)
        one = parts.mapInArrow(run, schema)
        found = one if found is None else found.unionByName(one)
    return found


def _projected(cells: DataFrame, k: int, n_attrs: int, projections: int, width: int, seed: int) -> DataFrame:
    """Approximate neighbours: those within `width` places on any of several sorted random projections."""
    rng = np.random.default_rng(seed)
    both = None
    for _ in range(projections):
        way = F.array(*[F.lit(float(x)) for x in rng.normal(size=n_attrs)])
        line = cells.select("cell_id", "lo", F.aggregate(F.zip_with("lo", way, lambda x, w: x * w), F.lit(0.0), lambda s, x: s + x).alias("at"))
        placed = with_row_ids(line.repartitionByRange("at", "cell_id").sortWithinPartitions("at", "cell_id"), "place")
        block = placed.withColumn("block", F.floor(F.col("place") / width))
        left = block.select("cell_id", "lo", F.explode(F.sequence(F.col("block") - 1, F.col("block") + 1)).alias("block"))
        right = block.select(F.col("cell_id").alias("neighbor"), F.col("lo").alias("near"), "block")
        pairs = left.join(right, "block").filter(F.col("cell_id") != F.col("neighbor")).select("cell_id", "neighbor", _d2("lo", "near").alias("d2"))
        top = _top(pairs, k).drop("rank")
        both = top if both is None else both.unionByName(top)
    return _top(both.distinct(), k)


def _count(cells: DataFrame, n_cells: int | None) -> int:
    return cells.count() if n_cells is None else n_cells


def knn(cells: DataFrame, k: int, n_attrs: int, method: str = "auto", n_cells: int | None = None, tile: int | None = None, projections: int = 12, width: int | None = None, seed: int = 7) -> DataFrame:
    """The k nearest cells of every cell; exact unless `method` is 'projected'.

    'projected' compares a cell with those up to `width` places (by default 16
    for each neighbour asked for) away on each of the `projections`; how many
    of the neighbours it finds depends on the data: measure it with `recall`.
    """
    if method == "auto":
        method = choose.knn_plan(_count(cells, n_cells))
    if method == "broadcast":
        return _all_pairs(cells, cells, k)
    if method == "tiled":
        return _top(_tiled(cells, k, _count(cells, n_cells), n_attrs, tile), k)
    if method == "projected":
        return _projected(cells, k, n_attrs, projections, width or max(32, 16 * k), seed)
    raise ValueError(method)


def neighbor_pairs(cells: DataFrame, k: int, n_attrs: int, method: str = "auto", n_cells: int | None = None, sent: list | None = None) -> DataFrame:
    """``cell_id, neighbor`` of `knn`, without ranks where one block of cells makes them needless; `sent` as in `_tiled`, then."""
    n = _count(cells, n_cells)
    if method == "auto":
        method = choose.knn_plan(n)
    if method == "tiled" and one_block(n, n_attrs):
        return _tiled(cells, k, n, n_attrs, None, sent=sent).select("cell_id", "neighbor")
    return knn(cells, k, n_attrs, method, n).select("cell_id", "neighbor")


def one_block(n_cells: int, n_attrs: int) -> bool:
    return 8 * (n_attrs + 1) * n_cells <= choose.NEIGHBOR_BLOCK_BYTES


def finished_pairs(cells: DataFrame, k: int, n_attrs: int, n_cells: int, finish, schema: str) -> tuple[DataFrame, list]:
    """What `finish` makes, in the tasks that find them, from arrays of cells, neighbours and distances (one block only); and the broadcasts that this needs."""
    sent: list = []
    return _tiled(cells, k, n_cells, n_attrs, None, finish, schema, sent), sent


def recall(approximate: DataFrame, exact: DataFrame) -> DataFrame:
    """Share of the exact neighbour distances that the approximate lists reach."""
    a = approximate.groupBy("cell_id").agg(F.sort_array(F.collect_list("d2")).alias("x"))
    e = exact.groupBy("cell_id").agg(F.sort_array(F.collect_list("d2")).alias("y"))
    hit = F.size(F.filter(F.arrays_zip("x", "y"), lambda z: z["x"] <= z["y"]))
    return e.join(a, "cell_id", "left").agg((F.sum(F.coalesce(hit, F.lit(0))) / F.sum(F.size("y"))).alias("recall"))


def knn_local(points: np.ndarray, k: int) -> np.ndarray:
    """Pairs (row, neighbour) of the k nearest rows of each row, ties to the smaller row."""
    n = len(points)
    k = min(k, n - 1)
    if k < 1:
        return np.zeros((0, 2), np.int64)
    points = np.asarray(points, np.int64)
    row, near, _ = Tiles(np.arange(n), points, k).nearest(np.arange(n), points)
    return np.stack([row, near], axis=1)


def edges(near: DataFrame) -> DataFrame:
    """Unordered neighbour pairs ``a < b`` without repeats: the starting candidates."""
    return near.select(F.least("cell_id", "neighbor").alias("a"), F.greatest("cell_id", "neighbor").alias("b")).dropDuplicates()


def check_every_pair(n: int) -> None:
    if n > choose.EVERY_PAIR_CELLS:
        raise ValueError(f"{n} cells make too many pairs; set a neighbour limit")


def every_pair(cells: DataFrame, n_cells: int | None = None) -> DataFrame:
    """All pairs of cells, for tables small enough."""
    check_every_pair(_count(cells, n_cells))
    right = F.broadcast(cells.select(F.col("cell_id").alias("b")))  # at most EVERY_PAIR_CELLS ids
    return cells.select(F.col("cell_id").alias("a")).join(right, F.col("a") < F.col("b"))
