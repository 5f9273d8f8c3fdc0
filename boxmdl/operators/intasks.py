"""Mining rounds whose candidate pairs stay in tasks; the driver holds the patterns only.

The pairs of a round lie in the shared folder, each once, as packed rows.  A
pass over them returns for every pattern its best pairs; a pair is taken if it
is the best left at both its ends and no pair that a task kept back can come
before it, so that the taken pairs are those of the greedy order over all pairs.
Patterns whose best pair is not certain wait for the next pass.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.codes import EPS
from ..plans import choose
from ..session import fixed, released
from . import kernel, neighbors
from .grid import Grid
from .model import hope, total_bits_local

#: Pairs that a pass may send to the driver (some 120 bytes each while they are matched), if the patterns' pairs lie in as many tasks as in the pass before.
SENT = 500_000
#: Pairs that a task sorts at once, and about as many as it is dealt.
BLOCK = 1 << 19
#: Effort of the compression of pairs.
LEVEL = 6


@dataclass
class Pairs:
    """Packed pairs in the shared folder, and their number.

    Their ends are rows, or places in `order`, which has the rows as they lie
    in space: then the numbers of neighbours are close, and the steps small.
    """

    frame: DataFrame
    n: int
    order: np.ndarray | None = None

    def rows(self) -> np.ndarray:
        """The packed row pairs, ascending."""
        held = np.concatenate([np.zeros(0, np.int64), *[_read(x) for x in self.frame.select("pairs").toArrow()["pairs"]]])
        return kernel.different(_as_rows(held, self.order))


def _as_rows(e: np.ndarray, order: np.ndarray | None) -> np.ndarray:
    return e if order is None else kernel.packed(order[e >> 32], order[e & kernel._LOW])


def _parts(spark, n: int) -> int:
    return max(2 * spark.sparkContext.defaultParallelism, -(-n // BLOCK))


def _stored(pairs: np.ndarray) -> bytes:
    """Ascending pairs as compressed bytes: the steps between them, byte by byte of their numbers."""
    steps = np.diff(pairs, prepend=0).view(np.uint8).reshape(-1, 8).T
    return len(pairs).to_bytes(8, "little") + (pa.Codec("zstd", LEVEL).compress(steps.tobytes(), asbytes=True) if len(pairs) else b"")


def _read(x: pa.Scalar) -> np.ndarray:
    held = x.as_buffer()
    n = int.from_bytes(held[:8].to_pybytes(), "little")
    if not n:
        return np.zeros(0, np.int64)
    steps = np.frombuffer(pa.decompress(held[8:], decompressed_size=8 * n, codec="zstd"), np.uint8)
    return np.cumsum(np.ascontiguousarray(steps.reshape(8, n).T).view(np.int64).ravel())


def _dealt(spark, chunks: DataFrame, parts: int) -> Pairs:
    """Pairs of ``part, pairs`` rows, brought together by part and freed of repeats (a pair always has the same part)."""

    def run(batches):
        held = [_read(x) for b in batches for x in b.column(1)]
        pairs = kernel.different(np.concatenate(held)) if held else np.zeros(0, np.int64)
        for at in range(0, len(pairs), BLOCK):
            block = pairs[at : at + BLOCK]
            yield pa.RecordBatch.from_arrays([pa.array([_stored(block)], pa.binary()), pa.array([len(block)], pa.int64())], names=["pairs", "n"])

    frame = fixed(chunks.repartitionById(parts, "part").mapInArrow(run, "pairs binary, n long"))
    return Pairs(frame, frame.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0])


def _places(p: kernel.Patterns, parts: int) -> np.ndarray:
    """A part for every row, so that patterns close along the first attribute share one."""
    live = p.live()
    place = np.zeros(p.size, np.int32)
    place[live[np.argsort(p.lo[live, 0], kind="stable")]] = np.arange(len(live)) * parts // max(1, len(live))
    return place


def _chunks(pairs: np.ndarray, place: np.ndarray):
    """Rows ``part, pairs``."""
    return _parted(pairs, place[pairs >> 32])


def _parted(pairs: np.ndarray, part: np.ndarray):
    order = np.argsort(part, kind="stable")
    part, pairs = part[order], pairs[order]
    cuts = np.flatnonzero(np.append(True, part[1:] != part[:-1])) if len(part) else np.zeros(0, np.int64)
    blobs = [_stored(x) for x in np.split(pairs, cuts[1:])] if len(part) else []
    return pa.RecordBatch.from_arrays([pa.array(part[cuts], pa.int32()), pa.array(blobs, pa.binary())], names=["part", "pairs"])


CHUNKS = "part int, pairs binary"


def _packing(shared, pieces):
    """Chunks from arrays of ids of both ends."""
    ids, place = shared.value
    # ids without gaps need no search
    row = (lambda x: x - ids[0]) if len(ids) and ids[-1] - ids[0] == len(ids) - 1 else (lambda x: np.searchsorted(ids, x))
    held, size = [], 0
    for a, b in pieces:
        held.append(kernel.packed(row(a), row(b)))
        size += len(held[-1])
        if size > 4 * BLOCK:
            yield _chunks(kernel.different(np.concatenate(held)), place)
            held, size = [], 0
    if held:
        yield _chunks(kernel.different(np.concatenate(held)), place)


def from_neighbors(near: DataFrame, p: kernel.Patterns, n: int) -> Pairs:
    """The pairs of ids in the two columns of `near`, about `n`."""
    spark = near.sparkSession
    parts = _parts(spark, n)
    shared = spark.sparkContext.broadcast((p.ids[: p.size].copy(), _places(p, parts)))

    def run(batches):
        yield from _packing(shared, ((b.column(0).to_numpy(), b.column(1).to_numpy()) for b in batches))

    out = _dealt(spark, near.mapInArrow(run, CHUNKS), parts)
    shared.destroy()
    return out


def from_cells(elementary: DataFrame, k: int, n_attrs: int, method: str, p: kernel.Patterns, n: int) -> Pairs:
    """The pairs of cells and their `k` neighbours, about `n`."""
    spark, n_cells = elementary.sparkSession, p.size
    if method not in ("auto", "tiled") or choose.knn_plan(n_cells) != "tiled" or not neighbors.one_block(n_cells, n_attrs):
        return from_neighbors(neighbors.neighbor_pairs(elementary, k, n_attrs, method, n_cells), p, n)
    parts = _parts(spark, n)
    shared = spark.sparkContext.broadcast((p.ids[: p.size].copy(), _places(p, parts)))

    def finish(found):
        yield from _packing(shared, ((own, near) for own, near, _ in found))

    found, sent = neighbors.finished_pairs(elementary, k, n_attrs, n_cells, finish, CHUNKS)
    out = _dealt(spark, found, parts)
    for b in (shared, *sent):
        b.destroy()
    return out


def contracted(pairs: Pairs, p: kernel.Patterns, roots: np.ndarray) -> Pairs:
    """Pairs after merges: ends that were merged become their hull; loops and repeats go."""
    spark = pairs.frame.sparkSession
    parts = _parts(spark, pairs.n)
    live = p.live()
    n_live = len(live)
    order = live[np.lexsort(p.lo[live].T[::-1])].astype(np.int32)
    place = np.zeros(p.size, np.int32)
    place[order] = np.arange(n_live)
    to = place[roots[: p.size]]
    shared = spark.sparkContext.broadcast(to if pairs.order is None else to[pairs.order])

    def run(batches):
        at = shared.value
        for b in batches:
            for x in b.column(0):
                e = _read(x)
                a, b_ = at[e >> 32], at[e & kernel._LOW]
                apart = a != b_
                e = kernel.different(kernel.packed(a[apart], b_[apart]))
                # neighbouring places share a part
                yield _parted(e, ((e >> 32) * parts // n_live).astype(np.int32))

    out = _dealt(spark, pairs.frame.mapInArrow(run, CHUNKS), parts)
    shared.destroy()
    return Pairs(out.frame, out.n, order)


def _best(pairs: np.ndarray, w: np.ndarray, ids: np.ndarray, tie: str, m: int, cut: np.ndarray):
    """The pairs among the first `m` of an end (ascending), the ends with more (into `cut`), and the last pair kept of every end in `cut`."""
    by_pair = np.argsort(pairs, kind="stable")
    pairs, w = pairs[by_pair], w[by_pair]
    order = kernel._preferred(w, pairs, ids, tie)
    ends = np.stack([pairs[order] >> 32, pairs[order] & kernel._LOW], axis=1).ravel()
    which = np.repeat(order, 2)
    by_end = np.argsort(ends, kind="stable")
    ends, which = ends[by_end], which[by_end]
    first = np.append(True, ends[1:] != ends[:-1]) if len(ends) else np.zeros(0, bool)
    starts = np.flatnonzero(first)
    nth = np.arange(len(ends)) - np.repeat(starts, np.diff(np.append(starts, len(ends))))
    cut[ends[nth >= m]] = True
    last = (nth == m - 1) & cut[ends]
    keep = np.zeros(len(pairs), bool)
    keep[which[nth < m]] = True
    return pairs[keep], w[keep], ends[last], pairs[which[last]]


def _pass(source: DataFrame, blocks_of, shared, used: np.ndarray, m: int, limit: float, eps: float, encoding: str, tie: str):
    """One pass: candidates seen, pairs with weights, and the cut ends with their last pairs."""
    flags = source.sparkSession.sparkContext.broadcast(used)

    def run(batches):
        p, gone = shared.value, flags.value
        cut = np.zeros(p.size, bool)
        kept, heavy, seen, size = [np.zeros(0, np.int64)], [np.zeros(0)], 0, 0
        for e in blocks_of(batches, p):
            seen += len(e)
            e = e[~(gone[e >> 32] | gone[e & kernel._LOW])]
            w = kernel.weights(p, e >> 32, e & kernel._LOW, eps, encoding)
            good = w > limit
            kept.append(e[good])
            heavy.append(w[good])
            size += len(kept[-1])
            if size > 2 * BLOCK:
                e, w, _, _ = _best(np.concatenate(kept), np.concatenate(heavy), p.ids, tie, m, cut)
                kept, heavy, size = [e], [w], len(e)
        out = _best(np.concatenate(kept), np.concatenate(heavy), p.ids, tie, m, cut)
        yield pa.RecordBatch.from_arrays([pa.array([seen], pa.int64()), *[pa.array([x.tobytes()], pa.binary()) for x in out]], names=["seen", "pairs", "w", "ends", "last"])

    got = source.mapInArrow(run, "seen long, pairs binary, w binary, ends binary, last binary").toArrow()
    flags.destroy()
    whole = lambda c, kind: np.concatenate([np.zeros(0, kind), *[np.frombuffer(x.as_buffer(), kind) for x in got[c]]])
    return sum(got["seen"].to_pylist()), whole("pairs", np.int64), whole("w", np.float64), whole("ends", np.int64), whole("last", np.int64)


def _certain(pairs: np.ndarray, w: np.ndarray, ends: np.ndarray, last: np.ndarray, ids: np.ndarray, tie: str, used: np.ndarray) -> np.ndarray:
    """Places of the pairs that greedy matching takes whatever the tasks kept back; `used` gets their ends.  Pairs ascend."""
    order = kernel._preferred(w, pairs, ids, tie)
    rank = np.empty(len(pairs), np.int64)
    rank[order] = np.arange(len(pairs))
    until = np.full(len(used), len(pairs), np.int64)
    np.minimum.at(until, ends, rank[np.searchsorted(pairs, last)])
    a, b = pairs[order] >> 32, pairs[order] & kernel._LOW
    place = np.arange(len(pairs))
    known = (place <= until[a]) & (place <= until[b])
    rest, taken, best = place, [], np.empty(len(used), np.int64)
    while len(rest):
        both = np.stack([a[rest], b[rest]], axis=1)[::-1]
        best[both.ravel()] = np.repeat(rest[::-1], 2)
        won = rest[(best[a[rest]] == rest) & (best[b[rest]] == rest) & known[rest]]
        if not len(won):
            break
        taken.append(won)
        used[a[won]] = used[b[won]] = True
        rest = rest[~(used[a[rest]] | used[b[rest]])]
    return order[np.concatenate(taken)] if taken else np.zeros(0, np.int64)


def _matched(spark, pairs: Pairs | None, p: kernel.Patterns, start: int, every: bool, limit: float, eps: float, encoding: str, tie: str):
    """The greedy matching of a round's candidates in its order, and their number.

    Candidates are the `pairs` whose later row is `start` or above; without
    `pairs` those rows with all live rows (`every`: each pair of live rows).
    """
    live = p.live()
    shared = spark.sparkContext.broadcast(kernel.Patterns(p.ids[: p.size].copy(), p.lo[: p.size], p.hi[: p.size], p.usage[: p.size].copy(), p.alive[: p.size].copy(), p.log_size[: p.size].copy(), p.size))
    sent = [shared]
    if pairs is not None:
        ordered = spark.sparkContext.broadcast(pairs.order)
        sent.append(ordered)
        # neighbouring parts share a task, so that an end's pairs lie in few tasks
        source = pairs.frame.coalesce(4 * spark.sparkContext.defaultParallelism)

        def blocks_of(batches, p):
            for b in batches:
                for x in b.column(0):
                    e = _as_rows(_read(x), ordered.value)
                    yield e[(e & kernel._LOW) >= start]
    else:
        parts = 4 * spark.sparkContext.defaultParallelism
        source = spark.range(0, parts, 1, parts)

        def blocks_of(batches, p):
            for b in batches:
                for part in b.column(0).to_pylist():
                    live = p.live()
                    new = live if every else live[live >= start]
                    for e in kernel._with_every(new[part::parts], live):
                        for at in range(0, len(e), BLOCK):
                            yield e[at : at + BLOCK]

    used = np.zeros(p.size, bool)
    found, heavy, seen = [], [], None
    tasks = 3.0  # in which a pattern's best pairs lie
    while True:
        free = max(1, len(live) - int(used.sum()))
        m = max(1, int(SENT / (tasks * free)))
        n, e, w, ends, last = _pass(source, blocks_of, shared, used, m, limit, eps, encoding, tie)
        seen = n if seen is None else seen
        tasks = max(tasks, len(e) / (m * free))
        by_pair = np.argsort(e, kind="stable")
        e, w = e[by_pair], w[by_pair]
        at = _certain(e, w, ends, last, p.ids, tie, used)
        found.append(e[at])
        heavy.append(w[at])
        if not len(ends):
            break
    for b in sent:
        b.destroy()
    e, w = np.concatenate(found), np.concatenate(heavy)
    by_pair = np.argsort(e, kind="stable")
    e, w = e[by_pair], w[by_pair]
    order = kernel._preferred(w, e, p.ids, tie)
    return seen, e[order], w[order]


def mine(spark, pairs: Pairs | None, p: kernel.Patterns, run: kernel.Run, grid: Grid, eps: float = EPS, scope: str = "inherited", gain_mode: str = "refreshed", tie: str = "hash", encoding: str = "plugin", requeue: bool = False, start: int = 0, total: float | None = None, after_round=None):
    """As `kernel.mine` (for requeueing with scope 'inherited' only), until the candidates fit the kernel.

    Returns the pairs, those of the next round (None: over) and the length.
    """
    n = int(p.usage[p.live()].sum())
    if total is None:
        live = p.live()
        total = total_bits_local(p.usage[live], p.log_size[live], grid, eps, encoding)
    every = pairs is None and not start
    while (pairs.n if pairs else 0) > choose.LOCAL_CANDIDATES or scope == "all" and choose.most_pairs(len(p.live())) > choose.LOCAL_CANDIDATES:
        k = len(p.live())
        # with requeueing every pair of the contracted set whose ends are there is a candidate again
        seen, e, w = _matched(spark, pairs, p, 0 if requeue else start, every, -hope(k, n, grid, eps, encoding), eps, encoding, tie)
        if not seen:
            return None, None, total
        run.explored.append(seen)
        first = p.size
        total = kernel.accept(p, run, e >> 32, e & kernel._LOW, w, k, n, grid, eps, gain_mode, encoding, total)
        if p.size == first and not (after_round and after_round()):
            return None, None, total
        if after_round and p.size > first:
            live = p.live()
            total = total_bits_local(p.usage[live], p.log_size[live], grid, eps, encoding)
        start, every = first, False
        pairs = contracted(pairs, p, run.roots()) if scope == "inherited" else None
        released(spark)
    if pairs is not None:  # at most LOCAL_CANDIDATES
        held = pairs.rows()
        return held, held if requeue else held[(held & kernel._LOW) >= start], total
    live = p.live()
    new = live if every else live[live >= start]
    return np.zeros(0, np.int64), np.concatenate([np.zeros(0, np.int64), *kernel._with_every(new, live)]), total
