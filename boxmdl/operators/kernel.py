"""The mining rounds and the pruning pass on arrays, for pattern sets that fit one process.

A round orders the candidates by weight (the order does not depend on the
number of patterns), takes pairs whose parts are both present, and ends at the
first whose gain is not positive.  Candidate pairs are held as one number each,
(row << 32) + row, in ascending order.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from ..functions import codes
from ..functions.codes import EPS, lgamma_bits
from .grid import Grid
from .model import hope, kappa, kappa_np, lgamma_bits_np, total_bits_local

#: Weights closer than this are ties.
TIE = 9
#: Pairs worked on at once.
CHUNK = 1 << 18
#: Bytes of bit sets that a search for pruning candidates may hold.
HOLDER_BYTES = 64 << 20
#: Pairs of a pattern that a search for pruning candidates looks into at once, the best first.
LOOKED_INTO = 1 << 12
#: Greatest usage of a pair up to which log-gammas come from a table.
TABLE = 1 << 22
#: Interval indices below which sides are held in 16 bits.
NARROW = 1 << 14
_LOW = (1 << 32) - 1


@dataclass
class Patterns:
    """Patterns by id: rows of the arrays, ids ascending; rows of merged patterns stay, no longer alive."""

    ids: np.ndarray
    lo: np.ndarray
    hi: np.ndarray
    usage: np.ndarray
    alive: np.ndarray
    log_size: np.ndarray
    size: int

    @classmethod
    def of(cls, ids, lo, hi, usage) -> Patterns:
        n = len(ids)
        room = 2 * n + 1
        grow = lambda a, fill=0: np.concatenate([a, np.full((room - n, *np.shape(a)[1:]), fill, a.dtype)])
        side = np.int16 if np.max(hi, initial=0) < NARROW and np.min(lo, initial=0) >= 0 else np.int32
        out = cls(grow(np.asarray(ids, np.int64)), grow(np.asarray(lo, side)), grow(np.asarray(hi, side)), grow(np.asarray(usage, np.float64)), grow(np.ones(n, bool), False), np.zeros(room), n)
        for at in range(0, n, CHUNK // 8):
            some = slice(at, min(n, at + CHUNK // 8))
            out.log_size[some] = np.log2(out.hi[some] - out.lo[some] + 1.0).sum(axis=1)
        return out

    def add(self, rows, pid: int) -> int:
        """The hull of `rows` takes their place."""
        at = self.size
        self.ids[at], self.lo[at], self.hi[at], self.usage[at] = pid, self.lo[rows].min(axis=0), self.hi[rows].max(axis=0), self.usage[rows].sum()
        self.log_size[at] = np.log2(self.hi[at] - self.lo[at] + 1.0).sum()
        self.alive[rows] = False
        self.alive[at] = True
        self.size += 1
        return at

    def add_pairs(self, a: np.ndarray, b: np.ndarray, first_id: int) -> np.ndarray:
        """The hulls of disjoint pairs take their places, with ids from `first_id` on."""
        at = np.arange(self.size, self.size + len(a))
        self.ids[at] = first_id + np.arange(len(a))
        self.lo[at], self.hi[at] = np.minimum(self.lo[a], self.lo[b]), np.maximum(self.hi[a], self.hi[b])
        self.usage[at] = self.usage[a] + self.usage[b]
        self.log_size[at] = np.log2(self.hi[at] - self.lo[at] + 1.0).sum(axis=1)
        self.alive[a] = self.alive[b] = False
        self.alive[at] = True
        self.size += len(a)
        return at

    def live(self) -> np.ndarray:
        return np.flatnonzero(self.alive[: self.size])


class Ledger:
    """A row for each merge (round, step, a, b, pid, k_before, gain, total_after), held as columns of numbers."""

    KINDS = (np.int32, np.int32, np.int64, np.int64, np.int64, np.int64, np.float64, np.float64)

    def __init__(self):
        self.parts: list[tuple[np.ndarray, ...]] = []
        self.rows: list[tuple] = []  # appended one by one, after the parts

    def append(self, row: tuple) -> None:
        self.rows.append(row)

    def extend(self, *columns) -> None:
        self._settle()
        self.parts.append(tuple(np.array(np.broadcast_to(c, len(columns[-1])), t) for c, t in zip(columns, self.KINDS, strict=True)))

    def _settle(self) -> None:
        if self.rows:
            self.parts.append(tuple(np.array(c, t) for c, t in zip(zip(*self.rows, strict=True), self.KINDS, strict=True)))
            self.rows = []

    def columns(self) -> list[np.ndarray]:
        self._settle()
        return [np.concatenate([np.zeros(0, t), *(p[i] for p in self.parts)]) for i, t in enumerate(self.KINDS)]

    def __len__(self) -> int:
        return sum(len(p[0]) for p in self.parts) + len(self.rows)

    def __iter__(self):
        self._settle()
        for p in self.parts:
            yield from zip(*(c.tolist() for c in p), strict=True)

    def __getitem__(self, at: int) -> tuple:
        return tuple(c[at].item() for c in self.columns())


@dataclass
class Run:
    patterns: Patterns
    parent: np.ndarray | None = None  # row -> row of the hull that took its place, or the row itself
    ledger: Ledger = field(default_factory=Ledger)
    explored: list[int] = field(default_factory=list)  # candidates evaluated in each round

    def __post_init__(self):
        if self.parent is None:
            self.parent = np.arange(len(self.patterns.ids))

    def roots(self) -> np.ndarray:
        """Where each row is now."""
        at = self.parent
        while True:
            up = at[at]
            if (up == at).all():
                return at
            at = up


def packed(a, b) -> np.ndarray:
    """Row pairs as single numbers, the smaller row first."""
    a, b = np.asarray(a, np.int64), np.asarray(b, np.int64)
    return (np.minimum(a, b) << 32) | np.maximum(a, b)


def pair_mix(a, b):
    """The number by which tie='hash' orders pairs of equal weight; the same arithmetic on arrays and columns."""
    x = (a * 7919 + b * 104729) % 2147483647
    return x * x % 2147483647


def different(x: np.ndarray) -> np.ndarray:
    """The different values, ascending."""
    x = np.sort(x)
    return x[np.append(True, x[1:] != x[:-1])] if len(x) else x


def _lgammas(joint: np.ndarray, eps: float) -> np.ndarray:
    """log2 of the gamma function of usages plus eps, from a table where that is less work."""
    most = int(joint.max(initial=0))
    if most < 4 * len(joint):
        return lgamma_bits_np(np.arange(most + 1) + eps)[joint.astype(np.int64)]
    return lgamma_bits_np(joint + eps)


def weights(p: Patterns, a: np.ndarray, b: np.ndarray, eps: float, encoding: str) -> np.ndarray:
    """The part of each pair's gain that depends on the pair."""
    out = np.empty(len(a))
    if not len(a):
        return out
    logs = np.log2(np.arange(1, int((p.hi.max() - min(p.lo.min(), 0)) + 2)))
    if encoding == "plugin":
        own = _lgammas(p.usage[: p.size], eps)
        least = lgamma_bits(eps)
    for at in range(0, len(a), CHUNK):
        x, y = a[at : at + CHUNK], b[at : at + CHUNK]
        hull = np.zeros(len(x))
        for d in range(p.lo.shape[1]):
            low, high = p.lo[:, d], p.hi[:, d]
            hull += logs[np.maximum(high[x], high[y]) - np.minimum(low[x], low[y])]
        u, v = p.usage[x], p.usage[y]
        joint = u + v
        space = u * p.log_size[x] + v * p.log_size[y] - joint * hull
        if encoding == "plugin":
            out[at : at + CHUNK] = _lgammas(joint, eps) + least - own[x] - own[y] + space
        else:
            out[at : at + CHUNK] = joint * np.log2(joint) - u * np.log2(u) - v * np.log2(v) + space
    return out


def _preferred(w: np.ndarray, pairs: np.ndarray, ids: np.ndarray, tie: str) -> np.ndarray:
    """Order of the pairs by falling weight; of equal weights by `tie`.  Rows ascend with ids, so packed pairs ascend with id pairs."""
    rounded = np.round(w, TIE)
    if tie == "first":
        return np.argsort(-rounded, kind="stable")
    if tie == "last":
        return len(w) - 1 - np.argsort(-rounded[::-1], kind="stable")
    mix = pair_mix(ids[pairs >> 32], ids[pairs & _LOW])
    by_mix = np.argsort(mix, kind="stable")
    return by_mix[np.argsort(-rounded[by_mix], kind="stable")]


def greedy_matching(a: np.ndarray, b: np.ndarray, n_rows: int) -> np.ndarray:
    """Which of the edges, given in order of preference, greedy matching takes.

    Again and again takes all edges that come first at both their ends.
    """
    rest, taken = np.arange(len(a)), []
    best, used = np.empty(n_rows, np.int64), np.zeros(n_rows, bool)
    while len(rest):
        ends = np.stack([a[rest], b[rest]], axis=1)[::-1]
        best[ends.ravel()] = np.repeat(rest[::-1], 2)  # of repeated places the last assignment, the most preferred, stays
        won = rest[(best[a[rest]] == rest) & (best[b[rest]] == rest)]
        taken.append(won)
        used[a[won]] = used[b[won]] = True
        rest = rest[~(used[a[rest]] | used[b[rest]])]
    return np.sort(np.concatenate(taken)) if taken else rest


def _hopeful(p: Patterns, blocks, limit: float, eps: float, encoding: str) -> tuple[np.ndarray, np.ndarray, int]:
    """The pairs (and weights) of the blocks that are above `limit`, and how many there were."""
    kept, heavy, seen = [np.zeros(0, np.int64)], [np.zeros(0)], 0
    for pairs in blocks:
        w = weights(p, pairs >> 32, pairs & _LOW, eps, encoding)
        good = w > limit
        kept.append(pairs[good])
        heavy.append(w[good])
        seen += len(pairs)
    pairs, w = np.concatenate(kept), np.concatenate(heavy)
    if (pairs[1:] < pairs[:-1]).any():
        order = np.argsort(pairs, kind="stable")
        pairs, w = pairs[order], w[order]
    return pairs, w, seen


def _with_every(new: np.ndarray, live: np.ndarray):
    """Blocks of the pairs of `new` rows with all `live` rows (which hold the new ones, the greatest rows)."""
    step = max(1, 4 * CHUNK // max(1, len(live)))
    for at in range(0, len(new), step):
        part = new[at : at + step]
        x, y = np.repeat(part, len(live)), np.tile(live, len(part))
        yield packed(x[y < x], y[y < x])


def _every_pair(live: np.ndarray):
    step = max(1, 4 * CHUNK // max(1, len(live)))
    for at in range(0, len(live), step):
        part = live[at : at + step]
        x, y = np.repeat(part, len(live)), np.tile(live, len(part))
        yield packed(x[x < y], y[x < y])


def accept(p: Patterns, run: Run, a: np.ndarray, b: np.ndarray, w: np.ndarray, k: int, n: int, grid: Grid, eps: float, gain_mode: str, encoding: str, total: float) -> float:
    """Merges the matched pairs, which come in their order, up to the first without gain; returns the length."""
    ks = k - np.arange(len(a))
    gains = np.where(ks > 1, kappa_np(ks if gain_mode == "refreshed" else np.full(len(ks), k), n, grid, eps, encoding) + w, -np.inf)
    stop = np.flatnonzero(gains <= 0)
    made = int(stop[0]) if len(stop) else len(a)
    if not made:
        return total
    a, b, gains = a[:made], b[:made], gains[:made]
    totals = total - np.cumsum(gains)
    rows = p.add_pairs(a, b, int(p.ids[: p.size].max(initial=0)) + 1)
    run.parent[a] = run.parent[b] = rows
    run.ledger.extend(len(run.explored), np.arange(1, made + 1), p.ids[a], p.ids[b], p.ids[rows], ks[:made], gains, totals)
    return float(totals[-1])


def mine(p: Patterns, edges: np.ndarray | None, grid: Grid, eps: float = EPS, scope: str = "inherited", gain_mode: str = "refreshed", tie: str = "first", encoding: str = "plugin", requeue: bool = False, run: Run | None = None, first_pairs: np.ndarray | None = None, after_round=None, total: float | None = None, left: np.ndarray | None = None) -> Run:
    """Merge rounds from the patterns `p`.

    `edges` are packed row pairs (None: every pair), `first_pairs` those of
    the first round if not all, `total` the ledger's length so far, `left` the
    pairs of earlier rounds that requeueing brings back.
    """
    run = run or Run(p)
    n = int(p.usage[p.live()].sum())
    if total is None:
        total = total_bits_local(p.usage[p.live()], p.log_size[p.live()], grid, eps, encoding)
    if edges is not None:
        edges = different(edges)
        blocks = [edges if first_pairs is None else different(first_pairs)]
    else:
        edges = np.zeros(0, np.int64)
        blocks = _every_pair(p.live()) if first_pairs is None else [different(first_pairs)]
    left = np.zeros(0, np.int64) if left is None else left
    while True:
        k = len(p.live())
        limit = -hope(k, n, grid, eps, encoding)
        if requeue:  # pairs are carried on even if they have no hope yet
            blocks = [different(np.concatenate([left, *blocks]))]
            blocks = [b[p.alive[b >> 32] & p.alive[b & _LOW]] for b in blocks]
            left = blocks[0]
        pairs, w, seen = _hopeful(p, blocks, limit, eps, encoding)
        if not seen:
            break
        run.explored.append(seen)
        order = _preferred(w, pairs, p.ids, tie)
        a, b, w = pairs[order] >> 32, pairs[order] & _LOW, w[order]
        taken = greedy_matching(a, b, p.size)
        start = p.size
        total = accept(p, run, a[taken], b[taken], w[taken], k, n, grid, eps, gain_mode, encoding, total)
        if p.size == start and not (after_round and after_round()):
            break
        if after_round and p.size > start:
            live = p.live()
            total = total_bits_local(p.usage[live], p.log_size[live], grid, eps, encoding)
        if scope == "inherited":
            at = run.roots()
            x, y = at[edges >> 32], at[edges & _LOW]
            moved = (x != edges >> 32) | (y != edges & _LOW)
            new = different(packed(x, y)[moved & (x != y)])
            edges = np.concatenate([edges[~moved], new])
            # an unmoved edge has old ends only, so it is not among the new; packed pairs with a new row at the end keep the order by ends
            blocks = [new[(new & _LOW) >= start]]
        else:
            new = np.arange(start, p.size)
            blocks = _with_every(new[p.alive[new]], p.live())
    return run


def _bits(ranks: np.ndarray, below: bool) -> np.ndarray:
    """For every rank, the set of boxes of at least (or, `below`, at most) that rank, as rows of 64-bit words."""
    k, levels = len(ranks), int(ranks.max()) + 1
    words = np.zeros((levels, (k + 63) // 64), np.uint64)
    np.bitwise_or.at(words, (ranks, np.arange(k) // 64), np.uint64(1) << (np.arange(k) % 64).astype(np.uint64))
    return np.bitwise_or.accumulate(words, axis=0) if below else np.bitwise_or.accumulate(words[::-1], axis=0)[::-1]


class Holders:
    """Finds the pairs of boxes whose hull holds a third: an intersection of bit sets for each side, or a scan where these would be too large."""

    def __init__(self, lo: np.ndarray, hi: np.ndarray):
        self.lo, self.hi = np.ascontiguousarray(lo.T), np.ascontiguousarray(hi.T)
        self.k = len(lo)
        self.above = self.below = None
        self.low, self.high = ([np.unique(side, return_inverse=True)[1] for side in sides] for sides in (self.lo, self.hi))
        levels = sum(int(r.max(initial=0)) + 1 for r in self.low + self.high)
        if levels * ((self.k + 63) // 64) * 8 <= HOLDER_BYTES:
            self.above, self.below = [_bits(r, False) for r in self.low], [_bits(r, True) for r in self.high]

    def inside(self, i: int, j: int) -> np.ndarray:
        """The boxes in the hull of i and j."""
        at = None
        for low, high in zip(self.lo, self.hi, strict=True):
            least, most = min(low[i], low[j]), max(high[i], high[j])
            at = np.flatnonzero((low >= least) & (high <= most)) if at is None else at[(low[at] >= least) & (high[at] <= most)]
            if len(at) <= 2:
                break
        return at

    def holding(self, i: int, j: np.ndarray) -> np.ndarray:
        """Whether the hull of i and each of j holds another box."""
        if self.above is None:
            return np.array([len(self.inside(i, x)) > 2 for x in j.tolist()], bool)
        out = np.zeros(len(j), bool)
        step = max(1, CHUNK // self.above[0].shape[1])
        for at in range(0, len(j), step):
            few = j[at : at + step]
            held = None
            for low, high, above, below in zip(self.low, self.high, self.above, self.below, strict=True):
                side = above[np.minimum(low[i], low[few])] & below[np.maximum(high[i], high[few])]
                held = side if held is None else np.bitwise_and(held, side, out=held)
            out[at : at + step] = np.bitwise_count(held).sum(axis=1) > 2
        return out


class EarlierPairs:
    """Weights (as `weights`) of a pattern with those of smaller rows, all of them `p`'s."""

    def __init__(self, p: Patterns, eps: float, encoding: str):
        self.lo, self.hi = np.ascontiguousarray(p.lo.T), np.ascontiguousarray(p.hi.T)
        self.usage, self.log_size, self.eps, self.encoding = p.usage, p.log_size, eps, encoding
        sides = np.log2(self.hi - self.lo + 1.0)
        self.rest = {d: sides[d + 1 :].sum(axis=0) for d in range(3, len(sides) - 1, 4)}  # log sizes over the attributes after d
        self.logs = np.log2(np.arange(1, int(self.hi.max() - min(self.lo.min(), 0)) + 2))
        self.table = None
        if encoding == "plugin":
            self.own = lgamma_bits_np(p.usage + eps)
            most = int(np.sort(p.usage)[-2:].sum())
            if most <= TABLE:
                self.table = lgamma_bits_np(np.arange(most + 1) + eps)

    def of(self, y: int, floor: float) -> tuple[np.ndarray, np.ndarray]:
        """The rows before `y` whose rounded weight with it is `floor` or more, and the weights."""
        x, u, v = np.arange(y), self.usage[:y], self.usage[y]
        joint = u + v
        if self.encoding == "plugin":
            data = (self.table[joint.astype(np.int64)] if self.table is not None else lgamma_bits_np(joint + self.eps)) + lgamma_bits(self.eps) - self.own[:y] - self.own[y]
        else:
            data = joint * np.log2(joint) - u * np.log2(u) - v * np.log2(v)
        space, hull = u * self.log_size[:y] + v * self.log_size[y], np.zeros(y)
        for d, (low, high) in enumerate(zip(self.lo, self.hi, strict=True)):
            near = slice(y) if len(x) == y else x
            hull += self.logs[np.maximum(high[near], high[y]) - np.minimum(low[near], low[y])]
            if d in self.rest and np.isfinite(floor):
                # the hull is at least as large as either box along the other attributes
                good = np.flatnonzero(data + space - joint * (hull + np.maximum(self.rest[d][near], self.rest[d][y])) > floor - 1e-3)
                x, joint, data, space, hull = x[good], joint[good], data[good], space[good], hull[good]
        w = data + (space - joint * hull)
        good = np.flatnonzero(np.round(w, TIE) >= floor)
        return x[good], w[good]


def _compact(p: Patterns, live: np.ndarray) -> Patterns:
    """The `live` rows, with the row numbers as ids."""
    return Patterns(live, p.lo[live].astype(np.int32), p.hi[live].astype(np.int32), p.usage[live], np.ones(len(live), bool), p.log_size[live], len(live))


def _until(pairs: np.ndarray, w: np.ndarray, floor: tuple[float, int] | None) -> np.ndarray:
    """Which pairs come before the pair `floor` (rounded weight, packed), or are it."""
    rounded = np.round(w, TIE)
    return np.ones(len(w), bool) if floor is None else (rounded > floor[0]) | ((rounded == floor[0]) & (pairs <= floor[1]))


def _last(pairs: np.ndarray, w: np.ndarray) -> tuple[float, int]:
    return float(np.round(w[-1], TIE)), int(pairs[-1])


def prune_pairs(few: Patterns, rows, most: int | None, eps: float, encoding: str, floor: tuple[float, int] | None = None):
    """The `most` pairs (packed ids of `few`) of largest weight whose hull holds another pattern, and the weights.

    A pair's later part is among `rows`; pairs after `floor` are left out.  The
    third value is the pair up to which the list is whole (None: all of it).
    """
    holders, earlier = Holders(few.lo, few.hi), EarlierPairs(few, eps, encoding)
    pairs, heavy = np.zeros(0, np.int64), np.zeros(0)
    held, size = [], 0

    def better():
        nonlocal pairs, heavy, held, size, floor
        pairs, heavy = np.concatenate([pairs, *(e for e, _ in held)]), np.concatenate([heavy, *(w for _, w in held)])
        held, size = [], 0
        order = np.lexsort((pairs, -np.round(heavy, TIE)))
        pairs, heavy = pairs[order][:most], heavy[order][:most]
        if most is not None and len(order) > most:
            floor = _last(pairs, heavy)

    for y in rows:
        x, w = earlier.of(y, -np.inf if floor is None else floor[0])
        e = (few.ids[x] << 32) | few.ids[y]
        order = np.lexsort((e, -np.round(w, TIE))) if most is not None and len(x) > LOOKED_INTO else np.arange(len(x))
        for at in range(0, len(x), LOOKED_INTO):
            good = order[at : at + LOOKED_INTO]
            good = good[_until(e[good], w[good], floor)]
            good = good[holders.holding(y, x[good])]
            held.append((e[good], w[good]))
            size += len(good)
            if size > (CHUNK if most is None else most):
                better()
    better()
    return pairs, heavy, floor


class Holding:
    """The pairs whose hull holds a third pattern, the best first, kept from one pass of pruning to the next.

    A pair that holds none never comes to hold one: what a new hull holds, its
    parts held before.  So after a search of all pairs only those of new
    patterns are looked for, until too few pairs of the search are left.
    """

    def __init__(self, p: Patterns, top_n: int | None, eps: float, encoding: str, find=None):
        self.p, self.top_n = p, top_n
        self.find = find or (lambda few, rows, top_n, floor: prune_pairs(few, rows, top_n, eps, encoding, floor))
        self.pairs = self.w = self.floor = None
        self.seen = 0

    def best(self) -> np.ndarray:
        """The first `top_n`, packed."""
        p = self.p
        live = p.live()
        few = _compact(p, live)
        new = np.flatnonzero(live >= self.seen)
        self.seen = p.size
        if self.pairs is not None and 12 * len(new) < len(live):
            there = p.alive[self.pairs >> 32] & p.alive[self.pairs & _LOW]
            pairs, w, floor = self.find(few, new, self.top_n, self.floor)
            pairs, w = np.concatenate([self.pairs[there], pairs]), np.concatenate([self.w[there], w])
            self.floor = floor
            order = np.lexsort((pairs, -np.round(w, TIE)))
            order = order[_until(pairs[order], w[order], floor)]
            self.pairs, self.w = pairs[order], w[order]
            if self._first(few) or floor is None:
                return self.pairs[: self.top_n]
        self.pairs, self.w, self.floor = self.find(few, np.arange(1, len(live)), self.top_n, None)
        return self.pairs[: self.top_n]

    def _first(self, few: Patterns) -> bool:
        """Leaves out pairs that hold no third any longer, until `top_n` are found; whether they are."""
        holders = Holders.__new__(Holders)
        holders.lo, holders.hi = np.ascontiguousarray(few.lo.T), np.ascontiguousarray(few.hi.T)
        a, b = np.searchsorted(few.ids, self.pairs >> 32), np.searchsorted(few.ids, self.pairs & _LOW)
        keep, found = np.ones(len(a), bool), 0
        for at, (i, j) in enumerate(zip(a.tolist(), b.tolist(), strict=True)):
            keep[at] = len(holders.inside(i, j)) > 2
            found += keep[at]
            if found == self.top_n:
                break
        self.pairs, self.w = self.pairs[keep], self.w[keep]
        return found == self.top_n


def prune(p: Patterns, run: Run, grid: Grid, eps: float = EPS, top_n: int | None = 1000, order: str = "id", encoding: str = "plugin", find=None) -> int:
    """Merge several patterns at once where a pair's hull holds others; returns the number of merges.

    `find(few, rows, top_n, floor)` looks for the pairs (default: `prune_pairs` here).
    """
    n = int(p.usage[p.live()].sum())
    log = lambda x: lgamma_bits(x + eps) if encoding == "plugin" else (-x * np.log2(x) if x else 0.0)
    merges = 0
    holding = Holding(p, top_n, eps, encoding, find)
    while True:
        live = p.live()
        found = holding.best()
        total = total_bits_local(p.usage[live], p.log_size[live], grid, eps, encoding)
        before, start, k = merges, p.size, len(live)
        lows, highs = np.ascontiguousarray(p.lo[live].T), np.ascontiguousarray(p.hi[live].T)
        fewer: dict[int, float] = {}  # kappa by the number of patterns merged, for this k
        for a, b in zip((found >> 32).tolist(), (found & _LOW).tolist(), strict=True):
            if not (p.alive[a] and p.alive[b]):
                continue
            low, high = np.minimum(p.lo[a], p.lo[b]), np.maximum(p.hi[a], p.hi[b])
            hull = float(np.log2(high - low + 1.0).sum())
            at = np.flatnonzero((lows[0] >= low[0]) & (highs[0] <= high[0]))
            for d in range(1, len(low)):
                at = at[(lows[d][at] >= low[d]) & (highs[d][at] <= high[d])]
            made = slice(start, p.size)
            inside = np.append(live[at], np.flatnonzero((p.lo[made] >= low).all(axis=1) & (p.hi[made] <= high).all(axis=1)) + start)
            inside = inside[p.alive[inside] & (inside != a) & (inside != b)].tolist()
            inside.sort(key=lambda h: p.ids[h] if order == "id" else (-p.usage[h], p.ids[h]))
            members = [a, b]
            joint = own = space = 0.0
            for h in members:
                joint, own, space = joint + p.usage[h], own + log(p.usage[h]), space + p.usage[h] * p.log_size[h]

            def gain_of(m, joint, own, space):
                if m not in fewer:
                    fewer[m] = kappa(k, n, grid, eps, m - 1, encoding)
                if encoding == "plugin":
                    return fewer[m] + log(joint) + (m - 1) * lgamma_bits(eps) - own + space - joint * hull  # noqa: B023
                return fewer[m] + own - log(joint) + space - joint * hull  # noqa: B023

            gain = gain_of(2, joint, own, space)
            for h in inside:
                wider = joint + p.usage[h], own + log(p.usage[h]), space + p.usage[h] * p.log_size[h]
                with_h = gain_of(len(members) + 1, *wider)
                if with_h > gain:
                    members.append(h)
                    gain, (joint, own, space) = with_h, wider
            if gain > 0:
                pid = int(p.ids[: p.size].max()) + 1
                row = p.add(members, pid)
                run.parent[members] = row
                total -= gain
                merges += 1
                run.ledger.append((0, merges, int(p.ids[a]), int(p.ids[b]), pid, k, float(gain), float(total)))
                k -= len(members) - 1
                fewer = {}
        if merges == before:
            return merges
