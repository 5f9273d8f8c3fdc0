"""External suffix sorting by recursive induction.

`sorted_suffixes` sorts the suffixes of a text and gives the common-prefix
value of each with the one before, up to a depth.  The substrings between
leftmost-S places are named; where names repeat, the text of names is sorted in
the same way, level by level, until it has at most `memory` symbols.  From the
sorted leftmost-S suffixes all L suffixes and then all S suffixes are induced
with a priority queue: what is popped is scanned, and pushes the tuple (symbol,
position, common prefix) of the suffix one place longer.  Tuples of one symbol
come out as they went in.

The queue holds `budget` bytes; beyond that its tuples are written as sorted
runs to files in `folder`, read back block by block and merged with what is in
memory.  L suffixes wait on a tape of such files for the second scan.  Pops
are batches: as many tuples as cannot be overtaken by what they push.  The text
and the types of its suffixes are arrays (mapped from a file where they exceed
the budget); the rest of what is in memory at a time is bounded by `budget` and
`memory`.
"""

from __future__ import annotations

import os
import tempfile
import uuid

import numpy as np

#: Longest common prefix that is told apart.
DEPTH = 250
#: Bytes of tuples that a queue or tape holds before it writes them out.
BUDGET = 16 << 20
#: Symbols of a text of names that is sorted in memory.
MEMORY = 1 << 22
#: Tuples read at once from a run.
BLOCK = 1 << 16


class Spill:
    """Runs of tuples in files of a folder that Arrow's file systems reach; they belong to one sort and go with it."""

    def __init__(self, folder: str | None = None):
        self.folder, self.fs, self.base, self.written = folder, None, None, 0

    def _open(self):
        if self.fs is None:
            from pyarrow import fs

            at = self.folder or tempfile.mkdtemp(prefix="boxmdl-suffix-")  # no folder only outside a cluster
            self.fs, base = fs.FileSystem.from_uri(at if "://" in at else os.path.abspath(at))
            self.base = f"{base}/boxmdl-suffix-{uuid.uuid4().hex}"
            self.fs.create_dir(self.base)

    def write(self, *columns: np.ndarray) -> tuple:
        self._open()
        self.written += 1
        path = f"{self.base}/{self.written}"
        with self.fs.open_output_stream(path) as out:
            for c in columns:
                out.write(np.ascontiguousarray(c).tobytes())
        return path, len(columns[0]), [c.dtype for c in columns]

    def read(self, run: tuple, start: int, stop: int) -> list[np.ndarray]:
        path, n, kinds = run
        out, base = [], 0
        with self.fs.open_input_file(path) as file:
            for kind in kinds:
                out.append(np.frombuffer(file.read_at((stop - start) * kind.itemsize, base + start * kind.itemsize), kind))
                base += n * kind.itemsize
        return out

    def drop(self, run: tuple) -> None:
        self.fs.delete_file(run[0])

    def close(self) -> None:
        if self.fs is not None:
            self.fs.delete_dir(self.base)
            self.fs = None


class _Source:
    """A sorted part of the queue: columns in memory, or a run of which a block is."""

    def __init__(self, columns: list[np.ndarray] | None = None, run: tuple | None = None):
        self.columns, self.run, self.read, self.at = columns, run, 0, 0

    def head(self, spill: Spill, limit: int) -> tuple[list[np.ndarray], bool]:
        """Up to `limit` next tuples, and whether there are more."""
        if self.run is not None and (self.columns is None or self.at == len(self.columns[0])):
            stop = min(self.run[1], self.read + BLOCK)
            self.columns, self.at, self.read = spill.read(self.run, self.read, stop), 0, stop
        stop = min(len(self.columns[0]), self.at + limit)
        return [c[self.at : stop] for c in self.columns], stop < len(self.columns[0]) or self.run is not None and self.read < self.run[1]

    def empty(self) -> bool:
        return (self.columns is None or self.at == len(self.columns[0])) and (self.run is None or self.read == self.run[1])


class Queue:
    """Priority queue of tuples (key, position, common prefix), first in first out among equal keys.

    Sources are kept from old to new: runs on disk, then sorted chunks in
    memory, merged whenever a newer one is as large as an older one.
    """

    def __init__(self, spill: Spill, budget: int):
        self.spill, self.budget, self.held = spill, budget, 0
        self.sources: list[_Source] = []

    def push(self, *columns: np.ndarray) -> None:
        """Tuples of ascending keys."""
        if not len(columns[0]):
            return
        self.held += sum(c.nbytes for c in columns)
        self.sources.append(_Source(list(columns)))
        left = lambda s: len(s.columns[0]) - s.at
        while len(self.sources) > 1 and self.sources[-2].run is None and left(self.sources[-2]) <= 2 * left(self.sources[-1]):
            self._join(2)
        if self.held > self.budget:
            k = 0
            while k < len(self.sources) and self.sources[-1 - k].run is None:
                k += 1
            if k:
                self._join(k)
                chunk = self.sources.pop()
                self.sources.append(_Source(run=self.spill.write(*(c[chunk.at :] for c in chunk.columns))))
            self.held = 0

    def _join(self, k: int) -> None:
        parts, self.sources[-k:] = self.sources[-k:], []
        columns = [np.concatenate(c) for c in zip(*([c[s.at :] for c in s.columns] for s in parts), strict=True)]
        order = np.argsort(columns[0], kind="stable")
        self.sources.append(_Source([c[order] for c in columns]))

    def pop(self, limit: int) -> list[np.ndarray]:
        """About `limit` of the first tuples, in order."""
        heads = [s.head(self.spill, limit) for s in self.sources]
        bound = min((h[0][-1] for h, more in heads if more), default=None)
        take = []
        if bound is None:
            take = [len(h[0]) for h, _ in heads]
        else:
            take = [int(np.searchsorted(h[0], bound, side="left")) for h, _ in heads]
            if not any(take):
                # many of one key: those of the oldest sources, up to the first that goes on beyond its head
                take = [0] * len(heads)
                for i, (h, more) in enumerate(heads):
                    take[i] = int(np.searchsorted(h[0], bound, side="right"))
                    if more and take[i] == len(h[0]):
                        break
        for s, t in zip(self.sources, take, strict=True):
            s.at += t
        columns = [np.concatenate(c) for c in zip(*([c[:t] for c in h] for (h, _), t in zip(heads, take, strict=True)), strict=True)]
        for s in self.sources:
            if s.run is not None and s.empty():
                self.spill.drop(s.run)
        self.sources = [s for s in self.sources if not s.empty()]
        if sum(t > 0 for t in take) > 1:
            order = np.argsort(columns[0], kind="stable")
            columns = [c[order] for c in columns]
        self.held = max(0, self.held - sum(c.nbytes for c in columns))
        return columns

    def put_back(self, columns: list[np.ndarray]) -> None:
        """Tuples that were popped last: they come before all that are in the queue with the same key."""
        if len(columns[0]):
            self.sources.insert(0, _Source(columns))
            self.held += sum(c.nbytes for c in columns)


class Tape:
    """Blocks written in order and read once, backwards."""

    def __init__(self, spill: Spill, budget: int):
        self.spill, self.budget, self.blocks, self.held = spill, budget, [], 0

    def append(self, *columns: np.ndarray) -> None:
        self.held += sum(c.nbytes for c in columns)
        self.blocks.append(columns)
        if self.held > self.budget:
            parts = [b for b in self.blocks if isinstance(b[0], np.ndarray)]
            self.blocks = [b for b in self.blocks if not isinstance(b[0], np.ndarray)]
            self.blocks.append(self.spill.write(*(np.concatenate(c) for c in zip(*parts, strict=True))))
            self.held = 0

    def backwards(self):
        while self.blocks:
            block = self.blocks.pop()
            if isinstance(block[0], np.ndarray):
                yield [c[::-1] for c in block]
            else:
                for stop in range(block[1], 0, -BLOCK):
                    yield [c[::-1] for c in self.spill.read(block, max(0, stop - BLOCK), stop)]
                self.spill.drop(block)


def s_types(text: np.ndarray) -> np.ndarray:
    """Whether each suffix is smaller than the one after it (the last, the sentinel, is)."""
    n = len(text)
    rises = np.ones(n, bool)
    rises[:-1] = text[:-1] < text[1:]
    differs = np.ones(n, bool)
    differs[:-1] = text[:-1] != text[1:]
    at = np.where(differs, np.arange(n), n)
    at = np.minimum.accumulate(at[::-1])[::-1]  # the next place where neighbours differ
    return rises[at]


def _refine(rank: np.ndarray, who: np.ndarray, key: np.ndarray) -> None:
    """Order `who`, whole groups of equal rank, by `key` inside the groups; a rank is the number of smaller elements."""
    old = rank[who]
    if not len(old) or old[0] == old[-1] and (old == old[0]).all():
        order = np.argsort(key)
    elif key.dtype == np.int64:  # ranks: both fit one sort key
        order = np.argsort(old * (len(rank) + 2) + key)
    else:
        order = np.lexsort((key, old))
    who, key = who[order], key[order]
    old = rank[who]
    place = np.arange(len(who))
    first = np.ones(len(who), bool)
    first[1:] = old[1:] != old[:-1]
    split = first.copy()
    split[1:] |= key[1:] != key[:-1]
    start = np.maximum.accumulate(np.where(first, place, 0))
    rank[who] = old + np.maximum.accumulate(np.where(split, place, 0)) - start


def _tied(rank: np.ndarray) -> np.ndarray:
    """Elements that share their rank."""
    return np.flatnonzero(np.bincount(rank, minlength=len(rank) + 1)[rank] > 1)


def _names(text: np.ndarray, s_type: np.ndarray, lms: np.ndarray) -> np.ndarray:
    """Rank of the substring from each leftmost-S place to the next; equal substrings share it."""
    m = len(lms)
    wide = int(text.max()) >= 1 << 15
    ends = np.append(lms[1:], lms[-1]) + 1
    step, bits = (1, 64) if wide else (4, 16)
    typed = np.concatenate([text.astype(np.uint64) * np.uint64(2) + s_type, np.zeros(4, np.uint64)])

    def word(start, end):
        out = np.zeros(len(start), np.uint64)
        for j in range(step):
            value = np.where(start + j < end, typed[np.minimum(start + j, len(typed) - 1)], np.uint64(0))
            out = value if bits == 64 else out << np.uint64(bits) | value
        return out

    rank = np.zeros(m, np.int64)
    who, at = np.arange(m), 0
    while len(who):
        _refine(rank, who, word(lms[who] + at, ends[who]))
        at += step
        who = who[lms[who] + at < ends[who]]
        if len(who):
            who = who[np.bincount(rank[who], minlength=m + 1)[rank[who]] > 1]
    return rank


def _doubled(rank: np.ndarray, depth: int) -> np.ndarray:
    """Order of the suffixes of a text of names, up to `depth` names, by doubling; in memory."""
    m, hop = len(rank), 1
    rank = rank.copy()
    while hop <= depth:
        who = _tied(rank)
        if not len(who):
            break
        after = who + hop
        _refine(rank, who, np.where(after < m, rank[np.minimum(after, m - 1)] + 1, 0))
        hop *= 2
    return np.argsort(rank, kind="stable")


def _leftmost(s_type: np.ndarray) -> np.ndarray:
    lms = np.flatnonzero(s_type[1:] & ~s_type[:-1]) + 1
    return lms if len(lms) else np.array([len(s_type) - 1])


def _ranked_lms(text: np.ndarray, s_type: np.ndarray, lms: np.ndarray, depth: int, spill: Spill, budget: int, memory: int) -> np.ndarray:
    """The leftmost-S places, sorted by their suffixes: by name, and where names repeat by the sorted text of names."""
    names = _names(text, s_type, lms)
    if not len(_tied(names)):
        return lms[np.argsort(names, kind="stable")]
    if len(lms) <= memory:
        return lms[_doubled(names, depth)]
    used = np.zeros(len(names) + 1, np.int64)
    used[names] = 1
    reduced = (np.cumsum(used) - 1)[names]  # the sentinel, alone in its name, is the last and least
    return lms[_suffix_order(reduced, depth, spill, budget, memory)]


def _suffix_order(text: np.ndarray, depth: int, spill: Spill, budget: int, memory: int) -> np.ndarray:
    """Places of a text of names, sorted by their suffixes: another level of the induction, without common prefixes."""
    s_type = s_types(text)
    lms = _leftmost(s_type)
    ranked = _ranked_lms(text, s_type, lms, depth, spill, budget, memory)
    tape = Tape(spill, budget)
    for pos, _ in _induce(text, ~s_type, [(ranked, None)], True, depth, spill, budget, None):
        tape.append(pos)
    out = np.empty(len(text), np.int64)
    at = len(text)
    down = ((pos, None) for (pos,) in tape.backwards())
    for pos, _ in _induce(text, s_type, down, False, depth, spill, budget, None, seeds_too=True):
        out[at - len(pos) : at] = pos[::-1]
        at -= len(pos)
    return out


def _common(text: np.ndarray, a: np.ndarray, b: np.ndarray, depth: int) -> np.ndarray:
    """Common prefixes of pairs of different suffixes up to the depth, four symbols at a time."""
    wide = np.concatenate([text, np.zeros(depth + 8, text.dtype)]).astype(np.uint64)
    four = wide[:-3] << np.uint64(48) | wide[1:-2] << np.uint64(32) | wide[2:-1] << np.uint64(16) | wide[3:]
    out = np.full(len(a), depth, np.int64)
    live = np.arange(len(a))
    for k in range(0, depth, 4):
        apart = four[a[live] + k] ^ four[b[live] + k]
        ended = apart != 0
        x = apart[ended]
        out[live[ended]] = k + (x < 1 << 48).astype(np.int64) + (x < 1 << 32) + (x < 1 << 16)
        live = live[~ended]
        if not len(live):
            break
    return np.minimum(out, depth).astype(np.uint8)


def _run_lengths(text: np.ndarray, pos: np.ndarray, depth: int) -> np.ndarray:
    """Lengths, up to the depth, of the runs of one symbol that start at `pos`."""
    out = np.ones(len(pos), np.int64)
    live = np.arange(len(pos))
    for k in range(1, depth):
        at = pos[live] + k
        live = live[(at < len(text)) & (text[np.minimum(at, len(text) - 1)] == text[pos[live]])]
        if not len(live):
            break
        out[live] += 1
    return out


def _range_min(values: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """Least of values[lo..hi], ends included."""
    table, width = [values], 1
    longest = int((hi - lo).max(initial=0)) + 1
    while 2 * width <= longest:
        table.append(np.minimum(table[-1][:-width], table[-1][width:]))
        width *= 2
    level = np.frexp((hi - lo + 1).astype(np.float64))[1] - 1
    out = np.empty(len(lo), values.dtype)
    for k in range(len(table)):
        at = np.flatnonzero(level == k)
        if len(at):
            out[at] = np.minimum(table[k][lo[at]], table[k][hi[at] - (1 << k) + 1])
    return out


def _induce(text, wanted, seeds, upwards, depth, spill, budget, symbols, seeds_too=False):
    """Induce the suffixes marked in `wanted` from sorted `seeds` (blocks of places and common prefixes, in scan order).

    Scans upwards (for L suffixes) or downwards (for S suffixes, from the L
    suffixes and the sentinel) and yields blocks of (places, common prefix with
    the one scanned before) of the induced, and of the seeds if `seeds_too`.
    Without `symbols`, their number, common prefixes are not worked out.
    A key is twice the symbol (counted from the top downwards), and one more
    for seeds, which come after the induced of their symbol.
    """
    top = int(text.max())
    key = (lambda s: 2 * s.astype(np.int64)) if upwards else (lambda s: 2 * (top - s.astype(np.int64)))
    queue = Queue(spill, budget)
    for pos, lcp in seeds:
        queue.push(key(text[pos]) + 1, pos, lcp if symbols else np.zeros(len(pos), np.uint8))
    if not upwards:
        end = np.array([len(text) - 1])
        queue.push(key(text[end]) + 1, end, np.zeros(1, np.uint8))
    #: Least common prefix scanned since the last push to each symbol.
    since = np.zeros(symbols or 0, np.uint8)
    limit, last = BLOCK, None

    def values(symbol, at, lcp):
        """Common prefixes of the pushed (those at the places `at` of the scanned block, grouped by symbol)."""
        first = np.ones(len(at), bool)
        first[1:] = symbol[1:] != symbol[:-1]
        least = _range_min(lcp, np.where(first, 0, np.append(0, at[:-1] + 1)), at)
        least = np.where(first, np.minimum(least, since[symbol]), least)
        starts = np.flatnonzero(first)
        tails = at[np.append(starts[1:], len(at)) - 1] + 1
        np.minimum(since, lcp.min(), out=since)
        left = np.full(len(tails), 255, np.uint8)
        inner = tails < len(lcp)
        left[inner] = _range_min(lcp, tails[inner], np.full(int(inner.sum()), len(lcp) - 1))
        since[symbol[starts]] = left
        return np.minimum(least.astype(np.int64) + 1, depth).astype(np.uint8)

    while queue.sources:
        keys, pos, lcp = queue.pop(limit)
        before = pos - 1
        pushes = (pos > 0) & wanted[np.maximum(before, 0)]
        pushed = np.where(pushes, key(text[np.maximum(before, 0)]), np.iinfo(np.int64).max)
        # a tuple must not be scanned before a lesser one that the block itself pushes
        safe = np.append(True, np.minimum.accumulate(pushed[:-1]) >= keys[1:])
        n = len(keys) if safe.all() else int(np.argmin(safe))
        limit = max(256, 2 * n)
        queue.put_back([c[n:] for c in (keys, pos, lcp)])
        keys, pos, lcp, pushes = keys[:n], pos[:n], lcp[:n], pushes[:n]
        if symbols:
            lcp = lcp.copy()
            ahead = np.append(-2 if last is None else last[0], keys[:-1])
            other = keys >> 1 != ahead >> 1
            lcp[other] = 0  # the first of its symbol in the scan
            # in a bucket the L suffixes and the S suffixes part where the shorter run of its symbol ends
            parts = np.flatnonzero(~other & (keys != ahead))
            if len(parts):
                two = np.stack([np.where(parts > 0, pos[parts - 1], -1 if last is None else last[1]), pos[parts]])
                lcp[parts] = _run_lengths(text, two.ravel(), depth).reshape(2, -1).min(axis=0)
        last = int(keys[-1]), int(pos[-1])
        shown = slice(None) if seeds_too else keys % 2 == 0
        if seeds_too or shown.any():
            yield pos[shown], lcp[shown]
        at = np.flatnonzero(pushes)
        if len(at):
            source = pos[at] - 1
            symbol = text[source]
            order = np.argsort(key(symbol), kind="stable")
            at, source, symbol = at[order], source[order], symbol[order]
            queue.push(key(symbol), source, values(symbol, at, lcp) if symbols else np.zeros(len(at), np.uint8))
        elif symbols:
            np.minimum(since, lcp.min(), out=since)


def sorted_suffixes(text: np.ndarray, symbols: int = 258, depth: int = DEPTH, budget: int = BUDGET, memory: int = MEMORY, spill: Spill | None = None):
    """Blocks (positions, common prefix with the suffix before) of all suffixes of `text`, from the greatest down.

    `text` ends with the one sentinel 0; a block's value is that of the suffix
    and the next smaller one that was yielded, so within the whole sequence it
    belongs to each suffix and its successor in the sequence.
    """
    spill = spill or Spill()
    s_type = s_types(text)
    lms = _leftmost(s_type)
    ranked = _ranked_lms(text, s_type, lms, depth, spill, budget, memory)

    def seeds():
        for at in range(0, len(ranked), BLOCK):
            part = ranked[max(0, at - 1) : at + BLOCK]
            common = _common(text, part[:-1], part[1:], depth)
            yield (part, np.append(np.uint8(0), common).astype(np.uint8)) if at == 0 else (part[1:], common)

    tape = Tape(spill, budget)
    for pos, lcp in _induce(text, ~s_type, seeds(), True, depth, spill, budget, symbols):
        tape.append(pos, lcp)
    del ranked

    def down():
        # scanned downwards, a value belongs to the suffix after it
        carried = np.zeros(1, np.uint8)
        for pos, lcp in tape.backwards():
            yield pos, np.concatenate([carried, lcp[:-1]])
            carried = lcp[-1:]

    yield from _induce(text, s_type, down(), False, depth, spill, budget, symbols, seeds_too=True)


def _mapped(n: int, kind, spill: Spill, budget: int) -> np.ndarray:
    """An array of ones, in a file where it exceeds the budget and the spill folder is one of files."""
    kind = np.dtype(kind)
    if n * kind.itemsize <= budget:
        return np.ones(n, kind)
    spill._open()
    if spill.fs.type_name != "local":
        return np.ones(n, kind)
    out = np.memmap(f"{spill.base}/text", kind, "w+", shape=(n,))
    out[:] = 1
    return out


def repeated_starts(segments: list[bytes], length: int, budget: int = BUDGET, memory: int = MEMORY, folder: str | None = None) -> list[np.ndarray]:
    """For each segment, the starts of its `length`-byte strings that also start elsewhere in the segments; what does not fit `budget` goes to `folder`."""
    if length > DEPTH:
        raise ValueError(f"strings of at most {DEPTH} bytes")
    sizes = np.fromiter(map(len, segments), np.int64, len(segments))
    spill = Spill(folder)
    text = _mapped(int(sizes.sum()) + len(segments) + 1, np.uint16, spill, budget)  # 1 ends a segment, 0 the text
    starts = np.cumsum(np.append(0, sizes[:-1] + 1))
    flat = np.frombuffer(b"\0".join(segments), np.uint8)
    text[: len(flat)] = flat
    text[: len(flat)] += 2
    text[(starts + sizes)] = 1
    text[-1] = 0
    end = np.repeat(starts + sizes, sizes + 1)
    inside = np.arange(len(text) - 1) + length <= end  # the string lies in its segment
    found = np.zeros(len(text), bool)
    before = None
    try:
        for pos, lcp in sorted_suffixes(text, depth=length, budget=budget, memory=memory, spill=spill):
            deep = lcp >= length
            if before is not None and deep[0]:
                found[before] = found[pos[0]] = True
            same = np.flatnonzero(deep[1:]) + 1
            found[pos[same]] = True
            found[pos[same - 1]] = True
            before = pos[-1]
    finally:
        spill.close()
    found = found[:-1] & inside
    return [np.flatnonzero(found[s : s + n]) for s, n in zip(starts.tolist(), sizes.tolist(), strict=True)]
