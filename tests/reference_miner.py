"""A plain miner for tests: recomputes the whole length for every gain."""

import itertools
import math


def lnat(n):
    total, term = math.log2(2.865064), float(n)
    while (term := math.log2(term)) > 0:
        total += term
    return total


def length(boxes, bins, eps):
    """boxes: list of (lo, hi, usage)."""
    g = lambda x: math.lgamma(x) / math.log(2)
    n, k = sum(u for _, _, u in boxes), len(boxes)
    out = lnat(len(bins)) + sum(lnat(b) for b in bins) + lnat(k) + k * sum(math.log2(b * (b + 1) / 2) for b in bins) + lnat(n)
    out += g(n + eps * k) - g(eps * k) - sum(g(u + eps) - g(eps) for _, _, u in boxes)
    return out + sum(u * sum(math.log2(h - low + 1) for low, h in zip(lo, hi)) for lo, hi, u in boxes)


def join(a, b):
    return tuple(map(min, a[0], b[0])), tuple(map(max, a[1], b[1])), a[2] + b[2]


def mine(cells, bins, k, eps=0.5, scope="inherited", tie="first"):
    """cells: list of (index tuple, usage) in order; returns boxes by id and the merges."""
    live = {i: (c, c, u) for i, (c, u) in enumerate(cells, 1)}
    d2 = lambda a, b: sum((x - y) ** 2 for x, y in zip(a, b))
    edges = set()
    for i, (c, _) in enumerate(cells, 1):
        near = sorted((d2(c, o), j) for j, (o, _) in enumerate(cells, 1) if j != i)
        edges |= {(min(i, j), max(i, j)) for _, j in near[:k]}
    pairs, merges, next_id = set(edges), [], len(cells) + 1
    while pairs:
        pairs = {p for p in pairs if p[0] in live and p[1] in live}
        base = length(list(live.values()), bins, eps)
        gain = {}
        for a, b in pairs:
            rest = [v for i, v in live.items() if i not in (a, b)]
            gain[a, b] = base - length([*rest, join(live[a], live[b])], bins, eps)
        mix = lambda a, b: ((a * 7919 + b * 104729) % 2147483647) ** 2 % 2147483647
        key = {"first": lambda p: p, "last": lambda p: (-p[0], -p[1]), "hash": lambda p: (mix(*p), *p)}[tie]
        order = sorted(pairs, key=lambda p: (-round(gain[p], 7), key(p)))
        first, renamed = next_id, {}
        for a, b in order:
            if a not in live or b not in live:
                continue
            rest = [v for i, v in live.items() if i not in (a, b)]
            won = length(list(live.values()), bins, eps) - length([*rest, join(live[a], live[b])], bins, eps)
            if won <= 0:
                break
            live[next_id] = join(live.pop(a), live.pop(b))
            merges.append((a, b, next_id, won))
            renamed |= {a: next_id, b: next_id}
            next_id += 1
        if next_id == first:
            break
        if scope == "inherited":
            edges = {tuple(sorted((renamed.get(a, a), renamed.get(b, b)))) for a, b in edges}
            edges = {e for e in edges if e[0] != e[1]}
            pairs = {e for e in edges if e[1] >= first}
        else:
            pairs = {(a, b) for a, b in itertools.combinations(sorted(live), 2) if b >= first}
    return live, merges


def partitions(items):
    if not items:
        yield []
        return
    head, *tail = items
    for part in partitions(tail):
        yield [[head], *part]
        for i in range(len(part)):
            yield [*part[:i], [head, *part[i]], *part[i + 1 :]]


def optimum(cells, bins, eps=0.5):
    """Least length over all ways to group the cells."""
    best = math.inf
    for part in partitions(cells):
        boxes = [(tuple(map(min, *(c for c, _ in g))) if len(g) > 1 else g[0][0], tuple(map(max, *(c for c, _ in g))) if len(g) > 1 else g[0][0], sum(u for _, u in g)) for g in part]
        best = min(best, length(boxes, bins, eps))
    return best
