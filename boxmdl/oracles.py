"""DuckDB SQL for the mining queries, written from the definitions and apart from the Spark code."""

from __future__ import annotations

from .functions.codes import C0, EPS
from .sources.workloads import LAYOUTS, slices

_SECONDS = "date_diff('second', TIMESTAMP '1970-01-01', {0})::DOUBLE"

#: attributes, and the view that gives them with a label (and an id where rows are reported)
VIEWS = {
    "W1": (("l_quantity", "l_extendedprice", "l_discount", "l_tax"), "SELECT l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag AS label FROM lineitem"),
    "W2": (("l_extendedprice", "l_shipdate"), f"SELECT l_extendedprice, {_SECONDS.format('l_shipdate')} AS l_shipdate, l_linestatus AS label FROM lineitem"),
    "W3": (("o_totalprice", "o_orderdate"), f"SELECT o_orderkey AS obj_id, o_totalprice, {_SECONDS.format('o_orderdate')} AS o_orderdate, o_orderstatus AS label FROM orders"),
    "W4": (("p_size", "p_retailprice"), "SELECT p_partkey AS obj_id, p_size::DOUBLE AS p_size, p_retailprice, p_brand AS label FROM part"),
    "W5": (("c_acctbal", "c_nationkey"), "SELECT c_custkey AS obj_id, c_acctbal, c_nationkey::DOUBLE AS c_nationkey, c_mktsegment AS label FROM customer"),
    "W6": (("value", "ts", "k"), f"SELECT event_id AS obj_id, value, {_SECONDS.format('ts')} AS ts, regexp_extract(props, '\"k\": *(-?[0-9.]+)', 1)::DOUBLE AS k, event_type AS label FROM events"),
    "W7": (("e1", "e2", "e3", "e4"), "SELECT vec_id AS obj_id, embedding[1]::DOUBLE AS e1, embedding[2]::DOUBLE AS e2, embedding[3]::DOUBLE AS e3, embedding[4]::DOUBLE AS e4, label::VARCHAR AS label FROM embeddings"),
    "W9": (("n_chars", "spaces", "words"), "SELECT doc_id AS obj_id, n_chars::DOUBLE AS n_chars, (length(text) - length(replace(text, ' ', '')))::DOUBLE AS spaces, (len(list_distinct(string_split(lower(text), ' '))) - list_contains(string_split(lower(text), ' '), '')::INT)::DOUBLE AS words, quality::VARCHAR AS label FROM documents JOIN labels USING (doc_id)"),
    "W10": (("s_acctbal", "s_nationkey"), "SELECT s_suppkey AS obj_id, s_acctbal, s_nationkey::DOUBLE AS s_nationkey, n_regionkey::VARCHAR AS label FROM supplier JOIN nation ON s_nationkey = n_nationkey"),
    "W12": (("turn", "text_length"), "SELECT turn::DOUBLE AS turn, length(text)::DOUBLE AS text_length, role AS label FROM conversations"),
}


def lnat(n: str) -> str:
    """Universal integer code of an SQL expression."""
    parts, term, limit = [], f"log2({n})", 1
    for limit in (1, 2, 4, 16, 65536):
        parts.append(f"CASE WHEN {n} > {limit} THEN {term} ELSE 0 END")
        term = f"log2({term})"
    return f"(CASE WHEN {n} < 1 THEN 0 ELSE log2({C0}) + {' + '.join(parts)} END)"


def lg(x: str) -> str:
    return f"(lgamma({x}) / ln(2))"


def grid(w: str, bins) -> str:
    """CTEs ``w`` (view), ``g`` (one row: n, B, lo_i, hi_i)."""
    attrs, view = VIEWS[w]
    b = "greatest(1, floor(sqrt(count(*))))::INT" if bins == "sqrt" else f"{bins}::INT"
    ends = ", ".join(f"min({a}) AS lo_{i}, max({a}) AS hi_{i}" for i, a in enumerate(attrs))
    return f"w AS ({view}), g AS (SELECT count(*) AS n, {b} AS nb, {ends} FROM w)"


def disc(w: str, bins) -> str:
    attrs, _ = VIEWS[w]
    cols = ", ".join(f"(CASE WHEN hi_{i} <= lo_{i} THEN 0 ELSE greatest(0, least(nb - 1, floor(({a} - lo_{i}) / (hi_{i} - lo_{i}) * nb))) END)::INT AS b_{i}" for i, a in enumerate(attrs))
    return f"{grid(w, bins)}, d AS (SELECT w.*, {cols} FROM w, g)"


def names(w: str, prefix: str = "b_") -> str:
    return ", ".join(f"{prefix}{i}" for i in range(len(VIEWS[w][0])))


def cells(w: str, bins) -> str:
    return f"{disc(w, bins)}, c AS (SELECT row_number() OVER (ORDER BY {names(w)}) AS cell_id, {names(w)}, count(*) AS usage FROM d GROUP BY {names(w)})"


def hulls(w: str, bins) -> str:
    """Boxes by label in interval indices: ``h`` (pid, label, usage, l_i, h_i, ls)."""
    k = len(VIEWS[w][0])
    ends = ", ".join(f"min(b_{i}) AS l_{i}, max(b_{i}) AS h_{i}" for i in range(k))
    size = " + ".join(f"log2(max(b_{i}) - min(b_{i}) + 1)" for i in range(k))
    return f"{cells(w, bins)}, h AS (SELECT row_number() OVER (ORDER BY label) AS pid, label, count(*) AS usage, {ends}, {size} AS ls FROM d GROUP BY label)"


def side_bits(w: str) -> str:
    return f"{len(VIEWS[w][0])} * log2(nb * (nb + 1) / 2.0)"


def grid_bits(w: str) -> str:
    k = len(VIEWS[w][0])
    return f"({lnat(str(k))} + {k} * {lnat('nb')})"


def equal_width(w: str, bins) -> str:
    rows = " UNION ALL ".join(f"SELECT '{a}' AS attr, nb AS n_bins, lo_{i} AS lo, hi_{i} AS hi FROM g" for i, a in enumerate(VIEWS[w][0]))
    return f"WITH {grid(w, bins)} {rows}"


def cell_rows(w: str, bins) -> str:
    return f"WITH {cells(w, bins)} SELECT * FROM c"


def length(w: str, bins, source: str = "c", encoding: str = "plugin") -> str:
    """All parts of the length of the cells (``c``) or the label hulls (``h``)."""
    ctes = cells(w, bins) if source == "c" else hulls(w, bins)
    ls = "0.0" if source == "c" else "ls"
    t = f"t AS (SELECT sum(usage)::BIGINT AS n, count(*) AS k, sum({lg(f'usage + {EPS}')}) AS slg, sum(usage * {ls}) AS rec, sum(usage * log2(usage)) AS ulog FROM {source})"
    data = f"{lg(f't.n + {EPS} * k')} - {lg(f'{EPS} * k')} - slg + k * {lg(str(EPS))}" if encoding == "plugin" else "t.n * log2(t.n) - ulog"
    return f"""WITH {ctes}, {t}, p AS (SELECT t.n, k, {grid_bits(w)} AS grid, {lnat('k')} + k * {side_bits(w)} AS patterns, {lnat('t.n')} AS "count", {data} AS data, rec::DOUBLE AS reconstruction FROM t, g)
SELECT n, k, round(grid, 6) AS grid, round(patterns, 6) AS patterns, round("count", 6) AS "count", round(data, 6) AS data, round(reconstruction, 6) AS reconstruction,
       round(grid + patterns + "count" + data + reconstruction, 6) AS total FROM p"""


def describe(specs: list[tuple[str, object]]) -> str:
    parts = []
    for w, bins in specs:
        k = len(VIEWS[w][0])
        distinct = " + ".join(f"count(DISTINCT b_{i})" for i in range(k))
        parts.append(f"SELECT * FROM (WITH {disc(w, bins)} SELECT '{w}' AS workload, '{bins}' AS bins, count(*) AS n, {k}::BIGINT AS k, ({distinct})::BIGINT AS n_intervals, count(DISTINCT label) AS classes FROM d)")
    return " UNION ALL ".join(parts)


def hull_real(w: str) -> str:
    attrs, view = VIEWS[w]
    ends = ", ".join(f"min({a}) AS lo_{i}, max({a}) AS hi_{i}" for i, a in enumerate(attrs))
    return f"SELECT label, count(*) AS usage, {ends} FROM ({view}) GROUP BY label"


def d2(w: str, a: str, b: str) -> str:
    return " + ".join(f"({a}.b_{i} - {b}.b_{i}) * ({a}.b_{i} - {b}.b_{i})" for i in range(len(VIEWS[w][0])))


def knn(w: str, bins, k: int) -> str:
    """CTE ``nn`` (cell_id, neighbor, d2, rank)."""
    return f"{cells(w, bins)}, nn AS (SELECT x.cell_id, y.cell_id AS neighbor, ({d2(w, 'x', 'y')})::BIGINT AS d2, row_number() OVER (PARTITION BY x.cell_id ORDER BY {d2(w, 'x', 'y')}, y.cell_id)::INT AS rank FROM c x JOIN c y ON x.cell_id <> y.cell_id QUALIFY rank <= {k})"


def knn_rows(w: str, bins, k: int) -> str:
    return f"WITH {knn(w, bins, k)} SELECT * FROM nn"


def edges(w: str, bins, k: int) -> str:
    return f"{knn(w, bins, k)}, e AS (SELECT DISTINCT least(cell_id, neighbor) AS a, greatest(cell_id, neighbor) AS b FROM nn)"


def edge_rows(w: str, bins, k: int) -> str:
    return f"WITH {edges(w, bins, k)} SELECT a, b FROM e"


def weight(u_a: str, u_b: str, space: str) -> str:
    return f"{lg(f'{u_a} + {u_b} + {EPS}')} + {lg(str(EPS))} - {lg(f'{u_a} + {EPS}')} - {lg(f'{u_b} + {EPS}')} + {space}"


def kappa(w: str, k: str, n: str) -> str:
    return f"({lnat(k)} - {lnat(f'({k} - 1)')} + {side_bits(w)} + {lg(f'{n} + {EPS} * {k}')} - {lg(f'{n} + {EPS} * ({k} - 1)')} + {lg(f'{EPS} * ({k} - 1)')} - {lg(f'{EPS} * {k}')})"


def pair_weights(w: str, bins, k: int, top: int | None = None) -> str:
    joint = " + ".join(f"log2(abs(x.b_{i} - y.b_{i}) + 1)" for i in range(len(VIEWS[w][0])))
    rows = f"SELECT a, b, {weight('x.usage', 'y.usage', f'(0 - (x.usage + y.usage) * ({joint}))')} AS w FROM e JOIN c x ON x.cell_id = a JOIN c y ON y.cell_id = b"
    if top is None:
        return f"WITH {edges(w, bins, k)} SELECT a, b, round(w, 6) AS w FROM ({rows})"
    return f"WITH {edges(w, bins, k)}, kk AS (SELECT count(*) AS kc FROM c) SELECT a, b, round(w + {kappa(w, 'kc', 'g.n')}, 6) AS gain FROM ({rows}), kk, g ORDER BY round(w, 9) DESC, a, b LIMIT {top}"


def _box(ids: str, boxes: str = "bx") -> str:
    return f"list_filter({boxes}, lambda z: z.id = {ids})[1]"


def _hull_bits(a: str, b: str) -> str:
    return f"list_sum(list_transform(range(1, len({a}.lo) + 1), lambda i: log2(greatest({a}.hi[i], {b}.hi[i]) - least({a}.lo[i], {b}.lo[i]) + 1)))"


def _ranked(pairs: str, boxes: str = "bx") -> str:
    """Pairs {a, b} as {s, t, a, b, w}, the one to take first in front: rounded weight, then the tie number, then ids."""
    a, b = _box("p.a", boxes), _box("p.b", boxes)
    both = f"list_transform({pairs}, lambda p: {{'p': p, 'x': {a}, 'y': {b}}})"
    w = weight("r.x.u", "r.y.u", f"(r.x.u * r.x.ls + r.y.u * r.y.ls - (r.x.u + r.y.u) * {_hull_bits('r.x', 'r.y')})")
    mix = "(p.a * 7919 + p.b * 104729) % 2147483647"
    weighed = f"list_transform({both}, lambda r: {{'p': r.p, 'w': {w}}})"
    keyed = f"list_transform({weighed}, lambda r: {{'s': -round(r.w, 9), 't': {mix.replace('p.', 'r.p.')}, 'a': r.p.a, 'b': r.p.b, 'w': r.w}})"
    return f"list_sort(list_transform({keyed}, lambda r: {{'s': r.s, 't': r.t * r.t % 2147483647, 'a': r.a, 'b': r.b, 'w': r.w}}))"


def _new_box(a: str, b: str, name: str) -> str:
    side = lambda f, c: f"list_transform(range(1, len({a}.lo) + 1), lambda i: {f}({a}.{c}[i], {b}.{c}[i]))"
    return f"{{'id': {name}, 'lo': {side('least', 'lo')}, 'hi': {side('greatest', 'hi')}, 'u': {a}.u + {b}.u, 'ls': {_hull_bits(a, b)}}}"


def _start(w: str, bins, k: int | None) -> str:
    """CTE ``s0``: the cells as a list of boxes, and the neighbour edges (every pair without a limit)."""
    spot = f"[{names(w)}]"
    near = edges(w, bins, k) if k else f"{cells(w, bins)}, e AS (SELECT x.cell_id AS a, y.cell_id AS b FROM c x JOIN c y ON x.cell_id < y.cell_id)"
    return f"""{near}, s0 AS (SELECT (SELECT list({{'id': cell_id, 'lo': {spot}, 'hi': {spot}, 'u': usage, 'ls': 0.0::DOUBLE}} ORDER BY cell_id) FROM c) AS bx, coalesce((SELECT list({{'a': a, 'b': b}}) FROM e), []) AS e, (SELECT count(*) FROM c) AS k)"""


def merging(w: str, bins, k: int | None, scope: str) -> str:
    """CTEs that mine step by step; ``st`` has a row for each step: a merge (kind 1), the start of a round (0) or the end (2).

    The state of a step is one row: boxes, edges, the candidates still to take
    and the merges of the round.
    """
    old = "{'a': 0::BIGINT, 'b': 0::BIGINT}"
    to = lambda end: f"coalesce(list_filter(m, lambda z: z.o = p.{end})[1].n, p.{end})"
    moved = f"list_transform(e, lambda p: {{'a': {to('a')}, 'b': {to('b')}}})"
    next_edges = f"list_distinct(list_filter(list_transform({moved}, lambda p: {{'a': least(p.a, p.b), 'b': greatest(p.a, p.b)}}), lambda p: p.a <> p.b))"
    fresh = "list_filter(e2, lambda p: p.b >= first_new)" if scope == "inherited" else "flatten(list_transform(list_filter(bx, lambda y: y.id >= first_new), lambda y: list_transform(list_filter(bx, lambda x: x.id < y.id), lambda x: {'a': x.id, 'b': y.id})))"
    gain = f"CASE WHEN len(q) = 0 OR k < 2 THEN -1.0 ELSE q[1].w + {kappa(w, 'k', 'n')} END"
    return f"""{_start(w, bins, k)},
st AS (
  SELECT 0 AS kind, 1 AS rnd, 0 AS step, s0.k AS k, s0.k + 1 AS next_id, s0.k + 1 AS first_new, bx, e, []::STRUCT(o BIGINT, n BIGINT)[] AS m, {_ranked('e')} AS q, 0::BIGINT AS a, 0::BIGINT AS b, 0.0::DOUBLE AS gain FROM s0
  UNION ALL
  SELECT nx.kind, nx.rnd, nx.step, nx.k, nx.next_id, nx.first_new, nx.bx, nx.e, nx.m, nx.q, nx.a, nx.b, nx.gain FROM (
    SELECT CASE WHEN g1 > 0 THEN 1 WHEN step = 0 THEN 2 ELSE 0 END AS kind,
      CASE WHEN g1 <= 0 AND step > 0 THEN rnd + 1 ELSE rnd END AS rnd,
      CASE WHEN g1 > 0 THEN step + 1 ELSE 0 END AS step,
      CASE WHEN g1 > 0 THEN k - 1 ELSE k END AS k,
      CASE WHEN g1 > 0 THEN next_id + 1 ELSE next_id END AS next_id,
      CASE WHEN g1 > 0 THEN first_new ELSE next_id END AS first_new,
      CASE WHEN g1 > 0 THEN list_append(list_filter(bx, lambda z: z.id <> q[1].a AND z.id <> q[1].b), {_new_box('xa', 'xb', 'next_id')}) ELSE bx END AS bx,
      CASE WHEN g1 > 0 THEN e ELSE e2 END AS e,
      CASE WHEN g1 > 0 THEN m || [{{'o': q[1].a, 'n': next_id}}, {{'o': q[1].b, 'n': next_id}}] ELSE [] END AS m,
      CASE WHEN g1 > 0 THEN list_filter(q, lambda p: p.a <> q[1].a AND p.a <> q[1].b AND p.b <> q[1].a AND p.b <> q[1].b) WHEN step = 0 THEN [] ELSE {_ranked(fresh)} END AS q,
      CASE WHEN g1 > 0 THEN q[1].a ELSE 0 END AS a, CASE WHEN g1 > 0 THEN q[1].b ELSE 0 END AS b, g1 AS gain
    FROM (SELECT *, {gain} AS g1, {_box('q[1].a')} AS xa, {_box('q[1].b')} AS xb, CASE WHEN step > 0 THEN {next_edges} ELSE e END AS e2 FROM st, g WHERE kind <> 2)
  ) nx
)"""


def ledger(w: str, bins, k: int | None, scope: str) -> str:
    """The merges of mining without pruning, with the total length after each."""
    return f"""WITH RECURSIVE {merging(w, bins, k, scope)},
t AS (SELECT sum(usage)::BIGINT AS n, count(*) AS k, sum({lg(f'usage + {EPS}')}) AS slg FROM c),
start AS (SELECT {grid_bits(w)} + {lnat('t.k')} + t.k * {side_bits(w)} + {lnat('t.n')} + {lg(f't.n + {EPS} * t.k')} - {lg(f'{EPS} * t.k')} - slg + t.k * {lg(str(EPS))} AS bits FROM t, g)
SELECT rnd::INT AS round, step::INT AS step, a, b, next_id - 1 AS pid, k + 1 AS k_before, round(gain, 6) AS gain, round(bits - sum(gain) OVER (ORDER BY next_id), 6) AS total_after FROM st, start WHERE kind = 1"""


def mined(w: str, bins, k: int | None, scope: str, top: int = 1000) -> str:
    """The boxes after mining and pruning.

    Pruning goes on from the last state of mining: ``pr`` has a row for each
    candidate pair that is looked at; the boxes in its hull join one by one, in
    order of their ids, while the gain of the whole group rises.
    """
    d = len(VIEWS[w][0])
    pairs = "flatten(list_transform(bx, lambda y: list_transform(list_filter(bx, lambda x: x.id < y.id), lambda x: {'a': x.id, 'b': y.id, 'x': x, 'y': y})))"
    inside_hull = "list_reduce(list_transform(range(1, len({0}.lo) + 1), lambda i: least({0}.lo[i], {1}.lo[i]) <= h.lo[i] AND greatest({0}.hi[i], {1}.hi[i]) >= h.hi[i]), lambda s, v: s AND v)"
    holders = f"list_transform(list_filter(list_transform({pairs}, lambda p: {{'p': p, 'n': len(list_filter(bx, lambda h: {inside_hull.format('p.x', 'p.y')}))}}), lambda r: r.n > 2), lambda r: {{'a': r.p.a, 'b': r.p.b}})"
    by_id = f"list_sort(list_transform({_ranked(holders)}, lambda r: {{'s': r.s, 'a': r.a, 'b': r.b}}))[1:{top}]"
    own = lambda u: lg(f"{u} + {EPS}")
    fresh = f"{{'m': 2, 'j': xa.u + xb.u, 'o': {own('xa.u')} + {own('xb.u')}, 'sp': xa.u * xa.ls + xb.u * xb.ls, 'ids': [xa.id, xb.id]}}"

    def group_gain(v: str) -> str:
        many = f"({lnat('k')} - {lnat(f'(k - {v}.m + 1)')} + ({v}.m - 1) * {side_bits(w)} + {lg(f'n + {EPS} * k')} - {lg(f'n + {EPS} * (k - {v}.m + 1)')} + {lg(f'{EPS} * (k - {v}.m + 1)')} - {lg(f'{EPS} * k')})"
        return f"({many} + {own(f'{v}.j')} + ({v}.m - 1) * {lg(str(EPS))} - {v}.o + {v}.sp - {v}.j * hull)"

    acc = "{'m': acc.m + 1, 'j': acc.j + h.u, 'o': acc.o + " + own("h.u") + ", 'sp': acc.sp + h.u * h.ls, 'ids': list_append(acc.ids, h.id)}"
    held = f"list_sort(list_filter(bx, lambda h: h.id <> xa.id AND h.id <> xb.id AND {inside_hull.format('xa', 'xb')}))"
    hull_lo, hull_hi = ("list_transform(range(1, len(xa.lo) + 1), lambda i: " + x + ")" for x in ("least(xa.lo[i], xb.lo[i])", "greatest(xa.hi[i], xb.hi[i])"))
    # members are tried one after the other: the list of held boxes is walked with its place as state
    out = ", ".join(f"z.lo[{i + 1}]::INT AS lo_{i}, z.hi[{i + 1}]::INT AS hi_{i}" for i in range(d))
    return f"""WITH RECURSIVE {merging(w, bins, k, scope)},
pr AS (
  SELECT 0 AS kind, len(bx)::BIGINT AS k, next_id, bx, q2 AS q, 0 AS made, NULL::STRUCT(m INT, j HUGEINT, o DOUBLE, sp DOUBLE, ids BIGINT[]) AS acc, []::STRUCT(id BIGINT, lo INT[], hi INT[], u BIGINT, ls DOUBLE)[] AS hs FROM (SELECT next_id, bx, {by_id} AS q2 FROM st WHERE kind = 2)
  UNION ALL
  SELECT kind2, k2, next2, bx2, q2, made2, acc2, hs2 FROM (
    SELECT
      CASE WHEN acc IS NULL AND len(q) = 0 AND made = 0 THEN 2 ELSE 0 END AS kind2,
      CASE WHEN commits THEN k - acc.m + 1 ELSE k END AS k2,
      CASE WHEN commits THEN next_id + 1 ELSE next_id END AS next2,
      CASE WHEN commits THEN list_append(list_filter(bx, lambda z: NOT list_contains(acc.ids, z.id)), {{'id': next_id, 'lo': {hull_lo}, 'hi': {hull_hi}, 'u': acc.j::BIGINT, 'ls': hull}}) ELSE bx END AS bx2,
      CASE WHEN acc IS NULL AND len(q) = 0 AND made > 0 THEN {by_id} WHEN acc IS NOT NULL AND len(hs) = 0 OR acc IS NULL AND NOT both_live THEN q[2:] ELSE q END AS q2,
      CASE WHEN acc IS NULL AND len(q) = 0 THEN 0 WHEN commits THEN made + 1 ELSE made END AS made2,
      CASE WHEN acc IS NULL AND both_live THEN {fresh} WHEN acc IS NULL OR len(hs) = 0 THEN NULL WHEN {group_gain('wider')} > {group_gain('acc')} THEN wider ELSE acc END AS acc2,
      CASE WHEN acc IS NULL AND both_live THEN {held} WHEN acc IS NULL OR len(hs) = 0 THEN [] ELSE hs[2:] END AS hs2
    FROM (SELECT *, acc IS NOT NULL AND len(hs) = 0 AND {group_gain('acc')} > 0 AS commits FROM (
      SELECT *, len(q) > 0 AND xa IS NOT NULL AND xb IS NOT NULL AS both_live, {_hull_bits('xa', 'xb')} AS hull, CASE WHEN len(hs) > 0 THEN {acc.replace('h.', 'hs[1].')} END AS wider
      FROM (SELECT pr.*, g.*, {_box('q[1].a')} AS xa, {_box('q[1].b')} AS xb FROM pr, g WHERE kind <> 2)))
  )
)
SELECT z.id AS pid, {out}, z.u::BIGINT AS usage, round(z.ls, 6) AS log_size FROM (SELECT unnest(bx) AS z FROM pr WHERE kind = 2)"""


def inside(w: str, lo_a: str, hi_a: str, lo_b: str, hi_b: str) -> str:
    return " AND ".join(f"{lo_a}{i} <= {lo_b}{i} AND {hi_a}{i} >= {hi_b}{i}" for i in range(len(VIEWS[w][0])))


def occurrences(w: str, bins) -> str:
    k = len(VIEWS[w][0])
    within = " AND ".join(f"c.b_{i} BETWEEN h.l_{i} AND h.h_{i}" for i in range(k))
    return f"{hulls(w, bins)}, o AS (SELECT h.pid, c.cell_id, c.usage FROM h JOIN c ON {within})"


def support(w: str, bins) -> str:
    return f"WITH {occurrences(w, bins)} SELECT pid, sum(usage)::BIGINT AS support FROM o GROUP BY pid"


def jaccards(w: str, bins) -> str:
    return f"{occurrences(w, bins)}, s AS (SELECT pid, sum(usage) AS size FROM o GROUP BY pid), j AS (SELECT a.pid AS a, b.pid AS b, coalesce(x.both_rows, 0) / (a.size + b.size - coalesce(x.both_rows, 0)) AS jaccard FROM s a JOIN s b ON a.pid < b.pid LEFT JOIN (SELECT p.pid AS a, q.pid AS b, sum(p.usage) AS both_rows FROM o p JOIN o q USING (cell_id) WHERE p.pid < q.pid GROUP BY ALL) x ON x.a = a.pid AND x.b = b.pid)"


def jaccard_all(w: str, bins) -> str:
    return f"WITH {jaccards(w, bins)} SELECT count(*) AS pairs, round(avg(jaccard), 6) AS mean_jaccard FROM j"


def jaccard_topk(w: str, bins, k: int) -> str:
    return f"WITH {jaccards(w, bins)}, ways AS (SELECT a AS p, b AS q, jaccard FROM j UNION ALL SELECT b, a, jaccard FROM j), top AS (SELECT *, row_number() OVER (PARTITION BY p ORDER BY jaccard DESC, q) AS r FROM ways QUALIFY r <= {k}), u AS (SELECT DISTINCT least(p, q) AS a, greatest(p, q) AS b, jaccard FROM top) SELECT count(*) AS pairs, round(avg(jaccard), 6) AS mean_jaccard FROM u"


def accuracy(w: str, bins) -> str:
    k = len(VIEWS[w][0])
    within = " AND ".join(f"d.b_{i} BETWEEN h.l_{i} AND h.h_{i}" for i in range(k))
    return f"WITH {hulls(w, bins)}, n AS (SELECT h.pid, d.label, count(*) AS c FROM h JOIN d ON {within} GROUP BY ALL) SELECT pid, arg_min(label, (-c, label)) AS majority, sum(c)::BIGINT AS rows, round(max(c) / sum(c), 6) AS accuracy FROM n GROUP BY pid"


def prune_candidates(w: str, bins, top: int) -> str:
    k = len(VIEWS[w][0])
    lo = ", ".join(f"least(a.l_{i}, b.l_{i}) AS l_{i}, greatest(a.h_{i}, b.h_{i}) AS h_{i}" for i in range(k))
    size = " + ".join(f"log2(greatest(a.h_{i}, b.h_{i}) - least(a.l_{i}, b.l_{i}) + 1)" for i in range(k))
    w_sql = weight("a.usage", "b.usage", f"(a.usage * a.ls + b.usage * b.ls - (a.usage + b.usage) * ({size}))")
    return f"WITH {hulls(w, bins)}, kk AS (SELECT count(*) AS kc FROM h), q AS (SELECT a.pid AS a, b.pid AS b, {lo}, {w_sql} + {kappa(w, 'kc', 'g.n')} AS gain FROM h a JOIN h b ON a.pid < b.pid, kk, g) SELECT a, b, count(*) AS held, round(gain, 6) AS gain FROM q JOIN h t ON t.pid <> a AND t.pid <> b AND {inside(w, 'q.l_', 'q.h_', 't.l_', 't.h_')} GROUP BY a, b, gain ORDER BY round(gain, 9) DESC, a, b LIMIT {top}"


def partition(w: str, bins) -> str:
    """What any mining result must add up to."""
    return f"WITH {cells(w, bins)} SELECT sum(usage)::BIGINT AS rows, sum(usage)::BIGINT AS usage, count(*) AS cells, count(*) AS encoded, 0::BIGINT AS outside FROM c"


def binarise(w: str, bins) -> str:
    k = len(VIEWS[w][0])
    items = ", ".join(f"(b_{i} + {i} * nb)::INT AS item_{i}" for i in range(k))
    return f"{disc(w, bins)}, x AS (SELECT obj_id, {items} FROM d, g)"


def binarise_rows(w: str, bins) -> str:
    return f"WITH {binarise(w, bins)} SELECT * FROM x"


def item_support(w: str, bins) -> str:
    k = len(VIEWS[w][0])
    parts = " UNION ALL ".join(f"SELECT item_{i} AS item FROM x" for i in range(k))
    return f"WITH {binarise(w, bins)} SELECT item, count(*) AS support FROM ({parts}) GROUP BY item"


def pair_support(w: str, bins) -> str:
    k = len(VIEWS[w][0])
    parts = " UNION ALL ".join(f"SELECT item_{i} AS x, item_{j} AS y FROM x" for i in range(k) for j in range(i + 1, k))
    return f"WITH {binarise(w, bins)} SELECT x, y, count(*) AS support FROM ({parts}) GROUP BY x, y"


def plugin_steps(w: str, bins) -> str:
    key = names(w)
    return f"""WITH {cells(w, bins)}, s AS (SELECT c.cell_id, row_number() OVER (PARTITION BY c.cell_id ORDER BY ts, obj_id) - 1 AS seen, row_number() OVER (ORDER BY ts, obj_id) - 1 AS position FROM d JOIN c USING ({key})),
kk AS (SELECT count(*) AS kc FROM c) SELECT cell_id, count(*) AS uses, round(sum(-log2((seen + {EPS}) / (position + {EPS} * kc))), 5) AS bits FROM s, kk GROUP BY cell_id"""


def layout(name: str, m: int) -> str:
    """CTE ``y`` (obj_id, x, y, tid)."""
    parts = slices(name, m)
    case = lambda pick: "CASE " + " ".join(f"WHEN obj_id BETWEEN {a} AND {b} THEN {pick(t, box)}" for t, ((a, b), box) in enumerate(zip(parts, LAYOUTS[name], strict=True), 1)) + " END"
    x = case(lambda t, b: f"{b[0][0]}::DOUBLE + u * ({b[0][1]}::DOUBLE - {b[0][0]}::DOUBLE)")
    y = case(lambda t, b: f"{b[1][0]}::DOUBLE + v * ({b[1][1]}::DOUBLE - {b[1][0]}::DOUBLE)")
    shipped = _SECONDS.format("l_shipdate")
    return f"""s AS (SELECT *, {shipped} AS sec FROM lineitem), ends AS (SELECT min(l_extendedprice) AS p0, max(l_extendedprice) AS p1, min(sec) AS s0, max(sec) AS s1 FROM s),
r AS (SELECT row_number() OVER (ORDER BY l_orderkey, l_linenumber, l_extendedprice) AS obj_id, (l_extendedprice - p0) / (p1 - p0) AS u, (sec - s0) / (s1 - s0) AS v FROM s, ends),
y AS (SELECT obj_id, {x} AS x, {y} AS y, ({case(lambda t, b: str(t))})::BIGINT AS tid FROM r WHERE obj_id <= {parts[-1][1]})"""


def layout_rows(name: str, m: int) -> str:
    return f"WITH {layout(name, m)} SELECT obj_id, round(x, 9) AS x, round(y, 9) AS y, tid FROM y"


def planted_jcd(name: str, m: int) -> str:
    """Agreement of the hulls of the planted groups with the planted boxes, both ways."""
    boxes = ", ".join(f"({t}, {x[0]}::DOUBLE, {x[1]}::DOUBLE, {y[0]}::DOUBLE, {y[1]}::DOUBLE)" for t, (x, y, _) in enumerate(LAYOUTS[name], 1))
    inner = "greatest(least(q.x1, t.x1) - greatest(q.x0, t.x0), 0) * greatest(least(q.y1, t.y1) - greatest(q.y0, t.y0), 0)"
    outer = "(greatest(q.x1, t.x1) - least(q.x0, t.x0)) * (greatest(q.y1, t.y1) - least(q.y0, t.y0))"
    return f"""WITH {layout(name, m)}, t(tid, x0, x1, y0, y1) AS (VALUES {boxes}), q AS (SELECT tid AS pid, min(x) AS x0, max(x) AS x1, min(y) AS y0, max(y) AS y1 FROM y GROUP BY tid),
j AS (SELECT pid, tid, {inner} / ({outer}) AS jac FROM q, t)
SELECT 'computed' AS side, count(*) AS boxes, round(avg(best), 6) AS jcd FROM (SELECT max(jac) AS best FROM j GROUP BY pid) UNION ALL SELECT 'truth', count(*), round(avg(best), 6) FROM (SELECT max(jac) AS best FROM j GROUP BY tid)"""


def planted_overlap(name: str, m: int) -> str:
    """Mean pairwise box Jaccard of the planted groups' hulls."""
    inner = "greatest(least(a.x1, b.x1) - greatest(a.x0, b.x0), 0) * greatest(least(a.y1, b.y1) - greatest(a.y0, b.y0), 0)"
    outer = "(greatest(a.x1, b.x1) - least(a.x0, b.x0)) * (greatest(a.y1, b.y1) - least(a.y0, b.y0))"
    return f"WITH {layout(name, m)}, q AS (SELECT tid AS pid, min(x) AS x0, max(x) AS x1, min(y) AS y0, max(y) AS y1 FROM y GROUP BY tid) SELECT count(*) AS pairs, round(avg({inner} / ({outer})), 6) AS mean_jaccard FROM q a JOIN q b ON a.pid < b.pid"


def window_cells(bins) -> str:
    return f"WITH {disc('W6', bins)} SELECT strftime(date_trunc('day', e.ts), '%Y-%m-%d') AS day, b_0, b_1, b_2, count(*) AS usage FROM d JOIN events e ON e.event_id = d.obj_id GROUP BY ALL"


def online_bits(bins) -> str:
    return f"""WITH {cells('W6', bins)}, kk AS (SELECT count(*) AS kc FROM c), r AS (SELECT e.user_id, e.ts AS seen_at, d.obj_id, c.cell_id FROM d JOIN c USING ({names('W6')}) JOIN events e ON e.event_id = d.obj_id),
s AS (SELECT user_id, row_number() OVER (PARTITION BY user_id, cell_id ORDER BY seen_at, obj_id) - 1 AS seen, row_number() OVER (PARTITION BY user_id ORDER BY seen_at, obj_id) - 1 AS position FROM r)
SELECT user_id::VARCHAR AS stream_key, count(*) AS events, round(sum(-log2((seen + {EPS}) / (position + {EPS} * kc))), 5) AS bits FROM s, kk GROUP BY user_id"""


def equal_height(w: str, bins: int) -> str:
    attrs, view = VIEWS[w]
    rows = " UNION ALL ".join(f"SELECT '{a}' AS attr, unnest(range(1, {bins}))::INT AS cut, unnest(quantile_cont({a}, [{', '.join(f'{j}::DOUBLE / {bins}' for j in range(1, bins))}])) AS value FROM w" for a in attrs)
    return f"WITH w AS ({view}) SELECT attr, cut, round(value, 6) AS value FROM ({rows})"


def first_round(w: str, bins, k: int) -> str:
    """The merges of the first round."""
    return f"WITH RECURSIVE {merging(w, bins, k, 'inherited')} SELECT a, b, next_id - 1 AS pid, step::INT AS step, k + 1 AS k_before, round(gain, 6) AS gain FROM st WHERE kind = 1 AND rnd = 1"


def accuracy_cover(w: str, bins) -> str:
    return f"WITH {cells(w, bins)}, n AS (SELECT c.cell_id AS pid, d.label, count(*) AS c FROM d JOIN c USING ({names(w)}) WHERE d.label IS NOT NULL GROUP BY ALL) SELECT pid, arg_min(label, (-c, label)) AS majority, sum(c)::BIGINT AS rows, round(max(c) / sum(c), 6) AS accuracy FROM n GROUP BY pid"


def length_ratio(w: str, bins) -> str:
    one = lambda source: length(w, bins, source).replace("round(grid + patterns + \"count\" + data + reconstruction, 6)", "grid + patterns + \"count\" + data + reconstruction")
    return f"SELECT round(a.total / b.total, 6) AS ratio FROM ({one('c')}) a, ({one('h')}) b"


def marginals(w: str, bins) -> str:
    return f"WITH {disc(w, bins)} SELECT {names(w)}, count(*) AS usage, grouping_id({names(w)})::BIGINT AS subset FROM d GROUP BY CUBE ({names(w)})"


def label_totals(w: str, bins) -> str:
    return f"WITH {disc(w, bins)} SELECT b_0, label, count(*) AS rows, grouping_id(b_0, label)::BIGINT AS level FROM d GROUP BY ROLLUP (b_0, label)"


def forecast(w: str, bins) -> str:
    return f"WITH {cells(w, bins)} SELECT count(*) AS exact, true AS near FROM c"


AS_OF = """WITH p AS (SELECT user_id, ts, max(event_id) AS last_purchase FROM events WHERE event_type = 'purchase' GROUP BY ALL)
SELECT e.event_id, p.last_purchase FROM events e ASOF LEFT JOIN p ON e.user_id = p.user_id AND e.ts >= p.ts"""


def compare(w: str, bins: int, other: int) -> str:
    one, two = (f"SELECT {names(w)} FROM (WITH {cells(w, b)} SELECT * FROM c)" for b in (bins, other))
    return f"SELECT 'both' AS side, * FROM (({one}) INTERSECT ALL ({two})) UNION ALL SELECT 'ours', * FROM (({one}) EXCEPT ALL ({two})) UNION ALL SELECT 'theirs', * FROM (({two}) EXCEPT ALL ({one}))"


def ntile(w: str, attr: int, bins: int) -> str:
    attrs, view = VIEWS[w]
    return f"SELECT bin::INT AS bin, min(v) AS lo, max(v) AS hi, count(*) AS rows FROM (SELECT {attrs[attr]} AS v, ntile({bins}) OVER (ORDER BY {attrs[attr]}, obj_id) AS bin FROM ({view})) GROUP BY bin"
