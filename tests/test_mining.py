"""The worked example, agreement with an independent miner, invariants, edge cases."""

import math
import random

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from boxmdl.functions import codes
from boxmdl.operators import cells, grid, intasks, kernel, matching, measures, miner, model, neighbors, prune
from boxmdl.plans import choose
from boxmdl.sources import workloads as W
from tests import reference_miner as R

SF = "/root/testdata/sf0.001"
POINTS = [(0.30, 0.15), (0.05, 3.90), (0.20, 4.35), (4.40, 0.00), (4.30, 3.70), (4.10, 3.90), (4.25, 6.60), (7.10, 4.15), (6.70, 6.50), (6.90, 7.40), (7.45, 6.75), (7.10, 7.35)]


@pytest.fixture(scope="module")
def example(spark):
    return spark.createDataFrame(POINTS, "m1 double, m2 double").cache()


def trace(found):
    return [(r.a, r.b, round(r.gain, 3)) for r in found.ledger.orderBy("round", "step").collect()]


def test_example_cells(spark, example):
    g = grid.equal_width(example, ["m1", "m2"], 8)
    got = [(r.cell_id, tuple(r.lo), r.usage) for r in cells.elementary(cells.discretise(example, g)).orderBy("cell_id").collect()]
    assert got == [(1, (0, 0), 1), (2, (0, 4), 2), (3, (4, 0), 1), (4, (4, 4), 2), (5, (4, 7), 1), (6, (7, 4), 1), (7, (7, 7), 4)]
    near = neighbors.knn(cells.elementary(cells.discretise(example, g)), 1, 2)
    assert {r.cell_id: r.neighbor for r in near.collect()} == {1: 2, 2: 1, 3: 1, 4: 5, 5: 4, 6: 4, 7: 5}
    assert sorted((r.a, r.b) for r in neighbors.edges(near).collect()) == [(1, 2), (1, 3), (4, 5), (4, 6), (5, 7)]


@pytest.mark.parametrize(
    ("eps", "start", "merges", "end"),
    [
        (0.5, 141.3178, [(1, 3, 8.951), (4, 6, 8.580), (5, 7, 5.808), (9, 10, 3.940), (2, 8, 3.213)], 110.8252),
        (1.0, 139.0806, [(1, 3, 8.743), (4, 6, 8.281), (5, 7, 5.480), (9, 10, 3.220), (2, 8, 3.050)], 110.3067),
    ],
)
def test_example_merges(example, eps, start, merges, end):
    # a new box inherits the neighbours of its parts, and of equal gains the later pair goes first
    found = miner.mine(example, ["m1", "m2"], 8, k=1, eps=eps, candidate_scope="inherited", tie="last", prune_when="never")
    assert found.report["start_bits"] == pytest.approx(start, abs=1e-4) and found.report["end_bits"] == pytest.approx(end, abs=1e-4)
    assert trace(found) == merges
    assert sorted((r.lo, r.hi, r.usage) for r in found.boxes.collect()) == [([0, 0], [4, 4], 4), ([4, 4], [7, 7], 8)]
    assert sorted(r.support for r in measures.support(found.boxes, found.cells).collect()) == [6, 8]
    assert measures.jaccard_all(found.boxes, found.cells).first().mean_jaccard == pytest.approx(2 / 12)


@pytest.mark.parametrize(("eps", "tie", "boxes", "end"), [(0.5, "first", [([0, 0], [7, 7])], 107.7397), (0.5, "last", [([0, 0], [7, 7])], 107.7397), (1.0, "first", [([0, 0], [7, 7]), ([7, 7], [7, 7])], 107.7312), (1.0, "last", [([0, 0], [7, 4]), ([4, 7], [7, 7])], 107.6628)])
def test_example_every_pattern_as_partner(example, eps, tie, boxes, end):
    found = miner.mine(example, ["m1", "m2"], 8, k=1, eps=eps, candidate_scope="all", tie=tie, prune_when="never")
    assert sorted((r.lo, r.hi) for r in found.boxes.collect()) == boxes and found.report["end_bits"] == pytest.approx(end, abs=1e-4)


def test_example_length_parts(example):
    found = miner.mine(example, ["m1", "m2"], 8, k=1, candidate_scope="inherited", tie="last", prune_when="never")
    parts = found.report["parts"]
    assert parts["grid"] + parts["patterns"] == pytest.approx(39.2528, abs=1e-4)
    assert (parts["count"], parts["data"], parts["reconstruction"]) == pytest.approx((7.8267, 13.1703, 50.5754), abs=1e-4)


def test_codes(spark):
    assert [round(codes.universal_int_bits(n), 4) for n in (1, 2, 8, 12)] == [1.5186, 2.5186, 6.7680, 7.8267]
    xs = [e + u for e in (0.01, 0.5, 1.0) for u in (*range(0, 300, 7), 10**6, 10**9, 10**12)]
    got = spark.createDataFrame([(x,) for x in xs], "x double").select("x", codes.lgamma_bits_col(F.col("x")).alias("g")).collect()
    assert all(r.g == pytest.approx(codes.lgamma_bits(r.x), rel=2e-13, abs=2e-13) for r in got)
    usages = [3, 0, 5, 1]
    seq = [i for i, u in enumerate(usages) for _ in range(u)]
    for seed in range(3):
        random.Random(seed).shuffle(seq)
        rows = spark.createDataFrame(list(enumerate(seq)), "t long, p long")
        total = codes.plugin_step_bits(rows, "p", ["t"], 4).agg(F.sum("bits")).first()[0]
        assert total == pytest.approx(codes.plugin_sequence_bits(usages))
    for x, step in ((3.0, 0.5), (1e6, 0.5), (1e12, 2.0)):
        assert codes.lgamma_step_bits(x, step) == pytest.approx(step * math.log2(x), rel=0.2)
    assert codes.shannon_bits([2, 2]) == 4 and codes.uniform_bits(8, 4) == 16 and codes.shannon_bits([5]) == 0


def random_cells(seed, n, bins):
    rng = random.Random(seed)
    spots = sorted({tuple(rng.randrange(b) for b in bins) for _ in range(n)})
    return [(s, rng.choice([1, 1, 2, 5, 30])) for s in spots]


def kernel_run(found, bins, k, **options):
    g = grid.Grid(tuple(grid.Axis(f"a{i}", b, 0.0, 1.0) for i, b in enumerate(bins)))
    spots = np.array([c for c, _ in found])
    p = kernel.Patterns.of(np.arange(1, len(found) + 1), spots, spots, np.array([u for _, u in found]))
    return g, p, kernel.mine(p, kernel.packed(*neighbors.knn_local(spots, k).T) if k else None, g, **options)


@pytest.mark.parametrize("seed", range(12))
@pytest.mark.parametrize("scope", ["inherited", "all"])
@pytest.mark.parametrize("tie", ["first", "last", "hash"])
def test_kernel_agrees_with_plain_miner(seed, scope, tie):
    bins = (6, 5) if seed % 2 else (4, 4, 3)
    found = random_cells(seed, 22, bins)
    live, merges = R.mine(found, bins, 3, scope=scope, tie=tie)
    g, p, run = kernel_run(found, bins, 3, scope=scope, tie=tie)
    assert [(a, b, pid) for _, _, a, b, pid, *_ in run.ledger] == [m[:3] for m in merges]
    assert [x[6] for x in run.ledger] == pytest.approx([m[3] for m in merges])
    at = p.live()
    assert {int(p.ids[r]): (tuple(p.lo[r]), tuple(p.hi[r]), int(p.usage[r])) for r in at} == live
    if run.ledger:
        assert run.ledger[-1][7] == pytest.approx(R.length(list(live.values()), bins, 0.5))


@pytest.mark.parametrize("seed", range(10))
def test_never_better_than_the_optimum(seed):
    found = random_cells(seed + 100, 6, (5, 5))
    g, p, run = kernel_run(found, (5, 5), None, scope="all")
    kernel.prune(p, run, g)
    at = p.live()
    assert model.total_bits_local(p.usage[at], p.log_size[at], g) >= R.optimum(found, (5, 5)) - 1e-9


@pytest.mark.parametrize("seed", range(6))
def test_pruning_only_shortens(seed):
    found = random_cells(seed + 50, 40, (9, 9))
    g, p, run = kernel_run(found, (9, 9), 2)
    before = model.total_bits_local(p.usage[p.live()], p.log_size[p.live()], g)
    rows = p.usage[p.live()].sum()
    merges = kernel.prune(p, run, g)
    after = model.total_bits_local(p.usage[p.live()], p.log_size[p.live()], g)
    assert (after < before) == bool(merges) and p.usage[p.live()].sum() == rows


def test_pruning_merges_three_where_no_pair_pays():
    g = grid.Grid((grid.Axis("x", 8, 0.0, 1.0), grid.Axis("y", 8, 0.0, 1.0)))
    lo, hi = np.array([[3, 0], [2, 3], [2, 0]]), np.array([[5, 3], [3, 3], [4, 0]])
    p = kernel.Patterns.of(np.arange(1, 4), lo, hi, np.array([37, 22, 37]))
    pairs = np.array([[0, 1], [0, 2], [1, 2]])
    assert (kernel.weights(p, *pairs.T, 0.5, "plugin") + model.kappa(3, 96, g)).max() <= 0
    run = kernel.mine(p, None, g, scope="all")
    assert not run.ledger
    before = model.total_bits_local(p.usage[p.live()], p.log_size[p.live()], g)
    assert kernel.prune(p, run, g) == 1 and len(p.live()) == 1
    assert model.total_bits_local(p.usage[p.live()], p.log_size[p.live()], g) < before


def test_group_gain_is_the_difference_of_totals():
    rng = np.random.default_rng(3)
    g = grid.Grid((grid.Axis("x", 9, 0.0, 1.0), grid.Axis("y", 12, 0.0, 1.0)))
    for eps, encoding in ((0.5, "plugin"), (0.1, "plugin"), (0.5, "shannon")):
        for _ in range(100):
            k = int(rng.integers(3, 9))
            lo = rng.integers(0, 8, (k, 2))
            p = kernel.Patterns.of(np.arange(k), lo, lo + rng.integers(0, 2, (k, 2)), rng.integers(1, 50, k))
            m = int(rng.integers(2, k))
            hull = float(np.log2(p.hi[:m].max(axis=0) - p.lo[:m].min(axis=0) + 1.0).sum())
            before = model.total_bits_local(p.usage[:k], p.log_size[:k], g, eps, encoding)
            after = model.total_bits_local(np.append(p.usage[m:k], p.usage[:m].sum()), np.append(p.log_size[m:k], hull), g, eps, encoding)
            assert model.group_gain(p.usage[:m], p.log_size[:m], hull, k, int(p.usage[:k].sum()), g, eps, encoding) == pytest.approx(before - after, abs=1e-8)


@pytest.mark.parametrize(
    ("scope", "options"),
    [("inherited", {"tie": "first"}), ("all", {"tie": "last", "requeue": True}), ("inherited", {"gain_mode": "stored"}), ("inherited", {"requeue": True, "prune_when": "final"}), ("inherited", {"encoding": "shannon"})],
)
def test_distributed_rounds_agree_with_the_kernel(spark, monkeypatch, scope, options):
    df = W.load(spark, SF, "W6")
    run = lambda: miner.mine(df, W.attrs("W6"), 4, k=3, candidate_scope=scope, **({"prune_when": "never"} | options))
    local = run()
    monkeypatch.setattr(choose, *(("LOCAL_CANDIDATES", 40) if "requeue" in options else ("LOCAL_PATTERNS", 15)))
    spread = run()
    boxes = lambda r: sorted((x.pid, tuple(x.lo), tuple(x.hi), x.usage) for x in r.boxes.collect())
    assert boxes(local) == boxes(spread) and local.report["explored"] == spread.report["explored"]
    assert sorted(map(tuple, local.lineage.collect())) == sorted(map(tuple, spread.lineage.collect()))
    ledger = lambda r: [(x.a, x.b, x.pid, round(x.total_after, 6)) for x in r.ledger.orderBy("pid").collect()]
    assert ledger(local) == ledger(spread)


@pytest.mark.parametrize("workload", ["W6", "W7", "W4"])
def test_tiles_find_the_same_neighbours(spark, monkeypatch, workload):
    df = W.load(spark, SF, workload)
    g = grid.equal_width(df, W.attrs(workload), 12)
    c = cells.elementary(cells.discretise(df, g)).cache()
    rows = lambda m, **o: sorted(map(tuple, neighbors.knn(c, 4, len(g.axes), m, **o).collect()))
    exact = rows("broadcast")
    assert exact == rows("tiled", tile=1) == rows("tiled", tile=3) == rows("tiled")
    points = np.array([r.lo for r in c.orderBy("cell_id").collect()])
    assert {(a + 1, b + 1) for a, b in neighbors.knn_local(points, 4).tolist()} == {(r[0], r[1]) for r in exact}
    near = neighbors.knn(c, 4, len(g.axes), "projected")
    assert neighbors.recall(near, neighbors.knn(c, 4, len(g.axes), "broadcast")).first().recall > 0.9
    monkeypatch.setattr(choose, "NEIGHBOR_BLOCK_BYTES", 8 * (len(g.axes) + 1) * 40)  # blocks of 40 cells
    assert exact == rows("tiled") == rows("tiled", tile=2)


@pytest.mark.parametrize("seed", range(8))
def test_tiles_by_brute_force(seed):
    rng = np.random.default_rng(seed)
    n, d, b, k = [(300, 2, 12, 4), (500, 3, 8, 7), (400, 4, 5, 3), (50, 1, 60, 5), (200, 6, 3, 5), (30, 2, 100, 29), (30, 2, 100, 40), (900, 2, 200, 60)][seed]
    points = np.unique(rng.integers(0, b, (n, d)), axis=0)
    ids = np.cumsum(rng.integers(1, 4, len(points)))
    row, near, d2 = neighbors.Tiles(ids, points, k).nearest(ids, points)
    every = ((points[:, None] - points[None]) ** 2).sum(axis=-1)
    for i in range(len(points)):
        want = sorted((int(every[i, j]), int(ids[j])) for j in range(len(points)) if j != i)[:k]
        assert sorted(zip(d2[row == i].tolist(), near[row == i].tolist())) == want


def test_matching_rounds_do_not_follow_ties():
    """10 000 cells of equal usage on a lattice, with their four neighbours."""
    at = np.arange(10_000).reshape(100, 100)
    a, b = np.concatenate([at[:, :-1].ravel(), at[:-1].ravel()]), np.concatenate([at[:, 1:].ravel(), at[1:].ravel()])
    order = np.argsort(kernel.pair_mix(a, b), kind="stable")
    rounds = []
    a, b = a[order], b[order]
    rest, alive = np.arange(len(a)), np.ones(10_000, bool)
    taken = kernel.greedy_matching(a, b, 10_000)
    slow = []
    for i in range(len(a)):
        if alive[a[i]] and alive[b[i]]:
            slow.append(i)
            alive[a[i]] = alive[b[i]] = False
    assert taken.tolist() == slow
    best = np.empty(10_000, np.int64)
    while len(rest):
        best[np.stack([a[rest], b[rest]], axis=1)[::-1].ravel()] = np.repeat(rest[::-1], 2)
        won = rest[(best[a[rest]] == rest) & (best[b[rest]] == rest)]
        gone = np.zeros(10_000, bool)
        gone[a[won]] = gone[b[won]] = True
        rest = rest[~(gone[a[rest]] | gone[b[rest]])]
        rounds.append(len(won))
    assert len(rounds) < 30


@pytest.mark.parametrize("limit", [0, 1])
def test_pruning_by_tasks_is_pruning_here(spark, monkeypatch, limit):
    g, p, run = kernel_run(random_cells(5, 120, (12, 12)), (12, 12), 1)
    boxes = miner._boxes_frame(spark, p, p.live())
    here, moved = prune.prune(boxes, g, top_n=50)
    monkeypatch.setattr(choose, "PRUNE_LOCAL", limit)
    there, again = prune.prune(boxes, g, top_n=50)
    assert sorted(map(tuple, moved.collect())) == sorted(map(tuple, again.collect()))
    assert sorted(map(str, here.collect())) == sorted(map(str, there.collect()))


def test_pairs_below_the_bound_never_gain():
    g = grid.Grid((grid.Axis("x", 31, 0.0, 1.0), grid.Axis("y", 7, 0.0, 1.0)))
    for n, k in ((10, 2), (100, 3), (5000, 40), (10**6, 3000)):
        for eps, encoding in ((0.5, "plugin"), (0.01, "plugin"), (3.0, "plugin"), (0.5, "shannon")):
            bound = model.hope(k, n, g, eps, encoding)
            assert all(model.kappa(x, n, g, eps, 1, encoding) <= bound for x in range(max(2, k - k // 2), k + 1))
            ks = np.arange(2, k + 1)
            assert model.kappa_np(ks, n, g, eps, encoding) == pytest.approx([model.kappa(int(x), n, g, eps, 1, encoding) for x in ks], abs=1e-7)


@pytest.mark.parametrize("options", [{}, {"candidate_scope": "all"}, {"prune_when": "each_round"}, {"requeue": True}, {"eps": 0.1}, {"encoding": "shannon"}, {"k": None, "n_bins": 3}])
def test_invariants(spark, options):
    df = W.load(spark, SF, "W7")
    found = miner.mine(df, W.attrs("W7"), **({"n_bins": 5, "k": 5} | options))
    check = measures.cover_is_partition(found.boxes, found.lineage, found.cells).first()
    assert check.rows == check.usage == found.report["n"] and check.cells == check.encoded and check.outside == 0
    totals = [r.total_after for r in found.ledger.orderBy("pid").collect()]
    assert totals == sorted(totals, reverse=True) and totals[-1] == pytest.approx(found.report["end_bits"])
    hulls = found.cells.join(found.lineage, "cell_id").groupBy("pid").agg(*[f(F.element_at("lo", i + 1)).alias(f"{p}{i}") for i in range(4) for p, f in (("l", F.min), ("h", F.max))])
    for r in hulls.join(found.boxes, "pid").collect():
        assert [r[f"l{i}"] for i in range(4)] == r.lo and [r[f"h{i}"] for i in range(4)] == r.hi
    bounds = measures.candidate_bounds(found.report)
    assert bounds["most_in_round"] <= bounds["round_bound"] and bounds["all"] <= bounds["bound"]


def test_order_of_rows_does_not_matter(spark):
    df = W.load(spark, SF, "W9")
    get = lambda d: sorted((tuple(r.lo), tuple(r.hi), r.usage) for r in miner.mine(d, W.attrs("W9"), 8, k=4).boxes.collect())
    assert get(df) == get(df.orderBy(F.rand(3)).repartition(7))
    assert get(df) == get(df.withColumn("n_chars", F.col("n_chars") * 4))


def test_planted_boxes_are_found_on_the_fine_grid(spark):
    for name, coarse, fine in (("Y1", 0.4, 0.85), ("Y5", 0.4, 0.95)):
        df, known = W.layout(spark, SF, name, 1000), W.truth(spark, name)
        scores = []
        for b, k in ((5, 5), ("sqrt", 60)):
            found = miner.mine(df, ["x", "y"], b, k=k, tie="first")
            real = cells.to_real(found.boxes, found.grid)
            scores.append((measures.jcd(real, known).first().jcd, measures.jcd(known, real, "tid", "pid").first().jcd))
        assert scores[1][0] > scores[0][0] and scores[1][1] > scores[0][1] and scores[1][0] > fine and scores[0][0] < coarse


def test_edge_inputs(spark, tmp_path):
    make = lambda rows: spark.createDataFrame(rows, "x double, y double")
    with pytest.raises(ValueError):
        miner.mine(make([]), ["x", "y"], 5)
    for rows in ([(1.0, 2.0)], [(1.0, 2.0)] * 9):
        one = miner.mine(make(rows), ["x", "y"], 5, k=3)
        assert one.report["patterns"] == 1 and one.report["candidates"] == 0 and one.boxes.first().usage == len(rows)
    constant = miner.mine(make([(float(i), 7.0) for i in range(20)]), ["x", "y"], 4, k=2)
    assert all(r.lo[1] == r.hi[1] == 0 for r in constant.boxes.collect())
    lattice = miner.mine(make([(float(i), float(j)) for i in range(4) for j in range(4)]), ["x", "y"], 4, k=2)
    assert measures.cover_is_partition(lattice.boxes, lattice.lineage, lattice.cells).first().outside == 0
    edges = make([(0.0, 0.0), (1.0, 1.0), (2.0, 2.0), (4.0, 4.0)])
    g = grid.equal_width(edges, ["x", "y"], 4)
    assert [r.b_0 for r in cells.discretise(edges, g).collect()] == [0, 1, 2, 3]
    bad = make([(1.0, None), (float("nan"), 1.0), (float("inf"), 1.0), (1.0, 1.0)])
    with pytest.raises(ValueError):
        miner.mine(bad, ["x", "y"], 5)
    assert miner.mine(bad, ["x", "y"], 5, on_missing="drop").report["n"] == 1
    with pytest.raises(ValueError):
        neighbors.every_pair(lattice.cells, 10**6)
    assert grid.bins_of("sqrt", ["a"], 9_000_000) == [3000]
    lattice.save(str(tmp_path / "r"))
    again = miner.MineResult.load(spark, str(tmp_path / "r"))
    assert again.report["patterns"] == lattice.report["patterns"] and again.grid.attrs == ["x", "y"] and again.boxes.count() == lattice.boxes.count()
    assigned = again.assign(make([(0.0, 0.0), (3.0, 3.0), (99.0, -5.0)])).collect()
    assert [r.pid is None for r in assigned] == [False, False, False]


def test_grids(spark):
    df = W.load(spark, SF, "W6").cache()
    g = grid.equal_height(df, ["value"], 4, exact=True)
    counts = [r.usage for r in cells.counts(cells.discretise(df, g)).collect()]
    assert len(counts) == 4 and max(counts) - min(counts) <= 2
    assert grid.from_frame(grid.to_frame(spark, g)) == grid.Grid(g.axes)
    assert grid.bins_of({"a": 3, "b": "sqrt"}, ["a", "b"], 100) == [3, 10] and grid.bins_of([2, 4], ["a", "b"], 9) == [2, 4]
    mdl = grid.mdl_1d(spark.createDataFrame([(float(x),) for x in [*np.linspace(0, 1, 300), *np.linspace(9, 10, 300)]], "v double"), ["v"])
    assert mdl.axes[0].n_bins in (2, 3, 4) and any(0.9 < c < 9.1 for c in mdl.axes[0].cuts)
    rng = np.random.default_rng(0)
    x = rng.random(2000)
    both = spark.createDataFrame([(float(a), float(a > 0.5) * 5 + float(b)) for a, b in zip(x, rng.random(2000))], "x double, y double")
    ipd = grid.interaction_preserving(both, ["x", "y"], 20)
    assert any(abs(c - 0.5) < 0.06 for c in ipd.axes[0].cuts) and ipd.axes[0].n_bins < 20
    assert grid.residual_bits(df, grid.equal_width(df, ["value"], 4), 1.0) >= 0
    from boxmdl.operators import boxes

    g2 = grid.equal_width(df, ["value", "ts"], 3)
    assert df.filter(boxes.contains_point(g2, [0, 0], [2, 2])).count() == df.count() == df.filter(boxes.to_predicate(g2, [0, 0], [2, 2])).count()


def test_prune_on_frames(spark):
    found = miner.mine(W.layout(spark, SF, "Y5", 500), ["x", "y"], 20, k=10, prune_when="never")
    t = found.report
    listed = prune.candidates(found.boxes, found.grid, t["n"], t["patterns"])
    boxes, moved = prune.prune(found.boxes, found.grid)
    after = model.total_bits(boxes, found.grid).first().total
    assert after <= t["end_bits"] + 1e-9 and boxes.count() <= t["patterns"] and moved.count() == t["patterns"] and listed.count() >= 0


@pytest.mark.parametrize(
    ("scope", "options"),
    [("inherited", {}), ("inherited", {"tie": "first", "requeue": True}), ("inherited", {"tie": "last", "prune_when": "each_round"}), ("inherited", {"gain_mode": "stored", "encoding": "shannon"}), ("all", {}), ("all", {"k": None, "tie": "last", "eps": 0.1})],
)
def test_rounds_in_tasks_agree_with_the_kernel(spark, monkeypatch, scope, options):
    df = W.load(spark, SF, "W6")
    run = lambda: miner.mine(df, W.attrs("W6"), 5, candidate_scope=scope, **({"k": 4, "prune_when": "never"} | options))
    local = run()
    monkeypatch.setattr(choose, "LOCAL_CANDIDATES", 30)
    monkeypatch.setattr(intasks, "SENT", 1)
    monkeypatch.setattr(intasks, "BLOCK", 50)
    seen, whole = [], kernel.mine
    monkeypatch.setattr(kernel, "mine", lambda p, *rest, **options: seen.append(len(p.live())) or whole(p, *rest, **options))
    tasks = run()
    assert all(n < local.report["cells"] for n in seen)
    boxes = lambda r: sorted((x.pid, tuple(x.lo), tuple(x.hi), x.usage) for x in r.boxes.collect())
    assert boxes(local) == boxes(tasks) and local.report["explored"] == tasks.report["explored"]
    assert sorted(map(tuple, local.lineage.collect())) == sorted(map(tuple, tasks.lineage.collect()))
    ledger = lambda r: [(x.round, x.step, x.a, x.b, x.pid, round(x.total_after, 6)) for x in r.ledger.orderBy("round", "step", "pid").collect()]
    assert ledger(local) == ledger(tasks)


@pytest.mark.parametrize("tie", ["hash", "first", "last"])
def test_matching_by_frames_is_matching_here(spark, monkeypatch, tie):
    rng = np.random.default_rng(4)
    a, b = rng.integers(1, 60, 300), rng.integers(61, 120, 300)
    edges = sorted(set(zip(a.tolist(), b.tolist(), strict=True)))
    frame = spark.createDataFrame([(x, y, float((x * y) % 7)) for x, y in edges], "a long, b long, w double")
    got = []
    for limit in (100_000, 20, 0):
        monkeypatch.setattr(choose, "MATCHING_LOCAL", limit)
        got.append(sorted((r.a, r.b, r.w) for r in matching.greedy_matching(frame, tie).collect()))
    assert got[0] == got[1] == got[2]
    empty = matching.greedy_matching(frame.limit(0), tie)
    assert empty.count() == 0 and "o" in empty.columns


@pytest.mark.parametrize("options", [{}, {"top_n": 20}, {"top_n": 30, "order": "usage"}])
def test_pruning_looks_through_all_pairs_once_or_twice(options, monkeypatch):
    """What a search of all pairs found is kept; a search from the start each time gives the same merges."""
    ledgers, whole = [], []
    for again in (False, True):
        g, p, run = kernel_run(random_cells(3, 700, (40, 40)), (40, 40), 1, tie="hash")

        def find(few, rows, top_n, floor):
            whole.append(len(rows) == few.size - 1)
            return kernel.prune_pairs(few, rows.tolist(), 5_000, 0.5, "plugin", floor)

        whole.clear()
        if again:
            monkeypatch.setattr(kernel.Holding, "best", fresh_search(kernel.Holding.best))
        merges = kernel.prune(p, run, g, find=find, **options)
        ledgers.append([x[:5] + tuple(round(v, 6) for v in x[5:]) for x in run.ledger])
        if not again:
            assert merges > 20 and sum(whole) * 2 < len(whole)
    assert ledgers[0] == ledgers[1]


def fresh_search(best):
    def run(self):
        self.pairs = None
        return best(self)

    return run


def test_holders_with_and_without_bit_sets(monkeypatch):
    rng = np.random.default_rng(2)
    lo = rng.integers(0, 12, (200, 6))
    hi = lo + rng.integers(0, 3, (200, 6))
    found = []
    for limit in (1 << 26, 0):
        monkeypatch.setattr(kernel, "HOLDER_BYTES", limit)
        holders = kernel.Holders(lo, hi)
        found.append([holders.holding(y, np.arange(y)).tolist() for y in range(1, 200)])
    assert found[0] == found[1] and any(map(any, found[0]))


@pytest.mark.parametrize("encoding", ["plugin", "shannon"])
def test_weights_of_earlier_pairs_above_a_floor(encoding):
    rng = np.random.default_rng(6)
    lo = rng.integers(0, 9, (80, 10))
    p = kernel.Patterns.of(np.arange(80), lo, lo + rng.integers(0, 3, lo.shape), rng.integers(1, 9, 80))
    earlier = kernel.EarlierPairs(kernel._compact(p, p.live()), 0.5, encoding)
    for y in range(1, 80):
        w = kernel.weights(p, np.arange(y), np.full(y, y), 0.5, encoding)
        for floor in (-np.inf, float(np.round(np.median(w), kernel.TIE))):
            x, got = earlier.of(y, floor)
            assert x.tolist() == np.flatnonzero(np.round(w, kernel.TIE) >= floor).tolist() and got == pytest.approx(w[x], abs=1e-9)


def test_stored_pairs_come_back():
    rng = np.random.default_rng(1)
    for n in (0, 1, 5000):
        pairs = kernel.different(kernel.packed(rng.integers(0, 1 << 20, n), rng.integers(0, 1 << 31, n)))
        held = intasks._stored(pairs)
        assert (intasks._read(pa.scalar(held, pa.binary())) == pairs).all()
    many = kernel.packed(np.repeat(np.arange(1000), 100), np.tile(np.arange(100), 1000) + 1000)
    assert len(intasks._stored(many)) < len(many)


def test_more_patterns_than_pruning_takes_are_mined_in_tasks(spark, monkeypatch):
    """Neighbours that are packed where they are found; the same boxes, and no pruning beyond its bound."""
    df = W.load(spark, SF, "W6")
    run = lambda: miner.mine(df, W.attrs("W6"), 6, k=4, prune_when="never")
    local = run()
    for name, limit in (("LOCAL_CANDIDATES", 30), ("ALL_PAIRS_CELLS", 1), ("PRUNE_PATTERNS", 1)):
        monkeypatch.setattr(choose, name, limit)
    monkeypatch.setattr(intasks, "BLOCK", 50)
    with pytest.warns(UserWarning, match="not pruned"):
        tasks = miner.mine(df, W.attrs("W6"), 6, k=4)
    boxes = lambda r: sorted((x.pid, tuple(x.lo), tuple(x.hi), x.usage) for x in r.boxes.collect())
    assert boxes(local) == boxes(tasks) and not tasks.report["pruned"] and choose.rounds_plan(400_000, 10**9, n_attrs=4) == "tasks"


def test_ledgers_are_columns():
    ledger = kernel.Ledger()
    ledger.append((0, 1, 1, 2, 9, 5, 0.5, 7.5))
    ledger.extend(1, np.arange(1, 3), np.array([3, 4]), np.array([5, 6]), np.array([10, 11]), np.array([4, 3]), np.array([1.0, 2.0]), np.array([6.5, 4.5]))
    rows = [(0, 1, 1, 2, 9, 5, 0.5, 7.5), (1, 1, 3, 5, 10, 4, 1.0, 6.5), (1, 2, 4, 6, 11, 3, 2.0, 4.5)]
    assert len(ledger) == 3 and list(ledger) == rows and ledger[-1] == rows[-1]
    assert [c.nbytes for c in ledger.columns()] == [12, 12, 24, 24, 24, 24, 24, 24]


def test_rounds_in_tasks_leave_no_broadcast(spark, monkeypatch):
    """What a step sends to the tasks goes when the step is over."""
    from pyspark.core.broadcast import Broadcast

    made, gone = [], []
    send, destroy = type(spark.sparkContext).broadcast, Broadcast.destroy
    monkeypatch.setattr(type(spark.sparkContext), "broadcast", lambda self, value: made.append(b := send(self, value)) or b)
    monkeypatch.setattr(Broadcast, "destroy", lambda self, blocking=False: gone.append(self) or destroy(self, blocking))
    for name, limit in (("LOCAL_CANDIDATES", 30), ("ALL_PAIRS_CELLS", 1)):
        monkeypatch.setattr(choose, name, limit)
    miner.mine(W.load(spark, SF, "W6"), W.attrs("W6"), 6, k=4, prune_when="never")
    assert made and {id(b) for b in made} == {id(b) for b in gone}


def test_sides_are_held_in_few_bits(monkeypatch):
    """Half the bytes, and the same merges as in 32 bits."""
    rng = np.random.default_rng(8)
    spots, usage = np.unique(rng.integers(0, 40, (200, 3)), axis=0, return_counts=True)
    g = grid.Grid(tuple(grid.Axis(f"a{i}", 40, 0.0, 1.0) for i in range(3)), int(usage.sum()))
    found = []
    for narrow, kind in ((1 << 14, np.int16), (0, np.int32)):
        monkeypatch.setattr(kernel, "NARROW", narrow)
        p = kernel.Patterns.of(np.arange(1, len(spots) + 1), spots, spots, usage)
        run = kernel.mine(p, kernel.packed(*neighbors.knn_local(spots, 8).T), g, tie="hash")
        kernel.prune(p, run, g)
        assert p.lo.dtype == p.hi.dtype == kind
        found.append((list(run.ledger), p.lo[p.live()].tolist(), p.hi[p.live()].tolist()))
    assert found[0] == found[1] and len(found[0][0]) > 10
    assert kernel.Patterns.of([1], [[0]], [[1 << 15]], [1]).hi[0, 0] == 1 << 15


def test_tiles_that_reach_all_points_are_looked_from_together(monkeypatch):
    rng = np.random.default_rng(5)
    points = np.unique(np.clip(np.round(rng.normal(2, 1, (2500, 64))), 0, 4).astype(np.int64), axis=0)
    ids, wide = np.arange(10, 10 + len(points)), []
    found_by = neighbors.Tiles._distances

    def counted(self, queries, rows):
        d = found_by(self, queries, rows)
        wide.append(d.shape[1] == len(points))
        return d

    monkeypatch.setattr(neighbors.Tiles, "_distances", counted)
    for k in (5, 300):
        wide.clear()
        row, near, d2 = neighbors.Tiles(ids, points, k).nearest(ids, points)
        assert sum(wide) <= 1 + len(points) ** 2 // neighbors.CHUNK
        d = ((points[:, None] - points[None]) ** 2).sum(axis=2)
        np.fill_diagonal(d, 1 << 40)
        best = np.argsort(d, axis=1, kind="stable")[:, :k]
        order = np.lexsort((near, d2, row))
        assert (near[order].reshape(-1, k) == ids[best]).all()
        assert (d2[order].reshape(-1, k) == np.take_along_axis(d, best, axis=1)).all()


def test_local_rounds_leave_no_broadcast_and_no_garbage(spark, monkeypatch):
    sent, freed, broadcast = [], [], type(spark.sparkContext).broadcast
    monkeypatch.setattr(type(spark.sparkContext), "broadcast", lambda self, value: sent.append(broadcast(self, value)) or sent[-1])
    let_go = miner.released
    monkeypatch.setattr(miner, "released", lambda s: freed.append(len(sent)) or let_go(s))
    df = W.load(spark, SF, "W3")
    g = grid.equal_width(df, W.attrs("W3"), "sqrt")
    plain = miner.mine(df, W.attrs("W3"), grid=g, k=4)
    assert not freed
    monkeypatch.setattr(choose, "ALL_PAIRS_CELLS", 50)
    found = miner.mine(df, W.attrs("W3"), grid=g, k=4)
    assert len(freed) == 3 and sent
    assert not [b for b in sent if b._jbroadcast.isValid()]
    assert sorted(map(tuple, found.boxes.collect())) == sorted(map(tuple, plain.boxes.collect()))


@pytest.mark.parametrize("options", [{"prune_when": "each_round"}, {"prune_when": "each_round", "requeue": True}, {"prune_when": "each_round", "candidate_scope": "all"}, {}])
def test_many_patterns_are_pruned_like_few(spark, monkeypatch, options):
    """Rounds on DataFrames to the end, then pruning, and after it further rounds."""
    df = W.load(spark, SF, "W6")
    run = lambda: miner.mine(df, W.attrs("W6"), 7, **({"k": 3, "eps": 0.1} | options))
    local = run()
    monkeypatch.setattr(choose, "LOCAL_PATTERNS", 2)
    spread = run()
    boxes = lambda r: sorted((x.pid, tuple(x.lo), tuple(x.hi), x.usage) for x in r.boxes.collect())
    assert boxes(local) == boxes(spread) and spread.report["pruned"] and not choose.unpruned(10**9)
    assert local.report["explored"] == spread.report["explored"] and local.report["rounds"] == spread.report["rounds"]
    assert local.report["end_bits"] == pytest.approx(spread.report["end_bits"])
    assert sorted(map(tuple, local.lineage.collect())) == sorted(map(tuple, spread.lineage.collect()))


def test_few_pairs_of_a_search_for_pruning_are_looked_into(monkeypatch):
    """The best pairs of a pattern first: with a floor the others need no look."""
    _, p, _ = kernel_run(random_cells(3, 700, (40, 40)), (40, 40), 1, tie="hash")
    few = kernel._compact(p, p.live())
    holding, seen, found = kernel.Holders.holding, [], []
    monkeypatch.setattr(kernel.Holders, "holding", lambda self, i, j: seen.append(len(j)) or holding(self, i, j))
    for size in (1 << 12, 16):
        monkeypatch.setattr(kernel, "LOOKED_INTO", size, raising=False)
        seen.clear()
        pairs, w, floor = kernel.prune_pairs(few, range(few.size - 1, 0, -1), 30, 0.5, "plugin")
        found.append((pairs.tolist(), w.tolist(), floor, sum(seen)))
    assert found[0][:3] == found[1][:3] and found[1][3] * 1.2 < found[0][3]


def test_tiles_meet_few_other_tiles(monkeypatch):
    """A tile is held against those near it along the first attribute, not against all; the neighbours are those of brute force."""
    points = np.unique(np.random.default_rng(4).integers(0, 3000, (4000, 2)), axis=0)
    points = np.concatenate([points, [[3600, 3900]]])
    tiles, met = neighbors.Tiles(np.arange(len(points)), points, 4), []
    rings = neighbors.Tiles._rings
    monkeypatch.setattr(neighbors.Tiles, "_rings", lambda self, spot, r: met.append(len((out := rings(self, spot, r))[1])) or out)
    row, near, d2 = tiles.nearest(np.arange(len(points)), points)
    assert sum(met) < len(tiles.spots) ** 2 / 2
    for q in (0, 17, 2000, len(points) - 1):
        far = ((points - points[q]) ** 2).sum(axis=1)
        far[q] = far.max() + 1
        best = np.lexsort((np.arange(len(points)), far))[:4]
        assert sorted(near[row == q].tolist()) == sorted(best.tolist()) and sorted(d2[row == q].tolist()) == sorted(far[best].tolist())


def test_contracted_pairs_are_stored_by_place(spark, monkeypatch):
    """After merges rows lie in no spatial order; pairs are numbered by place, so they stay small and are the same."""
    rng = np.random.default_rng(6)
    spots = np.unique(rng.integers(0, 200, (6000, 2)), axis=0)
    n = len(spots)
    p = kernel.Patterns.of(np.arange(1, n + 1), spots, spots, np.ones(n))
    near = neighbors.knn_local(spots, 60)
    merged = rng.permutation(n)[: n // 2 * 2].reshape(2, -1)  # into rows without any order
    run = kernel.Run(p)
    rows = p.add_pairs(merged[0], merged[1], n + 1)
    run.parent[merged] = rows
    want = kernel.packed(*run.roots()[near].T)
    want = kernel.different(want[want >> 32 != want & kernel._LOW])
    frame = spark.createDataFrame((near[:2000] + 1).tolist(), "a long, b long")
    few = intasks.contracted(intasks.from_neighbors(frame, p, 2000), p, run.roots())
    some = kernel.packed(*run.roots()[near[:2000]].T)
    assert few.rows().tolist() == kernel.different(some[some >> 32 != some & kernel._LOW]).tolist() and few.order is not None
    again = intasks.contracted(few, p, run.roots())
    assert again.rows().tolist() == few.rows().tolist() and len(want) > few.n
    # rows in the order of places, as neighbours' pairs are stored
    live = p.live()
    assert (np.diff(p.lo[few.order][:, 0].astype(int)) >= 0).all() and sorted(few.order.tolist()) == live.tolist()


def test_a_million_patterns_are_mined_in_tasks():
    """Pairs on DataFrames take many times the disk."""
    assert choose.rounds_plan(951_352, 2 * 10**9, n_attrs=2) == choose.rounds_plan(1_200_000, 10**9, n_attrs=4) == "tasks"
    assert choose.rounds_plan(1_200_001, 10**9) == "distributed"
