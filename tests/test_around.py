"""Baselines, measures by hand, streaming twins, SQL functions, driver contract."""

import math

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from boxmdl import experiments, session, sources, streaming
from boxmdl.functions import codes, sqlapi
from boxmdl.operators import baselines, cells, grid, measures, miner
from boxmdl.operators.baselines import itemset, sampling
from boxmdl.operators.baselines.limits import Limits
from boxmdl.sources import workloads as W

SF = "/root/testdata/sf0.001"


def test_itemsets_shorten_and_do_not_overlap(spark):
    df = W.load(spark, SF, "W7")
    g = grid.equal_width(df, W.attrs("W7"), 4)
    c = cells.elementary(cells.discretise(df, g)).cache()
    found = itemset.mine(c, g)
    assert found.end_bits <= found.start_bits and sum(u * len(i) for i, u in found.itemsets) == 4 * df.count()
    boxes = itemset.to_boxes(spark, found, g)
    assert boxes.count() == len(found.itemsets)
    strong = spark.createDataFrame([(1.0, 1.0)] * 200 + [(9.0, 9.0)] * 200 + [(1.0, 9.0)], "x double, y double")
    g = grid.equal_width(strong, ["x", "y"], 2)
    found = itemset.mine(cells.elementary(cells.discretise(strong, g)), g)
    assert ([0, 2], 200.0) in found.itemsets and ([1, 3], 200.0) in found.itemsets


def test_sampling_finds_a_dense_box_again_and_again(spark):
    df = W.layout(spark, SF, "Y5", 500).cache()
    found = sampling.mine(df, ["x", "y"], 0.5, thoroughness=40, seed=1)
    again = sampling.mine(df, ["x", "y"], 0.5, thoroughness=40, seed=1)
    assert found.boxes.count() == again.boxes.count() > 1 and found.sample == 500
    assert measures.box_jaccard_mean(found.boxes).first().mean_jaccard > 0.2
    sizes = sampling.size_of("sqrt", 100), sampling.size_of(0.25, 100), sampling.size_of(7, 100)
    assert sizes == (10, 25, 7)
    seen = sampling.as_occurrences(found, df, ["x", "y"], "obj_id").groupBy("pid").count().join(found.boxes, "pid").collect()
    assert all(abs(r["count"] - r.support) <= 1 for r in seen)


def test_one_box_and_clusters(spark):
    df = W.load(spark, SF, "W7")
    g = grid.equal_width(df, W.attrs("W7"), 5)
    c = cells.elementary(cells.discretise(df, g))
    one = baselines.single_box(c).first()
    assert one.usage == df.count() and one.lo == [0] * 4 and one.hi == [4] * 4
    assert baselines.elementary(c, g).first().k == c.count()
    assert baselines.cluster_boxes(df, W.attrs("W7"), 3).agg(F.sum("usage")).first()[0] == df.count()


def test_measures_by_hand(spark):
    boxes = spark.createDataFrame([(1, [0, 0], [1, 1], 3), (2, [1, 1], [2, 2], 4), (3, [5, 5], [5, 5], 1)], "pid long, lo array<int>, hi array<int>, usage long")
    c = spark.createDataFrame([(1, [0, 0], [0, 0], 2), (2, [1, 1], [1, 1], 3), (3, [2, 2], [2, 2], 5), (4, [5, 5], [5, 5], 1)], "cell_id long, lo array<int>, hi array<int>, usage long")
    assert {r.pid: r.support for r in measures.support(boxes, c).collect()} == {1: 5, 2: 8, 3: 1}
    both = measures.jaccard_pairs(boxes, c).collect()
    assert [(r.a, r.b, r.jaccard) for r in both] == [(1, 2, 3 / 10)]
    assert measures.jaccard_all(boxes, c).first().mean_jaccard == pytest.approx(0.1)
    assert measures.jaccard_topk(boxes, c, 1).first().pairs == 2
    real = spark.createDataFrame([(1, [0.0, 0.0], [2.0, 2.0]), (2, [1.0, 1.0], [3.0, 3.0])], "pid long, rlo array<double>, rhi array<double>")
    assert measures.box_jaccard_mean(real).first().mean_jaccard == pytest.approx(1 / 9)
    assert measures.jcd(real, real, "pid", "pid").first().jcd == 1.0
    disc = spark.createDataFrame([(0, 0, "a"), (0, 0, "b"), (1, 1, "a"), (5, 5, "c"), (2, 2, None)], "b_0 int, b_1 int, label string")
    acc = {r.pid: (r.majority, r.rows, r.accuracy) for r in measures.accuracy(boxes, disc, "label").collect()}
    assert acc == {1: ("a", 3, 2 / 3), 2: ("a", 1, 1.0), 3: ("c", 1, 1.0)}
    assert measures.confusion(boxes, disc, "label", ["a", "b"]).count() == 3
    assert measures.length_ratio(4.0, 2.0) == 2.0
    assert measures.mean_accuracy(measures.accuracy(boxes, disc, "label"), "rows").first().mean_accuracy == pytest.approx(4 / 5)


def test_stream_equals_batch(spark, tmp_path):
    events = sources.table(spark, SF, "events").withColumn("k", F.get_json_object("props", "$.k").cast("double"))
    events.coalesce(1).write.parquet(str(tmp_path / "in"))
    found = miner.mine(events, ["value", "k"], 4, k=3)
    stream = spark.readStream.schema(events.schema).parquet(str(tmp_path / "in")).withColumn("ts", F.col("ts").cast("timestamp"))
    batch = events.withColumn("ts", F.col("ts").cast("timestamp"))

    def drain(df, name, mode="append"):
        q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).option("checkpointLocation", str(tmp_path / name)).start()
        q.awaitTermination()
        return spark.table(name)

    scored = drain(streaming.score(stream, found), "scored")
    assert scored.count() == events.count() and scored.filter("pid is null").isEmpty()
    k = found.report["patterns"]
    bits = drain(streaming.online_bits(streaming.score(stream, found), "user_id", k), "bits")
    twin = streaming.online_bits_batch(streaming.score(batch, found), "user_id", k)
    assert {r.event_id: round(r.bits, 9) for r in bits.collect()} == {r.event_id: round(r.bits, 9) for r in twin.collect()}
    cells_now = drain(streaming.window_cells(stream, found.grid), "windows", "complete")
    assert sorted(map(str, cells_now.collect())) == sorted(map(str, streaming.window_cells(batch, found.grid).collect()))
    assert drain(streaming.distinct_events(stream), "distinct").count() == events.count()
    assert streaming.drift(twin).count() > 0 and streaming.session_cells(batch, found.grid).count() > 0
    seen = []
    streaming.remine(stream.select("value", "k"), lambda b: miner.mine(b, ["value", "k"], 4, k=3), lambda n, r: seen.append(r.report["n"]), str(tmp_path / "re")).awaitTermination()
    assert sum(seen) == events.count()


def test_sql_functions(spark):
    sqlapi.register(spark)
    row = spark.sql("SELECT lnat_bits(12L) AS n, lgamma_bits(7.5D) AS g, bin_of(5D, 0D, 10D, 4) AS b, bin_of(10D, 0D, 10D, 4) AS top, box_jaccard(array(0D, 0D), array(2D, 2D), array(1D, 1D), array(3D, 3D)) AS j").first()
    assert (row.n, row.g, row.b, row.top, row.j) == pytest.approx((codes.universal_int_bits(12), math.lgamma(7.5) / math.log(2), 2, 3, 1 / 9))
    W.layout(spark, SF, "Y5", 200).createOrReplaceTempView("y5")
    boxes = spark.sql("SELECT * FROM mine_boxes(TABLE(SELECT array(x, y) AS v FROM y5) WITH SINGLE PARTITION, 10, 5)").collect()
    assert sum(r.usage for r in boxes) == 400
    groups = sqlapi.mine_groups(W.layout(spark, SF, "Y1", 100), "tid", ["x", "y"]).groupBy("tid").agg(F.sum("usage").alias("n")).collect()
    assert {r.n for r in groups} == {100}


def test_sources(spark, tmp_path):
    for name in sources.TABLES:
        assert sources.table(spark, SF, name).limit(1).count() == 1
    for name, w in W.WORKLOADS.items():
        row = W.load(spark, SF, name)
        assert set(w.attrs) | {"label"} <= set(row.columns)
    sources.table(spark, SF, "nation").write.csv(str(tmp_path / "c"), header=True)
    assert sources.read(spark, "csv", str(tmp_path / "c"), "n_nationkey int, n_name string, n_regionkey int", header=True).count() == 25
    sources.register_all(spark, SF)
    assert spark.sql("SELECT count(*) AS n FROM nation JOIN region ON n_regionkey = r_regionkey").first().n == 25
    assert W.load(spark, SF, "W2").select("l_shipdate").dtypes == [("l_shipdate", "double")]


def test_driver_contract(spark):
    assert entry.entry(spark).count() > 0
    names = entry.queries()
    assert set(entry.oracle_sql()) <= set(names) and len(names) > 100


def test_limits_are_reported(spark):
    df = W.load(spark, SF, "W7")
    g = grid.equal_width(df, W.attrs("W7"), 5)
    c = cells.elementary(cells.discretise(df, g)).cache()
    assert itemset.mine(c, g).status == "ok" and itemset.mine(c, g, seconds=0.0).status == "time"
    assert sampling.mine(df, W.attrs("W7"), 0.25, seconds=0.0).status == "time"
    limits = Limits(memory=1000)
    assert not limits.over_memory(1000) and limits.over_memory(1001) and limits.status == "memory"
    with pytest.raises(ValueError):
        session.local_folder("spark://host:7077")
    assert session.local_folder("local[4]").startswith("file://")


def test_itemset_covers_stay_right_through_changes():
    """Usages kept up to date row by row equal those of covering all rows anew."""
    rng = np.random.default_rng(2)
    rows = np.unique(rng.integers(0, 3, (60, 4)) + np.array([0, 3, 6, 9]), axis=0)
    table = itemset.CodeTable(rows, rng.integers(1, 5, len(rows)).astype(float))

    def anew():
        usage, covers = {}, table._cover(np.arange(len(rows)))
        for r, parts in covers.items():
            for s in parts:
                usage[s] = usage.get(s, 0) + table.weight[r]
        return usage

    for _ in range(40):
        if table.support and rng.random() < 0.3:
            undo = table.change(drop=list(table.support)[int(rng.integers(len(table.support)))])
        else:
            joint = frozenset(rng.choice(rows[int(rng.integers(len(rows)))], int(rng.integers(2, 5)), replace=False).tolist())
            if joint in table.support:
                continue
            undo = table.change(add=joint)
        if rng.random() < 0.3:
            undo()
        assert {s: u for s, u in table.usage.items() if u} == anew()


def test_layout_runs_of_all_methods(spark):
    got = experiments.layouts(spark, SF, sizes=(100,), names=("Y1", "Y5")).toPandas()
    assert len(got) == 18 and (got.status == "ok").all() and got.notna().all().all()
    fine = got[(got.method == "boxes") & (got.setting == "sqrt")]
    assert (fine.jcd_computed > got[got.method == "itemsets"].jcd_computed.max()).all()


def test_local_interaction_cuts_are_those_on_rows(spark):
    rng = np.random.default_rng(0)
    x = np.round(rng.random(900), 3)
    values = np.stack([x, (x > 0.5) * 5 + np.round(rng.random(900), 3)], axis=1)
    df = spark.createDataFrame([tuple(map(float, v)) for v in values], "x double, y double")
    here, there = grid.interaction_cuts(values, 20), grid.interaction_preserving(df, ["x", "y"], 20)
    assert [a.cuts for a in there.axes] == here


@pytest.mark.parametrize("name", ["lnat_bits", "lgamma_bits"])
def test_code_queries_read_a_table(spark, name):
    from boxmdl import queries as Q

    made = Q.QUERIES[name](spark, "/root/testdata/sf0.01")
    assert any("lineitem.parquet" in f for f in made.inputFiles())
    con = duckdb.connect()
    con.sql("CREATE VIEW lineitem AS SELECT * FROM '/root/testdata/sf0.01/lineitem.parquet'")
    assert sorted(map(tuple, made.collect())) == sorted(con.sql(Q.ORACLES[name]).fetchall())


def test_sampled_boxes_keep_no_other_bounds():
    """A box that is a view would keep the bounds of every step of its growth."""
    rng = np.random.default_rng(3)
    lo, hi = sampling._grow(rng.random((500, 2)), 0, 10, 1000, 2)
    assert lo.base is None and hi.base is None


@pytest.mark.parametrize("seed", [0, 5])
def test_samples_numbered_by_tasks_are_those_chosen_here(spark, monkeypatch, seed):
    df = W.load(spark, SF, "W6")
    here = sampling._sampled(df, W.attrs("W6"), 300, seed)
    monkeypatch.setattr(sampling, "CHOSEN_HERE", 0)
    assert len(here) == 300 and (sampling._sampled(df, W.attrs("W6"), 300, seed) == here).all()


def test_itemsets_are_searched_by_a_task(spark, monkeypatch):
    """The driver holds no code table; the result is that of the search here."""
    df = W.load(spark, SF, "W7")
    g = grid.equal_width(df, W.attrs("W7"), 5)
    c = cells.elementary(cells.discretise(df, g)).cache()
    found = c.orderBy("cell_id").collect()
    here = itemset.mine_rows(np.array([r.lo for r in found]) + np.array(itemset.offsets(g)), np.array([float(r.usage) for r in found]))
    monkeypatch.setattr(itemset, "CodeTable", None)
    got = itemset.mine(c, g)
    assert (got.itemsets, got.start_bits, got.end_bits, got.evaluated) == (here.itemsets, here.start_bits, here.end_bits, here.evaluated)


def test_code_tables_hold_changed_covers_only():
    rows = np.array([[0, 3], [0, 4], [1, 3]])
    table = itemset.CodeTable(rows, np.ones(3))
    assert not table.covers
    table.change(add=frozenset([0, 3]))
    assert list(table.covers) == [0] and table.cover_of(1) == [frozenset([0]), frozenset([4])]


def test_baselines_run_whatever_their_memory(spark, monkeypatch):
    """The size of the input does not decide whether a baseline runs."""
    df = W.load(spark, SF, "W9")
    g = grid.equal_width(df, W.attrs("W9"), 5)
    c = cells.elementary(cells.discretise(df, g)).cache()
    monkeypatch.setattr(Limits, "over_memory", lambda self, needed: setattr(self, "status", "memory") or True)
    sets, grown = itemset.mine(c, g), sampling.mine(df, W.attrs("W9"), 20)
    assert sets.status == grown.status == "ok" and sets.itemsets and grown.evaluated
