"""Registered mining queries and their SQL oracles.

Integer results are exact; real ones are rounded to six places in both engines.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import experiments as E
from . import oracles as O
from . import streaming
from .functions import codes
from .operators import around, baselines, boxes, candidates, cells, grid, matching, measures, miner, model, neighbors, prune
from .operators.baselines import itemset, sampling
from .session import fixed
from .sources import workloads as W

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def rounded(df: DataFrame, places: int = 6) -> DataFrame:
    return df.select(*[F.round(c, places).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


def setup(spark, sf, w, bins):
    df = W.load(spark, sf, w)
    g = grid.equal_width(df, W.attrs(w), bins)
    return df, g


def cell_table(spark, sf, w, bins):
    df, g = setup(spark, sf, w, bins)
    return fixed(cells.elementary(cells.discretise(df, g))), g


def flat(df: DataFrame, k: int, **renamed: str) -> DataFrame:
    """Array columns as numbered columns."""
    out = [c for c in df.columns if c not in renamed]
    return df.select(*out, *[F.element_at(c, i + 1).alias(f"{p}{i}") for c, p in renamed.items() for i in range(k)])


def label_hulls(spark, sf, w, bins):
    """Hulls of the labels as a pattern set: ``pid, label, lo, hi, usage, log_size``, the cells and the grid."""
    df, g = setup(spark, sf, w, bins)
    disc = cells.discretise(df, g, ["label"])
    from pyspark.sql import Window

    hulls = cells.hull_cells(disc, "label").withColumn("pid", F.row_number().over(Window.orderBy("label")).cast("long"))  # a row for each label
    return boxes.with_log_size(hulls), cells.elementary(disc), disc, g


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Boxes of the embeddings' first elements on the root-n grid, with as many neighbours as intervals, in real bounds."""
    found = _mined(spark, sf_dir, "W7", "sqrt", "bins")
    return cells.to_real(found.boxes, found.grid)


# Grids, indices, cells

for _w, _b in (("W1", 5), ("W2", "sqrt"), ("W3", "sqrt"), ("W4", 5), ("W5", 5), ("W6", 5), ("W7", 5)):

    @query(f"grid_equal_width_{_w.lower()}", O.equal_width(_w, _b))
    def _(spark, sf, w=_w, b=_b):
        return grid.to_frame(spark, setup(spark, sf, w, b)[1]).drop("axis", "cuts")


@query("grid_equal_height_w3", O.equal_height("W3", 8))
def _(spark, sf):
    g = grid.equal_height(W.load(spark, sf, "W3"), W.attrs("W3"), 8, exact=True)
    return grid.to_frame(spark, g).select("attr", F.posexplode("cuts").alias("cut", "value")).select("attr", (F.col("cut") + 1).alias("cut"), F.round("value", 6).alias("value"))


@query("grid_equal_height_approx_w6")
def _(spark, sf):
    return grid.to_frame(spark, grid.equal_height(W.load(spark, sf, "W6"), W.attrs("W6"), 8))


@query("grid_mdl_1d_w6")
def _(spark, sf):
    return grid.to_frame(spark, grid.mdl_1d(W.load(spark, sf, "W6"), W.attrs("W6")))


@query("grid_interaction_preserving_w7")
def _(spark, sf):
    return grid.to_frame(spark, grid.interaction_preserving(W.load(spark, sf, "W7"), W.attrs("W7")))


@query("grid_user_cuts_w4", "SELECT obj_id, (p_size >= 10)::INT + (p_size >= 30)::INT AS b_0, (p_retailprice >= 950)::INT AS b_1 FROM (SELECT p_partkey AS obj_id, p_size, p_retailprice FROM part)")
def _(spark, sf):
    df = W.load(spark, sf, "W4")
    return cells.discretise(df, grid.from_cuts(df, {"p_size": [10, 30], "p_retailprice": [950]}), ["obj_id"])


for _w, _b in (("W4", 5), ("W4", "sqrt"), ("W6", 5), ("W3", "sqrt")):

    @query(f"discretise_{_w.lower()}_{_b}", f"WITH {O.disc(_w, _b)} SELECT obj_id, {O.names(_w)} FROM d")
    def _(spark, sf, w=_w, b=_b):
        df, g = setup(spark, sf, w, b)
        return cells.discretise(df, g, ["obj_id"])


for _w in ("W1", "W2", "W3", "W4", "W5", "W6", "W7", "W9", "W10", "W12"):
    for _b in (5, "sqrt"):

        @query(f"cells_{_w.lower()}_{_b}", O.cell_rows(_w, _b))
        def _(spark, sf, w=_w, b=_b):
            c, g = cell_table(spark, sf, w, b)
            return flat(c.drop("hi"), len(g.axes), lo="b_")


_DESCRIBED = [(w, b) for w in ("W1", "W2", "W3", "W4", "W5", "W6", "W7", "W9", "W10", "W12") for b in (5, "sqrt")]


@query("describe_workloads", O.describe(_DESCRIBED))
def _(spark, sf):
    out = None
    for w, b in _DESCRIBED:
        df, g = setup(spark, sf, w, b)
        one = measures.describe(df, W.attrs(w), g, "label").select(F.lit(w).alias("workload"), F.lit(str(b)).alias("bins"), "*")
        out = one if out is None else out.unionByName(one)
    return out


for _w in ("W1", "W7"):

    @query(f"hull_by_label_{_w.lower()}", O.hull_real(_w))
    def _(spark, sf, w=_w):
        return flat(cells.hull(W.load(spark, sf, w), W.attrs(w), "label"), len(W.attrs(w)), lo="lo_", hi="hi_")


# Codes and lengths


_LNAT_SQL = f"""
SELECT n, round({O.lnat('n')}, 6) AS bits
FROM (SELECT l_orderkey AS n FROM lineitem UNION SELECT l_partkey FROM lineitem UNION SELECT (round(l_extendedprice * 100))::BIGINT FROM lineitem)
"""


@query("lnat_bits", _LNAT_SQL)
def _(spark, sf):
    """Bits of every integer that is a key or a price in cents of `lineitem`."""
    rows = W.table(spark, sf, "lineitem").select(F.explode(F.array("l_orderkey", "l_partkey", F.round(F.col("l_extendedprice") * 100).cast("long"))).alias("n"))
    return rows.distinct().select("n", F.round(codes.universal_int_bits_col(F.col("n")), 6).alias("bits"))


_LGAMMA_SQL = f"""
SELECT n, round({O.lg('n + 0.5')}, 5) AS bits
FROM (SELECT count(*) AS n FROM lineitem GROUP BY l_partkey UNION SELECT count(*) FROM lineitem GROUP BY l_suppkey UNION SELECT l_quantity::BIGINT FROM lineitem)
"""


@query("lgamma_bits", _LGAMMA_SQL)
def _(spark, sf):
    """log2 gamma of the usages of the parts and suppliers of `lineitem`, and of its quantities."""
    lines = W.table(spark, sf, "lineitem")
    usages = lines.select(F.col("l_quantity").cast("long").alias("n"))
    for key in ("l_partkey", "l_suppkey"):
        usages = usages.unionByName(lines.groupBy(key).agg(F.count(F.lit(1)).alias("n")).select("n"))
    return usages.distinct().select("n", F.round(codes.lgamma_bits_col(F.col("n") + F.lit(0.5)), 5).alias("bits"))


for _w, _b in (("W1", 5), ("W2", "sqrt"), ("W3", "sqrt"), ("W4", 5), ("W4", "sqrt"), ("W5", 5), ("W6", "sqrt"), ("W7", 5), ("W9", "sqrt")):
    for _e in ("plugin", "shannon"):

        @query(f"length_cells_{_w.lower()}_{_b}_{_e}", O.length(_w, _b, "c", _e))
        def _(spark, sf, w=_w, b=_b, e=_e):
            c, g = cell_table(spark, sf, w, b)
            return rounded(model.total_bits(miner.starting_boxes(c), g, encoding=e))


for _w, _b in (("W7", 5), ("W6", 5), ("W1", 5)):

    @query(f"length_hulls_{_w.lower()}", O.length(_w, _b, "h"))
    def _(spark, sf, w=_w, b=_b):
        hulls, _c, _d, g = label_hulls(spark, sf, w, b)
        return rounded(model.total_bits(hulls, g))


@query("uniform_code_w4", f"WITH {O.cells('W4', 5)} SELECT sum(usage)::BIGINT AS n, count(*) AS k, round(sum(usage) * log2(count(*)), 6) AS bits FROM c")
def _(spark, sf):
    c, _g = cell_table(spark, sf, "W4", 5)
    t = c.agg(F.sum("usage").alias("n"), F.count(F.lit(1)).alias("k"))
    return t.select("n", "k", F.round(F.col("n") * F.log2(F.col("k").cast("double")), 6).alias("bits"))


@query("plugin_steps_w6", O.plugin_steps("W6", 5))
def _(spark, sf):
    df, g = setup(spark, sf, "W6", 5)
    c, _g = cell_table(spark, sf, "W6", 5)
    spot = F.array(*[f"b_{i}" for i in range(3)])
    seq = cells.discretise(df, g, ["obj_id", "ts"]).select("obj_id", "ts", spot.alias("lo")).join(c.select("lo", "cell_id"), "lo")
    steps = codes.plugin_step_bits(seq, "cell_id", ["ts", "obj_id"], c.count())
    return steps.groupBy("cell_id").agg(F.count(F.lit(1)).alias("uses"), F.round(F.sum("bits"), 5).alias("bits"))


# Neighbours, candidates, gains

for _w, _b, _k, _m in (("W4", 5, 5, "broadcast"), ("W5", 5, 5, "broadcast"), ("W6", 5, 3, "broadcast"), ("W4", "sqrt", 3, "tiled"), ("W6", 5, 3, "tiled")):

    @query(f"knn_{_w.lower()}_{_b}_k{_k}_{_m}", O.knn_rows(_w, _b, _k))
    def _(spark, sf, w=_w, b=_b, k=_k, m=_m):
        c, g = cell_table(spark, sf, w, b)
        return neighbors.knn(c, k, len(g.axes), m)


@query("knn_w8_recall")
def _(spark, sf):
    """Recall of the approximate neighbours in 64 attributes, against the exact ones."""
    c, g = cell_table(spark, sf, "W8", 5)
    return neighbors.recall(neighbors.knn(c, 5, len(g.axes), "projected"), neighbors.knn(c, 5, len(g.axes), "tiled"))


@query("knn_w8_projected")
def _(spark, sf):
    """Approximate neighbours in 64 attributes."""
    c, g = cell_table(spark, sf, "W8", 5)
    return neighbors.knn(c, 5, len(g.axes), "projected")


@query("candidates_w4_k1", O.edge_rows("W4", 5, 1))
def _(spark, sf):
    c, g = cell_table(spark, sf, "W4", 5)
    return neighbors.edges(neighbors.knn(c, 1, len(g.axes)))


@query("candidates_w4_every_pair", f"WITH {O.cells('W4', 5)} SELECT x.cell_id AS a, y.cell_id AS b FROM c x JOIN c y ON x.cell_id < y.cell_id")
def _(spark, sf):
    return neighbors.every_pair(cell_table(spark, sf, "W4", 5)[0])


@query("pair_weight_w4", O.pair_weights("W4", 5, 5))
def _(spark, sf):
    c, g = cell_table(spark, sf, "W4", 5)
    pairs = neighbors.edges(neighbors.knn(c, 5, len(g.axes)))
    return rounded(candidates.weighted(pairs, miner.starting_boxes(c), codes.EPS).select("a", "b", "w"))


@query("first_round_best_w4", O.pair_weights("W4", 5, 5, 20))
def _(spark, sf):
    c, g = cell_table(spark, sf, "W4", 5)
    pairs = neighbors.edges(neighbors.knn(c, 5, len(g.axes)))
    t = c.agg(F.count(F.lit(1)).alias("k"), F.sum("usage").alias("n")).first()
    gains = candidates.weighted(pairs, miner.starting_boxes(c), codes.EPS).withColumn("gain", F.col("w") + F.lit(model.kappa(t.k, t.n, g)))
    return gains.orderBy(F.desc(F.round("w", 9)), "a", "b").limit(20).select("a", "b", F.round("gain", 6).alias("gain"))


@query("matching_round_w3_sqrt")
def _(spark, sf):
    """The first round's accepted merges on a fine grid, found by distributed matching."""
    c, g = cell_table(spark, sf, "W3", "sqrt")
    t = c.agg(F.count(F.lit(1)).alias("k"), F.sum("usage").alias("n")).first()
    pairs = neighbors.edges(neighbors.knn(c, 4, 2, "tiled", t.k))
    weighted = candidates.weighted(pairs, miner.starting_boxes(c), codes.EPS).select("a", "b", "w")
    return rounded(matching.accepted(matching.greedy_matching(weighted), t.k, t.n, g, codes.EPS, "plugin", "refreshed", t.k + 1))


@query("prune_candidates_hulls_w7", O.prune_candidates("W7", 5, 1000))
def _(spark, sf):
    hulls, c, _d, g = label_hulls(spark, sf, "W7", 5)
    t = hulls.agg(F.count(F.lit(1)).alias("k"), F.sum("usage").alias("n")).first()
    return rounded(prune.candidates(hulls, g, t.n, t.k))


# Measures on the label hulls

for _w in ("W7", "W6"):

    @query(f"support_hulls_{_w.lower()}", O.support(_w, 5))
    def _(spark, sf, w=_w):
        hulls, c, _d, _g = label_hulls(spark, sf, w, 5)
        return measures.support(hulls, c)

    @query(f"jaccard_all_hulls_{_w.lower()}", O.jaccard_all(_w, 5))
    def _(spark, sf, w=_w):
        hulls, c, _d, _g = label_hulls(spark, sf, w, 5)
        return rounded(measures.jaccard_all(hulls, c))

    @query(f"jaccard_top3_hulls_{_w.lower()}", O.jaccard_topk(_w, 5, 3))
    def _(spark, sf, w=_w):
        hulls, c, _d, _g = label_hulls(spark, sf, w, 5)
        return rounded(measures.jaccard_topk(hulls, c, 3))

    @query(f"jaccard_top10_hulls_{_w.lower()}", O.jaccard_topk(_w, 5, 10))
    def _(spark, sf, w=_w):
        hulls, c, _d, _g = label_hulls(spark, sf, w, 5)
        return rounded(measures.jaccard_topk(hulls, c, 10))

    @query(f"accuracy_cover_cells_{_w.lower()}", O.accuracy_cover(_w, 5))
    def _(spark, sf, w=_w):
        """Accuracy of the unmerged cells over what they encode."""
        df, g = setup(spark, sf, w, 5)
        disc = cells.discretise(df, g, ["label"])
        c = fixed(cells.elementary(disc))
        own = c.select("cell_id", F.col("cell_id").alias("pid"))
        return rounded(measures.accuracy(miner.starting_boxes(c), disc, "label", "cover", own, c))

    @query(f"length_ratio_hulls_{_w.lower()}", O.length_ratio(_w, 5))
    def _(spark, sf, w=_w):
        """Length of the unmerged cells over that of the label hulls."""
        hulls, c, _d, g = label_hulls(spark, sf, w, 5)
        one, other = (model.total_bits(b, g).select(F.col("total").alias(x)) for b, x in ((miner.starting_boxes(c), "cells"), (hulls, "hulls")))
        return one.crossJoin(other).select(F.round(F.col("cells") / F.col("hulls"), 6).alias("ratio"))  # one row each

    @query(f"accuracy_hulls_{_w.lower()}", O.accuracy(_w, 5))
    def _(spark, sf, w=_w):
        hulls, _c, disc, _g = label_hulls(spark, sf, w, 5)
        return rounded(measures.accuracy(hulls, disc, "label"))


# Planted layouts

for _y in W.LAYOUTS:

    @query(f"layout_{_y.lower()}", O.layout_rows(_y, 200))
    def _(spark, sf, y=_y):
        return rounded(W.layout(spark, sf, y, 200), 9)

    @query(f"planted_jcd_{_y.lower()}", O.planted_jcd(_y, 200))
    def _(spark, sf, y=_y):
        found = cells.hull(W.layout(spark, sf, y, 200), ["x", "y"], "tid").select(F.col("tid").alias("pid"), F.col("lo").alias("rlo"), F.col("hi").alias("rhi"))
        known = W.truth(spark, y)
        ours = measures.jcd(found, known).select(F.lit("computed").alias("side"), "*")
        return rounded(ours.unionByName(measures.jcd(known, found, "tid", "pid").select(F.lit("truth").alias("side"), "*")))

    @query(f"planted_overlap_{_y.lower()}", O.planted_overlap(_y, 200))
    def _(spark, sf, y=_y):
        found = cells.hull(W.layout(spark, sf, y, 200), ["x", "y"], "tid").select(F.col("tid").alias("pid"), F.col("lo").alias("rlo"), F.col("hi").alias("rhi"))
        return rounded(measures.box_jaccard_mean(found))


# Baselines


@query("binarise_w4", O.binarise_rows("W4", 5))
def _(spark, sf):
    df, g = setup(spark, sf, "W4", 5)
    return flat(itemset.binarise(cells.discretise(df, g, ["obj_id"]), g, ["obj_id"]), 2, items="item_")


@query("item_support_w4", O.item_support("W4", 5))
def _(spark, sf):
    df, g = setup(spark, sf, "W4", 5)
    return itemset.item_support(itemset.binarise(cells.discretise(df, g), g))


@query("item_pair_support_w7", O.pair_support("W7", 5))
def _(spark, sf):
    df, g = setup(spark, sf, "W7", 5)
    return itemset.pair_support(itemset.binarise(cells.discretise(df, g), g))


@query("itemset_baseline_w7")
def _(spark, sf):
    c, g = cell_table(spark, sf, "W7", 5)
    return itemset.to_boxes(spark, itemset.mine(c, g, seconds=E.SECONDS), g)


@query("sampling_baseline_w7")
def _(spark, sf):
    return sampling.mine(W.load(spark, sf, "W7"), W.attrs("W7"), 0.25, seconds=E.SECONDS).boxes


@query("sample_w3", "SELECT greatest(2, floor(sqrt(count(*))))::BIGINT AS rows FROM orders")
def _(spark, sf):
    df = W.load(spark, sf, "W3")
    return sampling.sample_rows(df, W.attrs("W3"), sampling.size_of("sqrt", df.count()), id_col="obj_id").agg(F.count(F.lit(1)).alias("rows"))


@query("single_box_w4", f"WITH {O.cells('W4', 5)} SELECT 1::BIGINT AS pid, min(b_0) AS lo_0, min(b_1) AS lo_1, max(b_0) AS hi_0, max(b_1) AS hi_1, sum(usage)::BIGINT AS usage FROM c")
def _(spark, sf):
    return flat(baselines.single_box(cell_table(spark, sf, "W4", 5)[0]).drop("log_size"), 2, lo="lo_", hi="hi_")


@query("cluster_boxes_w7")
def _(spark, sf):
    return flat(baselines.cluster_boxes(W.load(spark, sf, "W7"), W.attrs("W7"), 10), 4, lo="lo_", hi="hi_")


# Mining: `None` neighbours are every pair, "bins" as many as intervals

_MINED = (
    ("W4", 5, 5, "inherited", True), ("W2", 5, 5, "inherited", True), ("W5", 5, 5, "all", True), ("W6", 5, 5, "inherited", True), ("W7", 5, 5, "inherited", True), ("W9", "sqrt", 8, "inherited", True),
    ("W10", 5, None, "all", True), ("W1", 5, 5, "inherited", True), ("W5", "sqrt", "bins", "inherited", True), ("W10", "sqrt", "bins", "inherited", True),
    ("W1", "sqrt", "bins", "inherited", False), ("W2", "sqrt", "bins", "inherited", False), ("W3", "sqrt", "bins", "inherited", False), ("W4", "sqrt", "bins", "inherited", False),
    ("W6", "sqrt", "bins", "inherited", False), ("W7", "sqrt", "bins", "inherited", False), ("W8", 5, 5, "inherited", False), ("W8", "sqrt", "bins", "inherited", False),
    ("W11", 5, 5, "inherited", False), ("W11", "sqrt", "bins", "inherited", False), ("W12", "sqrt", "bins", "inherited", False),
)


def _mined(spark, sf, w, b, k, scope="inherited", **options):
    df, g = setup(spark, sf, w, b)
    return miner.mine(df, W.attrs(w), grid=g, k=E.limit_of(g) if k == "bins" else k, candidate_scope=scope, **options)


for _w, _b, _k, _s, _sql in _MINED:
    _sql_k = "(SELECT max(nb) FROM g)" if _k == "bins" else _k

    @query(f"mine_{_w.lower()}_{_b}", O.mined(_w, _b, _sql_k, _s) if _sql else None)
    def _(spark, sf, w=_w, b=_b, k=_k, s=_s):
        return rounded(flat(_mined(spark, sf, w, b, k, s).boxes, len(W.attrs(w)), lo="lo_", hi="hi_"))

    if _w not in ("W8", "W11"):

        @query(f"mine_cover_{_w.lower()}_{_b}", O.partition(_w, _b))
        def _(spark, sf, w=_w, b=_b, k=_k, s=_s):
            found = _mined(spark, sf, w, b, k, s)
            return measures.cover_is_partition(found.boxes, found.lineage, found.cells)

    if _sql:

        @query(f"ledger_{_w.lower()}_{_b}", O.ledger(_w, _b, _sql_k, _s))
        def _(spark, sf, w=_w, b=_b, k=_k, s=_s):
            return rounded(_mined(spark, sf, w, b, k, s, prune_when="never").ledger)


for _w, _k in (("W6", 5), ("W7", 5), ("W1", 5)):

    @query(f"matching_round_{_w.lower()}_5", O.first_round(_w, 5, _k))
    def _(spark, sf, w=_w, k=_k):
        """The first round's accepted merges, by distributed matching."""
        c, g = cell_table(spark, sf, w, 5)
        t = c.agg(F.count(F.lit(1)).alias("k"), F.sum("usage").alias("n")).first()
        pairs = neighbors.edges(neighbors.knn(c, k, len(g.axes)))
        weighted = candidates.weighted(pairs, miner.starting_boxes(c), codes.EPS).select("a", "b", "w")
        return rounded(matching.accepted(matching.greedy_matching(weighted), t.k, t.n, g, codes.EPS, "plugin", "refreshed", t.k + 1).withColumn("step", F.col("step").cast("int")))


@query("mine_interaction_grid_w7")
def _(spark, sf):
    df = W.load(spark, sf, "W7")
    g = grid.interaction_preserving(df, W.attrs("W7"))
    return flat(miner.mine(df, W.attrs("W7"), grid=g, k=E.limit_of(g)).boxes, 4, lo="lo_", hi="hi_")


@query("mine_describe_w6")
def _(spark, sf):
    found = _mined(spark, sf, "W6", 5, 5)
    return found.describe(W.load(spark, sf, "W6")).select("pid", "usage", "support", "intervals", "majority", "accuracy")


@query("describe_interaction_grids")
def _(spark, sf):
    """The description table's third grid."""
    out = None
    for w in ("W4", "W5", "W6", "W7", "W9"):
        df = W.load(spark, sf, w)
        one = measures.describe(df, W.attrs(w), grid.interaction_preserving(df, W.attrs(w)), "label").select(F.lit(w).alias("workload"), "*")
        out = one if out is None else out.unionByName(one)
    return out


# Experiments

QUERIES["experiment_layouts"] = E.layouts
QUERIES["experiment_compression"] = E.compression
QUERIES["experiment_neighbours"] = E.neighbours
QUERIES["experiment_complexity"] = E.complexity
for _w in ("W4", "W5", "W6", "W7", "W9"):
    QUERIES[f"experiment_methods_{_w.lower()}"] = lambda spark, sf, w=_w: E.methods(spark, sf, w)
for _w in ("W6", "W7"):
    QUERIES[f"experiment_settings_{_w.lower()}"] = lambda spark, sf, w=_w: E.settings(spark, sf, w)


# Relational operations around mining


@query("marginals_w6", O.marginals("W6", 5))
def _(spark, sf):
    df, g = setup(spark, sf, "W6", 5)
    return around.marginals(cells.discretise(df, g))


@query("label_totals_w7", O.label_totals("W7", 5))
def _(spark, sf):
    df, g = setup(spark, sf, "W7", 5)
    return around.label_totals(cells.discretise(df, g, ["label"]), "b_0", "label")


@query("cell_forecast_w6", O.forecast("W6", "sqrt"))
def _(spark, sf):
    """Whether the forecast is within a tenth of the number of cells."""
    df, g = setup(spark, sf, "W6", "sqrt")
    disc = cells.discretise(df, g)
    exact = cells.counts(disc).agg(F.count(F.lit(1)).alias("exact"))
    return around.cell_forecast(disc).crossJoin(exact).select("exact", (F.abs(F.col("cells") - F.col("exact")) <= F.col("exact") / 10).alias("near"))


@query("as_of_versions", O.AS_OF)
def _(spark, sf):
    """Every event of a user with the last purchase of that user at or before it."""
    events = W.table(spark, sf, "events").select("event_id", "user_id", "ts", "event_type")
    versions = events.filter("event_type = 'purchase'").groupBy("user_id", "ts").agg(F.max("event_id").alias("last_purchase"))
    return around.as_of(events.select("event_id", "user_id", "ts"), versions, "ts", "user_id", ("last_purchase",)).select("event_id", "last_purchase")


@query("compare_runs_w4", O.compare("W4", 5, 4))
def _(spark, sf):
    """Cells of two grids, held against each other as multisets."""
    one, other = (cell_table(spark, sf, "W4", b)[0].select(F.element_at("lo", 1).alias("b_0"), F.element_at("lo", 2).alias("b_1")) for b in (5, 4))
    return around.compare(one, other)


@query("equal_height_rows_w3", O.ntile("W3", 0, 16))
def _(spark, sf):
    return around.equal_height_rows(W.load(spark, sf, "W3"), "o_totalprice", 16, ("obj_id",))


# Streaming twins


@query("window_cells_daily", O.window_cells(5))
def _(spark, sf):
    df, g = setup(spark, sf, "W6", 5)
    events = df.withColumn("at", F.timestamp_seconds("ts"))
    names = ["b_0", "b_1", "b_2"]
    counts = events.select("at", *g.indices()).groupBy(F.window("at", "1 day").alias("w"), *names).agg(F.count(F.lit(1)).alias("usage"))
    return counts.select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), *names, "usage")


@query("online_bits_by_user", O.online_bits(5))
def _(spark, sf):
    df, g = setup(spark, sf, "W6", 5)
    c, _g = cell_table(spark, sf, "W6", 5)
    events = W.table(spark, sf, "events").select("event_id", "user_id", F.col("ts").alias("at"))
    spot = F.array(*[f"b_{i}" for i in range(3)])
    scored = cells.discretise(df, g, ["obj_id"]).select(F.col("obj_id").alias("event_id"), spot.alias("lo")).join(c.select("lo", F.col("cell_id").alias("pid")), "lo").join(events, "event_id")
    steps = streaming.online_bits_batch(scored.withColumnRenamed("at", "ts"), "user_id", c.count())
    return steps.groupBy("stream_key").agg(F.count(F.lit(1)).alias("events"), F.round(F.sum("bits"), 5).alias("bits"))
