"""Feature views of the given tables: ``obj_id``, numeric attributes, and a ``label`` that mining never reads."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import table


@dataclass(frozen=True)
class Workload:
    attrs: tuple[str, ...]
    label: str | None
    select: object  # (spark, sf_dir) -> DataFrame with the attributes and the label


def epoch(column: str):
    """Seconds since 1970 of a timestamp without zone, read as UTC."""
    return F.timestamp_diff("SECOND", F.lit("1970-01-01 00:00:00").cast("timestamp_ntz"), F.col(column)).cast("double")


def _num(name: str):
    return F.col(name).cast("double").alias(name)


def _lineitem(spark, sf, attrs, label):
    shipped = epoch("l_shipdate").alias("l_shipdate")
    return table(spark, sf, "lineitem").select(*[shipped if a == "l_shipdate" else _num(a) for a in attrs], F.col(label).alias("label"))


def _orders(spark, sf):
    return table(spark, sf, "orders").select(F.col("o_orderkey").alias("obj_id"), _num("o_totalprice"), epoch("o_orderdate").alias("o_orderdate"), F.col("o_orderstatus").alias("label"))


def _part(spark, sf):
    return table(spark, sf, "part").select(F.col("p_partkey").alias("obj_id"), _num("p_size"), _num("p_retailprice"), F.col("p_brand").alias("label"))


def _customer(spark, sf):
    return table(spark, sf, "customer").select(F.col("c_custkey").alias("obj_id"), _num("c_acctbal"), _num("c_nationkey"), F.col("c_mktsegment").alias("label"))


def _events(spark, sf):
    return table(spark, sf, "events").select(F.col("event_id").alias("obj_id"), _num("value"), epoch("ts").alias("ts"), F.get_json_object("props", "$.k").cast("double").alias("k"), F.col("event_type").alias("label"))


def _embeddings(spark, sf, size):
    return table(spark, sf, "embeddings").select(F.col("vec_id").alias("obj_id"), *[F.element_at("embedding", i).cast("double").alias(f"e{i}") for i in range(1, size + 1)], F.col("label").cast("string").alias("label"))


def _documents(spark, sf):
    text = F.coalesce("text", F.lit(""))
    words = F.filter(F.split(F.lower(text), " "), lambda w: w != "")
    docs = table(spark, sf, "documents").select("doc_id", _num("n_chars"), (F.length(text) - F.length(F.replace(text, F.lit(" "), F.lit("")))).cast("double").alias("spaces"), F.size(F.array_distinct(words)).cast("double").alias("words"))
    return docs.join(table(spark, sf, "labels"), "doc_id").select(F.col("doc_id").alias("obj_id"), "n_chars", "spaces", "words", F.col("quality").cast("string").alias("label"))


def _supplier(spark, sf):
    nation = F.broadcast(table(spark, sf, "nation"))  # 25 rows at every scale
    return table(spark, sf, "supplier").join(nation, F.col("s_nationkey") == F.col("n_nationkey")).select(F.col("s_suppkey").alias("obj_id"), _num("s_acctbal"), _num("s_nationkey"), F.col("n_regionkey").cast("string").alias("label"))


def _pages(spark, sf):
    return table(spark, sf, "pages").select(F.col("page_id").alias("obj_id"), F.length("html").cast("double").alias("html_length"), F.regexp_count("html", F.lit("<[A-Za-z]")).cast("double").alias("tags"), (F.size(F.split("url", "/")) - 3).cast("double").alias("url_depth"), F.lit(None).cast("string").alias("label"))


def _conversations(spark, sf):
    return table(spark, sf, "conversations").select(_num("turn"), F.length("text").cast("double").alias("text_length"), F.col("role").alias("label"))


_L1, _L2 = ("l_quantity", "l_extendedprice", "l_discount", "l_tax"), ("l_extendedprice", "l_shipdate")
_E = lambda size: tuple(f"e{i}" for i in range(1, size + 1))

WORKLOADS = {
    "W1": Workload(_L1, "label", lambda s, d: _lineitem(s, d, _L1, "l_returnflag")),
    "W2": Workload(_L2, "label", lambda s, d: _lineitem(s, d, _L2, "l_linestatus")),
    "W3": Workload(("o_totalprice", "o_orderdate"), "label", _orders),
    "W4": Workload(("p_size", "p_retailprice"), "label", _part),
    "W5": Workload(("c_acctbal", "c_nationkey"), "label", _customer),
    "W6": Workload(("value", "ts", "k"), "label", _events),
    "W7": Workload(_E(4), "label", lambda s, d: _embeddings(s, d, 4)),
    "W8": Workload(_E(64), "label", lambda s, d: _embeddings(s, d, 64)),
    "W9": Workload(("n_chars", "spaces", "words"), "label", _documents),
    "W10": Workload(("s_acctbal", "s_nationkey"), "label", _supplier),
    "W11": Workload(("html_length", "tags", "url_depth"), None, _pages),
    "W12": Workload(("turn", "text_length"), "label", _conversations),
}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return WORKLOADS[name].select(spark, sf_dir)


def attrs(name: str) -> list[str]:
    return list(WORKLOADS[name].attrs)


# Planted boxes: ((x0, x1), (y0, y1)) in the unit square, and the rows of each as a share of m.
LAYOUTS: dict[str, list[tuple[tuple[float, float], tuple[float, float], float]]] = {
    "Y1": [((0.05, 0.25), (0.05, 0.35), 1), ((0.40, 0.60), (0.10, 0.30), 1), ((0.70, 0.95), (0.60, 0.90), 1), ((0.10, 0.30), (0.65, 0.95), 1)],
    "Y2": [((0.1, 0.3), (0.1, 0.3), 1), ((0.3, 0.9), (0.1, 0.3), 1), ((0.1, 0.3), (0.3, 0.9), 1), ((0.3, 0.9), (0.3, 0.9), 1)],
    "Y2e": [((0.1, 0.4), (0.1, 0.5), 1), ((0.4, 0.7), (0.1, 0.5), 1), ((0.1, 0.4), (0.5, 0.9), 1), ((0.4, 0.9), (0.5, 0.9), 1)],
    "Y3": [((0.35, 0.65), (0.35, 0.65), 0.1), ((0.05, 0.95), (0.05, 0.35), 1), ((0.05, 0.95), (0.65, 0.95), 1), ((0.05, 0.35), (0.35, 0.65), 1), ((0.65, 0.95), (0.35, 0.65), 1)],
    "Y4": [((0.1, 0.5), (0.1, 0.5), 1), ((0.35, 0.8), (0.35, 0.8), 1), ((0.65, 0.95), (0.05, 0.45), 1)],
    "Y5": [((0.1, 0.9), (0.1, 0.9), 1), ((0.3, 0.5), (0.3, 0.5), 1)],
    "Y6": [((0.05, 0.95), (0.05, 0.95), 1), ((0.15, 0.6), (0.15, 0.6), 1), ((0.25, 0.4), (0.25, 0.4), 1), ((0.65, 0.9), (0.6, 0.9), 1)],
}
OBJECTS = (100, 200, 500, 700, 1000)


def slices(name: str, m: int) -> list[tuple[int, int]]:
    """First and last row number (from 1) of each planted box."""
    out, at = [], 0
    for _, _, share in LAYOUTS[name]:
        rows = int(m * share)
        out.append((at + 1, at + rows))
        at += rows
    return out


def layout(spark: SparkSession, sf_dir: str, name: str, m: int) -> DataFrame:
    """``obj_id, x, y, tid``: points of the planted boxes, placed by two flat columns of `lineitem` in the order of its unique key."""
    rows = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", _num("l_extendedprice"), epoch("l_shipdate").alias("s"))
    ends = rows.agg(F.min("l_extendedprice").alias("p0"), F.max("l_extendedprice").alias("p1"), F.min("s").alias("s0"), F.max("s").alias("s1"))
    parts = slices(name, m)
    order = ["l_orderkey", "l_linenumber", "l_extendedprice"]
    # a few thousand rows at every scale: the layout's size is the feature
    head = rows.orderBy(*order).limit(parts[-1][1]).withColumn("obj_id", F.row_number().over(Window.orderBy(*order)).cast("long"))
    unit = head.crossJoin(F.broadcast(ends)).select("obj_id", ((F.col("l_extendedprice") - F.col("p0")) / (F.col("p1") - F.col("p0"))).alias("u"), ((F.col("s") - F.col("s0")) / (F.col("s1") - F.col("s0"))).alias("v"))
    x = y = tid = F.lit(None)
    for t, ((first, last), ((x0, x1), (y0, y1), _)) in enumerate(zip(parts, LAYOUTS[name], strict=True), 1):
        here = F.col("obj_id").between(first, last)
        x = F.when(here, F.lit(x0) + F.col("u") * (F.lit(x1) - F.lit(x0))).otherwise(x)
        y = F.when(here, F.lit(y0) + F.col("v") * (F.lit(y1) - F.lit(y0))).otherwise(y)
        tid = F.when(here, F.lit(t)).otherwise(tid)
    return unit.select("obj_id", x.cast("double").alias("x"), y.cast("double").alias("y"), tid.cast("long").alias("tid"))


def truth(spark: SparkSession, name: str) -> DataFrame:
    """``tid, rlo, rhi`` of the planted boxes."""
    rows = [(t, [x[0], y[0]], [x[1], y[1]]) for t, (x, y, _) in enumerate(LAYOUTS[name], 1)]
    return spark.createDataFrame(rows, "tid long, rlo array<double>, rhi array<double>")
