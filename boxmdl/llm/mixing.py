"""Mixing sources to target weights by weighted fair queueing.

Every source has a weight; its target is its weight's share of all tokens, but
at most `max_repeat` times what it holds, the excess going to the other
sources by weight (one water level for all).  The documents of a source are
shuffled by a digest of their id and served again from the start when the
target exceeds the source.  A served copy's virtual finish time is the tokens
its source has served up to its end, divided by the source's target, so at
time 1 the whole budget is served.  The copies are range-sorted by finish time
and cut off at time 1; the copy that is being served then is cut there.

Running sums are taken in two steps, within digest buckets of a source and
over the buckets' totals; with as many buckets as a bucket has rows, neither
step grows faster than the root of the source, and a source that holds most
rows is dealt out over many tasks.  The sources themselves are ranked and
summed up by one window while they are few, and through range partitions and
their totals (`sharding.with_global_prefix`) when they are many, as where every
host is a source.  Only DataFrame functions are used.

Edge cases: a null text or source counts as size 0 and as a source of its own,
last in order; documents of size 0 take nothing; repeated rows are separate
documents; a table without words has targets of 0; an empty table gives no
rows; extra columns are kept, and helper columns have names with "__".
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import documents, stored, word_count
from .sharding import with_global_prefix

#: Weights of the sources in their order, repeated.
WEIGHTS = (5, 2, 1)
MAX_REPEAT = 3
#: Sources (some 100 bytes each) up to which one task ranks them and their plan is sent to every task.
BROADCAST_SOURCES = 100_000


def source_targets(sizes: DataFrame, weights=WEIGHTS, max_repeat: int = MAX_REPEAT, many: bool = False) -> DataFrame:
    """Targets of the sources in `sizes` (``__null``, ``__src``, ``source_size``): its rows with ``weight`` and ``target``.

    In order of cap per weight, the first k sources are capped and the others
    share what is left by weight; k is the smallest number for which the next
    source stays within its cap.  many: rank and sum in many tasks, with the
    same result (to the last bit where weights are whole numbers).
    """
    names = sizes.columns
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.pmod("__nth", F.lit(len(weights))) + 1).cast("int"))
    if many:
        ranked = with_global_prefix(sizes.withColumn("__one", F.lit(1)), "__one", ["__null", "__src"]).withColumn("__nth", F.col("__row")).drop("__one", "__row", "__before", "__total")
    else:
        ranked = sizes.withColumn("__nth", F.row_number().over(Window.orderBy("__null", "__src")) - 1)
    ranked = ranked.withColumn("weight", weight).withColumn("__cap", max_repeat * F.col("source_size").cast("double"))
    ranked = ranked.withColumn("__ratio", F.col("__cap") / F.col("weight"))
    order = ["__ratio", "__null", "__src"]
    if many:
        for c in ("__cap", "weight"):
            ranked = with_global_prefix(ranked, c, order).withColumn(f"{c}_before", F.col("__before").cast("double")).drop("__row", "__before", "__total")
        whole = ranked.agg(F.sum("source_size").alias("size"), F.sum("weight").alias("weight")).first()
        all_size, all_weight = F.lit(whole.size), F.lit(whole.weight)
    else:
        ahead, everything = Window.orderBy(*order).rowsBetween(Window.unboundedPreceding, -1), Window.partitionBy(F.lit(0))
        ranked = ranked.withColumns({f"{c}_before": F.coalesce(F.sum(c).over(ahead), F.lit(0.0)) for c in ("__cap", "weight")})
        all_size, all_weight = F.sum("source_size").over(everything), F.sum("weight").over(everything)
    ranked = ranked.withColumn("__level", (all_size - F.col("__cap_before")) / (all_weight - F.col("weight_before")))
    least = F.min(F.when(F.col("__level") <= F.col("__ratio"), F.struct(*order, "__level")))
    water = F.lit(ranked.agg(least["__level"].alias("level")).first().level).cast("double") if many else least.over(everything)["__level"]
    return ranked.withColumn("target", F.least(F.col("__cap"), F.coalesce(water, F.lit(0.0)) * F.col("weight"))).select(*names, "weight", "target")


def serve(docs: DataFrame, size: str, id_col: str = "doc_id", source_col: str = "source", seed: str = "mix-1", weights=WEIGHTS, max_repeat: int = MAX_REPEAT) -> DataFrame:
    """One row per copy to be served, in order of virtual finish time, with ``epoch``, ``finish``, ``words`` (of this copy, served by time 1).

    Every document has the row of its first copy, even where no word of it is
    served; ``__key`` tells repeated rows apart.
    """
    rows = docs.withColumns({
        "__null": F.col(source_col).isNull(),
        "__src": F.coalesce(F.col(source_col).cast("string"), F.lit("")),
        "__mix": F.conv(F.substring(F.md5(F.concat(F.lit(seed + ":"), F.coalesce(F.col(id_col).cast("string"), F.lit(""))).cast("binary")), 1, 15), 16, 10).cast("long"),
    })
    buckets = F.ceil(F.sqrt(F.count(F.lit(1)).cast("double"))).cast("long")
    held = stored(rows.groupBy("__null", "__src").agg(F.sum(size).alias("source_size"), buckets.alias("__buckets")), "held")
    many = held.count() > BROADCAST_SOURCES
    plan = stored(source_targets(held, weights, max_repeat, many), "sources")
    if not many:  # beyond that, a join that Spark deals out by source
        plan = F.broadcast(plan)
    rows = rows.join(plan, ["__null", "__src"]).withColumn("__bucket", F.expr("__mix div ((1152921504606846976 + __buckets - 1) div __buckets)"))

    bucket = ["__null", "__src", "__bucket"]
    ahead = Window.partitionBy("__null", "__src").orderBy("__bucket").rowsBetween(Window.unboundedPreceding, -1)
    offsets = rows.groupBy(*bucket).agg(F.sum(size).alias("__sum")).withColumn("__ahead", F.coalesce(F.sum("__sum").over(ahead), F.lit(0))).drop("__sum")
    order = Window.partitionBy(*bucket).orderBy("__mix", F.col(id_col), F.col(size))
    rows = rows.withColumns({"__local": F.coalesce(F.sum(size).over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)), "__nth": F.row_number().over(order)})
    rows = rows.join(offsets, bucket).withColumn("__start", F.col("__ahead") + F.col("__local"))

    budget = F.floor(F.col("target") + 0.5).cast("long")
    last = F.when(F.col("source_size") > 0, F.least(F.lit(max_repeat - 1), F.expr("cast(floor(target + 0.5) as bigint) div source_size"))).otherwise(0)
    copies = rows.withColumn("epoch", F.explode(F.sequence(F.lit(0).cast("long"), last.cast("long"))))
    served = F.col("epoch") * F.col("source_size") + F.col("__start")
    copies = copies.withColumns({
        "words": F.greatest(F.lit(0), F.least(F.col(size), budget - served)).cast("long"),
        "finish": F.when(F.col("target") > 0, (served + F.col(size)) / F.col("target")).otherwise(F.lit(1.0)),
        "__key": F.struct(*bucket, "__nth"),
    })
    return copies.repartitionByRange(F.col("finish"), F.col("__mix")).sortWithinPartitions("finish", "__null", "__src", "__mix", "__nth")


def mix(docs: DataFrame, size: str, whole: bool = True, **options) -> DataFrame:
    """The mixed corpus: rows of `docs`, repeated as served, in the order of the mix.

    whole: a copy stays, uncut, if at least half of it is served by time 1
    (documents of size 0: once); otherwise any copy of which a word is served
    stays, with ``words``, the number of its leading words to use.
    """
    names = docs.columns
    copies = serve(docs, size, **options)
    if whole:
        return copies.filter(F.when(F.col(size) == 0, F.col("epoch") == 0).otherwise(2 * F.col("words") >= F.col(size))).select(*names)
    return copies.filter(F.col("words") > 0).select(*names, *(c for c in ("epoch", "finish", "words") if c not in names))


def op5_weighted_fair_mix(spark, sf_dir) -> DataFrame:
    """What the mix takes of every document, over all its copies."""
    slim = stored(documents(spark, sf_dir).select("doc_id", "source", word_count("text").alias("size")), "sizes")
    copies = serve(slim, "size")
    return copies.groupBy("__key", "doc_id", "source", "size", "source_size", "target").agg(F.sum("words").cast("long").alias("taken"), F.min("finish").alias("first_finish")).select(
        "doc_id", "size", F.col("source_size").cast("long").alias("source_size"), "target", "taken", "source", "first_finish"
    )


OP5_SQL = r"""
WITH d AS (
  SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size,
         ('0x' || substr(md5('mix-1:' || doc_id), 1, 15))::BIGINT AS h FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source),
r AS (SELECT *, CASE (row_number() OVER (ORDER BY source IS NULL, encode(source)) - 1) % 3 WHEN 0 THEN 5.0 WHEN 1 THEN 2.0 ELSE 1.0 END::DOUBLE AS weight,
             3.0::DOUBLE * source_size AS cap FROM s),
l AS (SELECT *, cap / weight AS ratio,
             (sum(source_size) OVER () - coalesce(sum(cap) OVER b, 0)) / (sum(weight) OVER () - coalesce(sum(weight) OVER b, 0)) AS level
      FROM r WINDOW b AS (ORDER BY cap / weight, source IS NULL, encode(source) ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
t AS (SELECT source, source_size, least(cap, weight * (SELECT coalesce(arg_min(level, ratio), 0) FROM l WHERE level <= ratio)) AS target FROM l),
p AS (SELECT d.*, t.source_size, t.target, floor(t.target + 0.5)::BIGINT AS budget,
             coalesce(sum(size) OVER (PARTITION BY d.source ORDER BY h, doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS start
      FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source)
SELECT doc_id, size, source_size, target,
       (size * (budget // greatest(source_size, 1)) + greatest(0, least(size, budget - (budget // greatest(source_size, 1)) * source_size - start)))::BIGINT AS taken,
       source, CASE WHEN target > 0 THEN (start + size) / target ELSE 1.0 END AS first_finish
FROM p
"""
