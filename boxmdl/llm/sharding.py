"""Contiguous shards of near-equal byte size, from global prefix sums.

The rows are range-partitioned by their order columns and fixed by a reliable
checkpoint (so that totals and prefixes see the same partitions).  Each
partition gives one total; the running sum of those few totals, added to the
running sum inside a partition, is the global prefix.  A row belongs to the
shard that holds the middle of its own byte range, so every shard boundary
lies within half a row of an equal target.  Only DataFrame functions are used.

Edge cases: a null text counts 0 bytes; rows without an order value come last;
tied or repeated rows keep one order each, fixed by the checkpoint; an empty
table gives no rows; extra columns are carried along untouched, and helper
columns have names with a leading "__".
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import checkpointed

#: What a row costs besides its text.
ROW_BYTES = 16
N_SHARDS = 40


def with_global_prefix(df: DataFrame, size: str, order: list, partitions: int | None = None) -> DataFrame:
    """Rows in global order with ``__row`` (number from 0), ``__before`` (sum of `size` over earlier rows) and ``__total`` (sum over all)."""
    ranged = df.repartitionByRange(partitions, *order) if partitions else df.repartitionByRange(*order)
    fixed = checkpointed(ranged.sortWithinPartitions(*order))
    local = fixed.withColumns({"__part": F.spark_partition_id(), "__at": F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))})
    ahead = Window.orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)
    totals = (
        local.groupBy("__part")
        .agg(F.sum(size).alias("__sum"), F.count(F.lit(1)).alias("__n"))
        .withColumns({
            "__sum_ahead": F.coalesce(F.sum("__sum").over(ahead), F.lit(0)),
            "__n_ahead": F.coalesce(F.sum("__n").over(ahead), F.lit(0)),
            "__total": F.sum("__sum").over(Window.partitionBy(F.lit(0))),
        })
    )
    inside = Window.partitionBy("__part").orderBy("__at").rowsBetween(Window.unboundedPreceding, -1)
    return (
        local.withColumn("__local", F.coalesce(F.sum(size).over(inside), F.lit(0)))
        .join(F.broadcast(totals), "__part")  # one row per partition of the shuffle above
        .withColumns({"__row": F.col("__n_ahead") + F.col("__at"), "__before": F.col("__sum_ahead") + F.col("__local")})
        .drop("__part", "__at", "__sum", "__n", "__local", "__sum_ahead", "__n_ahead")
    )


def shard(df: DataFrame, size: str, order: list, n_shards: int = N_SHARDS) -> DataFrame:
    """`df` with ``shard`` (0 to n_shards - 1, contiguous in `order`) and ``slot`` (row number in the shard from 0).

    With no bytes at all, everything is in shard 0.
    """
    placed = with_global_prefix(df, size, order).withColumn(
        "shard",
        F.when(F.col("__total") > 0, F.least(F.lit(n_shards - 1), F.expr(f"(2 * __before + {size}) * {n_shards} div (2 * __total)"))).otherwise(0).cast("int"),
    )
    first = placed.groupBy("shard").agg(F.min("__row").alias("__first"))
    return placed.join(F.broadcast(first), "shard").withColumn("slot", F.col("__row") - F.col("__first")).drop("__first", "__row", "__before", "__total")


def op4_prefix_sum_shards(spark, sf_dir) -> DataFrame:
    """Shards of all documents in order of doc_id, with the digest of each text."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    slim = docs.select(
        "doc_id",
        (F.coalesce(F.octet_length("text"), F.lit(0)) + ROW_BYTES).cast("long").alias("size"),
        F.crc32(F.coalesce("text", F.lit("")).cast("binary")).alias("text_crc32"),
    )
    out = shard(slim, "size", [F.col("doc_id").asc_nulls_last(), F.col("text_crc32"), F.col("size")])
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
