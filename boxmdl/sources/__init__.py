"""Readers: the given tables, other formats, streams; and the feature views made from them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read(spark: SparkSession, fmt: str, path: str | None = None, schema=None, **options) -> DataFrame:
    """Any batch format; give a schema at scale, inference reads everything once more."""
    reader = spark.read.format(fmt).options(**options)
    if schema is not None:
        reader = reader.schema(schema)
    return reader.load(path) if path else reader.load()


def register_all(spark: SparkSession, sf_dir: str) -> None:
    """The tables as SQL views."""
    for name in TABLES:
        table(spark, sf_dir, name).createOrReplaceTempView(name)


def event_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """The events at `path` (Parquet files) as a stream with event time in ``ts`` (timestamp)."""
    schema = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return stream.withColumn("ts", stream["ts"].cast("timestamp"))
