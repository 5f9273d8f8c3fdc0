"""A training-corpus pipeline: five stages, each one of the corpus operators.

Every stage works on all rows that its predecessor kept, and is written as
Parquet into the shared folder and read again before the next.  All but the
last return the columns of `documents`; the last returns packed pieces.

Edge cases, by stage: a null or empty text is clean, has no near-duplicate and
no repeat, counts no words in the mix and is packed as its closing token alone;
rows that repeat an id and a text are one document from the second stage on;
of documents with equal texts the one of the least id stays; rows without an
id are kept apart from each other unless their texts are alike; very long texts
are cut into pieces only when packed; extra columns, whatever their names, are
carried to the mix; an empty table gives no rows at any stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from boxmdl.llm import mixing, neardup, packing, suffix_dedup, toxicity
from boxmdl.llm.common import documents, stored, word_count


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the clause grammar scores below the threshold; the grammar is learned from labelled documents of the training part."""
    return toxicity.without_toxic(docs, toxicity.learn(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of every group of near-duplicates: the one of the least id."""
    return neardup.without_near_duplicates(docs)


def cut_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the byte strings that occur more than once."""
    return suffix_dedup.without_repeats(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Whole documents of the sources in their target shares: some repeated, some left out."""
    sized = docs.withColumn("__size", word_count("text"))
    return mixing.mix(sized, "__size").drop("__size")


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token sequences: a row for each piece, with its ids."""
    return packing.pack(docs).withColumn("ids_crc32", F.crc32("ids"))


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_duplicates),
    ("suffix_dedup", cut_repeats),
    ("mixing", mix_sources),
    ("packing", pack_sequences),
]

#: Learned scores and token ids are beyond SQL; tests/llm/test_pipeline.py holds the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The pieces that the five stages make of `documents`."""
    docs = documents(spark, sf_dir)
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = stored(docs, name)
    return docs
