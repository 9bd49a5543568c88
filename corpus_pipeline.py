"""A corpus pipeline of five stages over documents: quality, near copies, benchmark leaks, mixing, sharding.

Each stage takes (spark, docs, sf_dir) and works on all that the one before it kept; its result is written as Parquet in the
shared folder and read again, so a lost executor never costs more than a stage.

Odd input, in every stage: a null text counts as empty; a null doc_id is a row like any other, told apart by its text; very long
texts are read whole; rows that repeat an id with another text are documents of their own, and rows equal in id and text are copies
(one stays in near_copies); ties go to the least doc_id, then to the least text hash; an empty table gives an empty table with the
same columns; other columns stay as they are, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fadestream.llm.common import documents, stored
from fadestream.llm.mixing import mixed
from fadestream.llm.quality import reject_low_quality
from fadestream.llm.sharding import shard
from fadestream.llm.simhash import drop_near_duplicates
from fadestream.llm.winnowing import drop_contaminated

#: Shards of the result; share of the tokens that the mixture takes.
SHARDS, SHARE = 16, 0.8


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose score reaches the cut; the rest goes. All rows stay if the labels don't have both classes."""
    return reject_low_quality(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies: least doc_id (null last), then least text hash. Texts without words are copies of each other."""
    return drop_near_duplicates(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no window of a benchmark item; a text without words holds none."""
    return drop_contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the hierarchical budget takes, each once at most; null language and source are nodes of their own."""
    return mixed(docs, share=SHARE)


def sharding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents with size, text_crc32, shard and slot; columns of these names are replaced."""
    return shard(docs, SHARDS)


STAGES = [("quality", quality), ("near_copies", near_copies), ("decontamination", decontamination), ("mixing", mixing), ("sharding", sharding)]

#: Fingerprints, fitted scores and winnowing have no SQL form; tests compare the stages with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for name, stage in STAGES:
        docs = stored(stage(spark, docs, sf_dir), f"stage-{name}")
    return docs
