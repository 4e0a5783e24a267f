"""From raw documents to training shards: quality rules, near duplicates, decontamination, source mixing, sharding."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from rangesieve.llm.common import cut_lineage, table
from rangesieve.llm.decontamination import find_contamination
from rangesieve.llm.mixing import mixed
from rangesieve.llm.ngram_join import keep_one
from rangesieve.llm.quality import cleaned
from rangesieve.llm.sharding import shard_by_bytes


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality rules keep, without the lines above the limit."""
    return cleaned(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The smallest document of each group of near copies."""
    return keep_one(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold little or nothing of the benchmark."""
    return find_contamination(docs, table(spark, sf_dir, "benchmark")).where("not contaminated").select(*(f"`{c}`" for c in docs.columns))


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix of sources takes them."""
    return mixed(docs)


def sharding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents with their size, shard and slot."""
    return shard_by_bytes(docs, 8)


STAGES = [
    ("quality rules", quality),
    ("n-gram Jaccard join", near_duplicates),
    ("benchmark decontamination", decontamination),
    ("mixing sources", mixing),
    ("sharding", sharding),
]

#: Components, boilerplate counts and seeded mixing have no SQL; a brute-force version in the tests stands in.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = cut_lineage(docs)
    return docs
