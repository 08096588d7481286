"""A corpus pipeline: toxic documents go, one document of each group of near
duplicates stays, contaminated documents go, sources are mixed to their target
weights, and what is left is dealt to shards.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame that is written
as Parquet and read again as the next stage's docs.

Defined cases: null and empty texts are documents like any other (without words
they are not toxic by any word, and near copies of each other); documents
without an id stay in near_dedup; repeated rows are judged alike, and each has
copies of its own; an empty table stays empty. All stages but the last return
the columns they got.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from spreadmax.llm.common import table
from spreadmax.llm.decontaminate import decontaminate
from spreadmax.llm.mixing import mix
from spreadmax.llm.sharding import shard_documents
from spreadmax.llm.simhash import one_of_each
from spreadmax.llm.toxicity import drop_toxic
from spreadmax.session import written


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return drop_toxic(docs, table(spark, sf_dir, "labels"))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return one_of_each(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate(docs, table(spark, sf_dir, "benchmark"))


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mix(docs)


def sharding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return shard_documents(docs)


STAGES = [
    ("toxicity", toxicity),
    ("near_dedup", near_dedup),
    ("decontamination", decontamination),
    ("mixing", mixing),
    ("sharding", sharding),
]

#: A trained classifier and iterative joins have no SQL form; tests hold run() against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
