"""The corpus pipeline: quality, exact dedup, near dedup, mix, packing. Each stage is written and read again."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from rangesieve.llm.common import materialise, read_table
from rangesieve.llm.exact_dedup import keep_first_copies
from rangesieve.llm.jaccard_join import keep_one_of_each
from rangesieve.llm.packing import pack_documents
from rangesieve.llm.rule_quality import keep_good
from rangesieve.llm.source_mix import mix_documents


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return keep_good(docs, read_table(spark, sf_dir, "labels"))


def exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return keep_first_copies(docs)


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return keep_one_of_each(docs)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mix_documents(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    # Python workers outlive their stage; a smaller word cache leaves the other stages their memory.
    return pack_documents(docs, cached_words=200_000)


STAGES = [("quality", quality), ("exact_dedup", exact), ("near_dedup", near), ("mix", mix), ("pack", pack)]

#: The classifier and the tokenizer can't be told in SQL. The tests hold quality against labels, and all that follows it
#: against plain Python: near_dedup and mix alone, and run() from what the classifier kept, with the pieces' ids.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
