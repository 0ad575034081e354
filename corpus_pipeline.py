"""From raw documents to token files: five stages, each one operator of batchfeed.llm.

A stage takes (spark, docs, sf_dir) and returns a DataFrame; `run` writes each result
as Parquet into the shared folder and hands it, read again, to the next stage. All but
the last stage return the columns of docs, whatever else these are called.

Edge cases: null and empty texts fail the quality rules, and so never reach the others;
without labels fixed line rules decide; of equal rows and of rows of one doc_id and text
one stays, rows of one doc_id with other texts are documents of their own; an empty
benchmark contaminates nothing; a null source is a source; documents are written in
ascending doc_id order, null first, a repeated one as often as the mix takes it; an
empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from batchfeed.llm import decontaminate, mixing, quality_rules, simhash, token_files
from batchfeed.llm.common import new_path, scratch, table, written
from batchfeed.llm.queries import vocabulary_path


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop the documents that the quality rules reject."""
    return quality_rules.keep_good(docs, quality_rules.train(docs, table(spark, sf_dir, "labels", "doc_id", "quality")))


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep the document with the smallest doc_id of each group of near copies."""
    return simhash.keep_first(docs)


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop the documents that hold too much of a benchmark."""
    return decontaminate.keep_clean(docs, table(spark, sf_dir, "benchmark", "item_id", "text"))


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Leave out and repeat documents so that the sources meet their targets."""
    return mixing.mix(docs, keep_columns=True)


def token_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Write the token files and return what is read back from them."""
    return token_files.round_trip(docs, vocabulary_path())


STAGES = [
    ("quality_rules", quality_stage),
    ("near_duplicates", near_duplicate_stage),
    ("decontamination", decontamination_stage),
    ("mixing", mixing_stage),
    ("token_files", token_stage),
]

ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents table; what a stage stored on its way is removed once its result is written."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        with scratch(spark) as keep:
            path = new_path(spark, name)
            keep(path)
            docs = written(stage(spark, docs, sf_dir), name, path)
    return docs
