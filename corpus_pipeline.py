"""The corpus pipeline: quality classifier, line dedup, near-dedup, decontamination, packing.

Every stage takes (spark, docs, sf_dir) and works on all that its predecessor kept, written as Parquet in the shared
folder and read again, so no stage is computed twice; all but the last return the columns of documents. Stages that
only filter decide next to the text and shuffle no text.

Defined results of all stages: an empty table gives no rows; columns of docs beside doc_id and text, whatever their names, are
carried along. Nulls, ties, repeated rows and long texts: see each stage and the operator's module.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from robustcenters.llm import cotraining, decontamination, line_dedup, packing, simhash
from robustcenters.llm.common import written


def keep_good_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the co-trained classifier does not reject.

    Null metadata are a value of their own, a null text is an empty one; repeated rows get one verdict.
    """
    return cotraining.keep_good(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def drop_recurring_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the lines of templates that an earlier document has; every document stays, if with an empty text.

    A null text stays null; a null doc_id is earlier than all others; repeated rows with one doc_id count as one document.
    """
    return line_dedup.drop_recurring_lines(docs)


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the smallest id of each group of near-duplicates (five-word shingles, similarity 0.8).

    Null and wordless texts are one group; a null doc_id comes last; of repeated rows one stays.
    """
    return simhash.keep_one_similar(docs)


def drop_leaked(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a benchmark item; null texts and items match nothing, repeated rows get one verdict."""
    return decontamination.drop_leaked(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Planned places of all pieces in sequences; a null text is its end id alone, repeated rows are packed each."""
    return packing.pack_documents(docs)


STAGES = [
    ("quality classifier", keep_good_quality),
    ("line dedup", drop_recurring_lines),
    ("simhash near-dedup", one_of_each_group),
    ("benchmark decontamination", drop_leaked),
    ("best-fit packing", pack),
]
#: Trained models and iteration are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
