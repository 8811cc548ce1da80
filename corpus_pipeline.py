"""A training-data pipeline of five corpus operators: documents in, packed pieces out.

Each stage is a function of (spark, docs, sf_dir). All but the last return rows of
docs with all columns; what a stage rejects is gone for the stages after it.

Defined results in every stage: an empty table gives an empty table; extra columns,
whatever their names, are kept as they are; nulls in columns other than doc_id and text
play no part; very long texts are read whole.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from tallgram.llm.common import bounded_batches, stored, table
from tallgram.llm.decontaminate import keep_uncontaminated
from tallgram.llm.language import keep_identified
from tallgram.llm.near_dups import keep_one_of_each_class
from tallgram.llm.packing import pack_documents
from tallgram.llm.toxicity import fit as fit_lexicon
from tallgram.llm.toxicity import keep_clean


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts in which no language can be told (null, empty, or no letters) go. Repeated rows are judged each, and alike."""
    bounded_batches(spark)
    return keep_identified(docs)


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts that score 0.5 or more by the lexicon learned from labels go.

    Null and empty texts have the score of no match and stay; equal texts go or stay
    together; without labels of both kinds nothing goes.
    """
    return keep_clean(docs, fit_lexicon(docs, table(spark, sf_dir, "labels")))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each class of copies and near copies the row with the smallest doc_id stays.

    Rows without a doc_id all stay; null texts are alone in their class; texts without
    words are copies of equal texts only; of repeated rows of one doc_id one stays.
    """
    bounded_batches(spark)
    return keep_one_of_each_class(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts that hold ten words in a row of a benchmark item (or a whole shorter item) go.

    Null and empty texts have no words and stay; items without words match nothing;
    repeated rows are judged each.
    """
    return keep_uncontaminated(docs, table(spark, sf_dir, "benchmark"))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces in sequences of 2048. Null and empty texts are the end token alone; repeated rows are packed each."""
    bounded_batches(spark)
    return pack_documents(docs)


STAGES = [("language", language), ("toxicity", toxicity), ("near_duplicates", near_duplicates), ("decontamination", decontamination), ("packing", packing)]

#: SQL has no form of the trained stages; tests compare each stage with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; what one returns is written to the shared folder and reread."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = stored(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
