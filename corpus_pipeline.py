"""A corpus through quality classifier, quality rules, near-duplicate removal and packing.

All stages take nulls in any column, repeated rows, an empty table and further columns of any name; the first
three return the columns that they were given. Null and empty texts have no words: the classifier keeps them, as
it does whatever it knows nothing of, and the rules then reject them.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from calib.llm import near_dups, packing, rules, weak_labels
from calib.llm.queries import vocabulary
from calib.llm.shared import drop_tables, materialize, read_table
from calib.session import shipped


@shipped
def quality_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents that the scorer does not reject, by their whole texts."""
    return weak_labels.keep_good(spark, docs)


@shipped
def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents that pass base and thresholds."""
    return rules.keep_good(spark, docs)


@shipped
def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates, that of the least doc_id; rows with one doc_id go or stay together."""
    return near_dups.keep_one_of_each(spark, docs)


@shipped
def best_fit_packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents with their places in sequences."""
    return packing.pack_documents(docs, vocabulary("byte_bpe_50k.json"))


#: Each takes (spark, docs, sf_dir); its result is written and read again as the docs of the next.
STAGES = [
    ("quality_classifier", quality_classifier),
    ("quality_rules", quality_rules),
    ("near_duplicates", near_duplicates),
    ("best_fit_packing", best_fit_packing),
]
#: SQL can express neither a trained classifier nor signatures and tokenizers; tests/llm compares with brute force.
ORACLE_SQL = None


@shipped
def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The packed pieces of what the first three stages leave of `documents`. A stage's table is deleted after the next one's."""
    docs, before = read_table(spark, sf_dir, "documents"), []
    for name, stage in STAGES[:-1]:
        made: list[str] = []
        docs = materialize(stage(spark, docs, sf_dir), name, made)
        drop_tables(spark, before)
        before = made
    return STAGES[-1][1](spark, docs, sf_dir)
