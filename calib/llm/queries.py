"""The queries of this subpackage: each applies one operator, with production parameters, to its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from calib.llm.shared import read_table


def vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    from calib.llm.style_tree import extract

    return extract(read_table(spark, sf_dir, "pages"))


def op2_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from calib.llm.packing import pack_documents

    return pack_documents(read_table(spark, sf_dir, "documents"), vocabulary("byte_bpe_50k.json"))


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from calib.llm.rules import judge

    return judge(read_table(spark, sf_dir, "documents"))


def op4_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    from calib.llm.weak_labels import judge

    return judge(read_table(spark, sf_dir, "documents"))


def op5_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    from calib.llm.topk import search

    table = read_table(spark, sf_dir, "embeddings")
    return search(table, table.where("vec_id % 20 = 0"))


def op6_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from calib.llm.bpe_fold import digests, encode, read_ranks

    ranks = read_ranks(vocabulary("byte_bpe_multi_50k.tiktoken"))
    return digests(encode(read_table(spark, sf_dir, "documents"), public_tokenizers.PATTERN, ranks, decoded=True))


def op7_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    from calib.llm.url_filter import judge

    return judge(read_table(spark, sf_dir, "pages"))


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from calib.llm.toxicity import judge

    return judge(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"))


def op9_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    from calib.llm.near_dups import near_duplicates

    return near_duplicates(read_table(spark, sf_dir, "documents"))


def op10_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from calib.llm.token_counts import maintained

    return maintained(read_table(spark, sf_dir, "documents"), {"words_v1": None, "byte_bpe_50k_v1": vocabulary("byte_bpe_50k.json")})


def token_counts_of_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The part of op10 that SQL can express."""
    from calib.llm.token_counts import maintained

    return maintained(read_table(spark, sf_dir, "documents"), {"words_v1": None})


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {k: f for k, f in globals().items() if k.startswith(("op", "token_counts"))}


def oracle_sql() -> dict[str, str]:
    from calib.llm import sql

    return dict(sql.ORACLES)
