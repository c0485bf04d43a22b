"""Random physical order: a hash of the key decides each example's place and block, whatever its content."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BLOCKS = 64


def digest(keys: list[str], seed: int = 0) -> Column:
    return F.md5(F.concat_ws(":", *(F.col(k).cast("string") for k in keys), F.lit(str(seed))))


def digits(digest_: Column, at: int) -> Column:
    """Eight hexadecimal digits from place `at` as a number below 2 ** 32."""
    return F.conv(F.substring(digest_, at, 8), 16, 10).cast("long")


def with_order(df: DataFrame, keys: list[str], blocks: int = BLOCKS, seed: int = 0) -> DataFrame:
    """Adds ord and blk. Labels that are made up by a hash must use other digits, or blocks are no random samples."""
    return df.withColumn("ord", digits(digest(keys, seed), 1)).withColumn("blk", (F.col("ord") % blocks).cast("int"))


def prepare(examples: DataFrame, path: str) -> DataFrame:
    """Writes the examples by block, each block in random order, and reads them again: one shuffle for all later runs."""
    examples.repartition("blk").sortWithinPartitions("blk", "ord").write.mode("overwrite").partitionBy("blk").parquet(path)
    return examples.sparkSession.read.parquet(path)


def block_sequence(blocks: int, k: int, seed: int = 0) -> list[int]:
    """The blocks in the order in which iteration k reads them: from a random one on, with wrap-around."""
    start = int(np.random.default_rng([seed, k]).integers(blocks))
    return [(start + i) % blocks for i in range(blocks)]
