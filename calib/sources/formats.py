"""Text formats and a generator of separable examples as a data source."""

from __future__ import annotations

import sys

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, In, InputPartition


def to_libsvm(df: DataFrame) -> DataFrame:
    """Sparse examples (idx, val, y) as lines `label idx:val ..`, with indices from 1."""
    pairs = F.transform(F.arrays_zip("idx", "val"), lambda e: F.concat((e["idx"] + 1).cast("string"), F.lit(":"), e["val"].cast("string")))
    return df.select(F.concat_ws(" ", F.col("y").cast("int").cast("string"), F.array_join(pairs, " ")).alias("value"))


def parse_libsvm(value: Column) -> Column:
    """struct(y, idx, val) of such a line; blanks around it do not matter."""
    parts = F.split(F.trim(value), " +")
    entries = F.filter(F.slice(parts, 2, F.greatest(F.size(parts) - 1, F.lit(0))), lambda p: p != "")
    return F.struct(
        F.element_at(parts, 1).cast("double").alias("y"),
        F.transform(entries, lambda p: F.substring_index(p, ":", 1).cast("long") - 1).alias("idx"),
        F.transform(entries, lambda p: F.substring_index(p, ":", -1).cast("double")).alias("val"),
    )


def read_libsvm(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.text(path).select(parse_libsvm(F.col("value")).alias("e")).select("e.*")


class SeparableSource(DataSource):
    """`separable`: examples of a planted separator, made up block by block. Options: rows, dims, blocks, seed, flip.

    A filter on blk (= or IN) is pushed into the source, which then makes only those blocks.
    """

    @classmethod
    def name(cls) -> str:
        return "separable"

    def schema(self) -> str:
        return "ex_id long, blk int, x array<double>, y double"

    def reader(self, schema) -> DataSourceReader:
        return SeparableReader(self.options)


def register(spark: SparkSession) -> None:
    """Makes the source known to a session. Spark's planner runs it in a process that gets no files, so its code travels by value."""
    cloudpickle.register_pickle_by_value(sys.modules[__name__])
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(SeparableSource)


class SeparableReader(DataSourceReader):
    def __init__(self, options):
        get = lambda k, v: type(v)(options.get(k, v))
        self.rows, self.dims, self.blocks, self.seed, self.flip = get("rows", 10_000), get("dims", 20), get("blocks", 16), get("seed", 1), get("flip", 0.05)
        self.wanted = set(range(self.blocks))

    def pushFilters(self, filters):
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute == ("blk",):
                self.wanted &= {f.value}
            elif isinstance(f, In) and f.attribute == ("blk",):
                self.wanted &= set(f.value)
            else:
                yield f

    def partitions(self):
        return [InputPartition(b) for b in sorted(self.wanted)]

    def read(self, partition):
        blk = partition.value
        ids = np.arange(blk, self.rows, self.blocks)
        r = np.random.default_rng([self.seed, blk])
        planted = np.random.default_rng(self.seed).standard_normal(self.dims)
        for at in range(0, len(ids), 8192):
            part = ids[at : at + 8192]
            x = r.standard_normal((len(part), self.dims))
            y = np.where(x @ planted > 0, 1.0, -1.0) * np.where(r.random(len(part)) < self.flip, -1.0, 1.0)
            yield pa.RecordBatch.from_arrays([pa.array(part), pa.array(np.full(len(part), blk, np.int32)), pa.array(list(x), pa.list_(pa.float64())), pa.array(y)], names=["ex_id", "blk", "x", "y"])
