"""User-defined functions, aggregates and table functions over Arrow, and functions registered for SQL."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def margin_udf(w):
    """Arrow function of (x0.., y): y times w.x. The built-in expression is faster; this one shows the interface."""
    w = np.asarray(w, dtype=float)

    @F.pandas_udf("double")
    def margin(y: pd.Series, *xs: pd.Series) -> pd.Series:
        return y * sum(x * v for x, v in zip(xs, w))

    return margin


def moments_udaf(df: DataFrame, group: str, value: str) -> DataFrame:
    """n, s1 and s2 of a value by group: partial sums in each task over Arrow, then merged by Spark. No group meets in one task."""

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state: dict = {}
        for b in batches:
            t = b.to_pandas()
            for k, v in t.groupby(group, dropna=False)[value]:
                n, s1, s2 = state.get(k, (0, 0.0, 0.0))
                state[k] = (n + v.count(), s1 + v.sum(), s2 + (v * v).sum())
        rows = [(k, *v) for k, v in state.items()]
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows) if rows else [[]] * 4, (pa.string(), pa.int64(), pa.float64(), pa.float64()))], names=[group, "n", "s1", "s2"])

    parts = df.select(F.col(group).cast("string"), F.col(value).cast("double")).mapInArrow(partial, f"{group} string, n long, s1 double, s2 double")
    return parts.groupBy(group).agg(F.sum("n").alias("n"), F.sum("s1").alias("s1"), F.sum("s2").alias("s2"))


class _StepGrid:
    """Steps from one by powers of a factor, alternately larger and smaller."""

    def eval(self, s: int, first: float, factor: float):
        for i in range(s):
            yield i, first * factor ** ((i + 1) // 2 * (1 if i % 2 else -1))


def register_udtf(spark: SparkSession):
    """step_grid(s, first, factor) for SQL; also as a function to call."""
    grid = F.udtf(_StepGrid, returnType="i int, alpha double")
    spark.udtf.register("step_grid", grid)
    return grid


SQL_FUNCTIONS = {
    "svm_loss": ("dot DOUBLE, y DOUBLE", "DOUBLE", "greatest(1 - y * dot, 0D)"),
    "lr_loss": ("dot DOUBLE, y DOUBLE", "DOUBLE", "greatest(-y * dot, 0D) + log1p(exp(-abs(y * dot)))"),
    "rel_error": ("est DOUBLE, std DOUBLE", "DOUBLE", "CASE WHEN std = 0 THEN 0D WHEN est = 0 THEN double('infinity') ELSE 2 * std / abs(est) END"),
}


def register_sql(spark: SparkSession) -> None:
    """The losses as SQL functions, expanded by Catalyst like any expression."""
    for name, (args, kind, body) in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {kind} RETURN {body}")
