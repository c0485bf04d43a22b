"""Calibration of examples that any SQL text gives."""

from __future__ import annotations

from pyspark.sql import SparkSession

from calib.functions.losses import Spec
from calib.operators.batch import Run, trace_frame
from calib.operators.speculative import Grid, train_spec_bgd


def calibrate_sql(spark: SparkSession, text: str, loss: str = "svm", steps=(1e-6, 1e-5, 1e-4), iterations: int = 5, trace_view: str | None = None) -> Run:
    """Speculative descent on the result of `text`, which has columns x0.. or x, and y. The trace becomes a temporary view."""
    ex = spark.sql(text)
    d = len(ex.first()["x"]) if "x" in ex.columns else sum(c[0] == "x" and c[1:].isdigit() for c in ex.columns)
    run = train_spec_bgd(ex, Spec(loss), [0.0] * d, Grid(tuple(steps)), iterations=iterations)
    if trace_view:
        trace_frame(spark, run, {"k": "int", "alpha": "double", "loss": "double"}, {"alpha": 12}).createOrReplaceTempView(trace_view)
    return run
