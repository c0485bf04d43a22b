"""Streams: blocks as they arrive feed online aggregation, event-time windows, late rows and models of users."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from calib.functions.losses import Spec
from calib.operators.estimators import estimate
from calib.operators.halting import stop_loss
from calib.plans.moments import Moments, multi_eval
from calib.session import shared_dir


def ola_stream(spark: SparkSession, path: str, schema, models: np.ndarray, spec: Spec, total: int, files: int = 1, halt=None) -> Moments:
    """Moments of all models over a folder that is read as a stream, `files` a trigger. halt(moments) stops the stream early."""
    state: dict[str, Moments | None] = {"m": None}
    query = None

    def batch(df: DataFrame, _: int) -> None:
        new = multi_eval(df, models, spec, plan="wide", want_sq=True)
        state["m"] = new if state["m"] is None else state["m"] + new
        if halt is not None and query is not None and halt(state["m"]):
            query.stop()

    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files).option("recursiveFileLookup", "true").parquet(path)
    query = stream.writeStream.foreachBatch(batch).option("checkpointLocation", shared_dir(spark, "stream")).trigger(availableNow=True).start()
    query.awaitTermination()
    return state["m"]


def lone_survivor(total: int, eps: float = 0.05):
    """A halting test: one model is left by its loss's bounds."""

    def halt(m: Moments) -> bool:
        e = estimate(m, total)
        low, high = e.bounds()
        return len(stop_loss(low[:, 0], high[:, 0], eps)) == 1

    return halt


def windowed(events: DataFrame, kind: str = "tumbling") -> DataFrame:
    """Counts and sums of events by event-time window; the same code for a batch and for a stream with a watermark."""
    if kind == "session":
        w, keys = F.session_window("ts", "6 hours").alias("w"), ["user_id"]
    else:
        w, keys = (F.window("ts", "6 hours") if kind == "tumbling" else F.window("ts", "12 hours", "6 hours")).alias("w"), []
    out = events.groupBy(w, *keys).agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("value").cast("decimal(38,12)")).alias("v"))
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *keys, "n", F.round(F.col("v").cast("double"), 4).alias("total"))


def watermarked(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Events without repeats of an id within the watermark; later ones are dropped. ts may be without a time zone: it is read in the session's."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def user_models(events: DataFrame, d: int = 6, alpha: float = 0.1, loss: str = "lr") -> DataFrame:
    """A linear model for each user, moved by one step for each event as it comes: the state of users with new events, after them."""
    xs, spec = [f"x{j}" for j in range(d)], Spec(loss)

    def step(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, w = state.get if state.exists else (0, [0.0] * d)
        w = np.array(w, dtype=float)
        for pdf in parts:
            pdf = pdf.sort_values("event_id")
            for x, y in zip(pdf[xs].to_numpy(), pdf["y"].to_numpy()):
                w -= alpha * float(spec.f.slope(w @ x, y)) * x
                n += 1
        state.update((n, w.tolist()))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "w": [w.tolist()]})

    return events.groupBy("user_id").applyInPandasWithState(step, "user_id long, n long, w array<double>", "n long, w array<double>", "update", GroupStateTimeout.NoTimeout)


def score_stream(events: DataFrame, models: DataFrame) -> DataFrame:
    """Events joined with a static table of models (m, w)."""
    dot = F.aggregate(F.zip_with(F.array(*(f"x{j}" for j in range(6))), "w", lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)
    return events.join(F.broadcast(models)).select("event_id", "m", dot.alias("dot"))
