"""Seconds per iteration by task, method and number of concurrent steps; python bench/table2.py [sf_dir]."""

from __future__ import annotations

import json
import sys
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parents[1]))

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from calib.functions.losses import Spec
from calib.operators.baselines import time_per_iteration
from calib.operators.incremental import in_turns
from calib.operators.speculative import igd_children, merge_children
from calib.plans.moments import multi_eval
from calib.queries_experiments import star
from calib.queries_methods import LINE_KEY
from calib.session import ship
from calib.sources.views import STAR_D


def main(sf_dir: str) -> None:
    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "12g").config("spark.ui.enabled", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    ship(spark)
    ex = star(spark, sf_dir).withColumn("part", F.col("ord") % 8)
    for task in ("svm", "lr"):
        spec = Spec(task)
        for s in (1, 2, 4, 8, 16, 32):
            models = np.random.default_rng(0).standard_normal((s, STAR_D)) * 0.01
            secs = time_per_iteration(lambda: multi_eval(ex, models, spec, "arrow"), 3)
            print(json.dumps({"task": task, "method": "batch", "s": s, "secs": round(secs, 3)}), flush=True)
        turns = in_turns(ex, LINE_KEY, 8, 4)
        for method, frame, part, late in (("merge", ex, "part", 0), ("lock", turns, "node", 0), ("nolock", turns, "node", 4)):
            for s in (1, 2, 4, 8, 16):
                parents, alphas = np.zeros((s, STAR_D)), np.full(s, 1e-3)
                secs = time_per_iteration(lambda: merge_children(igd_children(frame, spec, parents, alphas, LINE_KEY, part, late=late), STAR_D), 1)
                print(json.dumps({"task": task, "method": method, "s": s, "secs": round(secs, 3)}), flush=True)


if __name__ == "__main__":
    main(sys.argv[1] if len(sys.argv) > 1 else "/root/testdata/sf0.01")
