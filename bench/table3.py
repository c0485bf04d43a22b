"""One update and one loss: this engine, an online learner's pass and Spark's own library; python bench/table3.py [sf_dir]."""

from __future__ import annotations

import json
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parents[1]))

import numpy as np
from pyspark.sql import SparkSession

from calib.functions.losses import Spec
from calib.operators.baselines import library_model, time_per_iteration
from calib.operators.incremental import progressive_loss
from calib.plans.moments import multi_eval
from calib.queries_methods import LINE_KEY, line
from calib.session import ship


def main(sf_dir: str) -> None:
    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "12g").config("spark.ui.enabled", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    ship(spark)
    ex = line(spark, sf_dir)
    for task in ("svm", "lr"):
        spec = Spec(task)
        ours = time_per_iteration(lambda: multi_eval(ex, np.zeros(5), spec, "arrow"), 3)
        began = time.perf_counter()
        progressive_loss(ex, spec, [0.0] * 5, 1e-3, LINE_KEY).collect()
        multi_eval(ex, np.zeros(5), spec, "arrow")
        online = time.perf_counter() - began
        _, one = library_model(ex, task, 5, 1)
        print(json.dumps({"task": task, "ours": round(ours, 3), "online": round(online, 3), "library_one_iteration": round(one, 3)}), flush=True)


if __name__ == "__main__":
    main(sys.argv[1] if len(sys.argv) > 1 else "/root/testdata/sf0.1")
