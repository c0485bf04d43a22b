"""Making the package known to executors, and tables in the folder that they share."""

from __future__ import annotations

import tempfile
import uuid
import zipfile
from collections.abc import Callable, Iterable
from concurrent.futures import ThreadPoolExecutor
from functools import wraps
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

PACKAGE = Path(__file__).resolve().parent


def ship(spark: SparkSession) -> None:
    """Sends the package's source to the executors, once a context, so that they need not have it installed."""
    sc = spark.sparkContext
    if getattr(sc, "_calib_shipped", False):
        return
    path = Path(tempfile.mkdtemp(prefix="calib-"), "calib_source.zip")
    with zipfile.ZipFile(path, "w", zipfile.ZIP_DEFLATED) as z:
        for p in sorted(PACKAGE.rglob("*.py")):
            z.write(p, p.relative_to(PACKAGE.parent))
    sc.addPyFile(str(path))
    sc._calib_shipped = True


def shipped(f):
    """f(spark, ...), with the package sent first."""

    @wraps(f)
    def run(spark, *args, **kwargs):
        ship(spark)
        return f(spark, *args, **kwargs)

    return run


def shared_dir(spark: SparkSession, tag: str) -> str:
    """A new folder below the shared one that the session names in spark.checkpoint.dir.

    Where the setting is absent, a temporary folder stands in, but only in local mode: on a cluster
    the executors could not see it.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        base = getattr(spark.sparkContext, "_calib_scratch", None)
        if base is None:
            base = spark.sparkContext._calib_scratch = "file://" + tempfile.mkdtemp(prefix="calib-")
    return f"{base.rstrip('/')}/{tag}-{uuid.uuid4().hex}"


def together(f: Callable, items: Iterable) -> list:
    """f of each item, all at once: jobs of few tasks that do not wait for one another."""
    items = list(items)
    with ThreadPoolExecutor(max(1, len(items))) as pool:
        return list(pool.map(f, items))


def drop_table(spark: SparkSession, path: str) -> None:
    """Deletes a table of the shared folder. Nothing may be read from it any more."""
    path = spark._jvm.org.apache.hadoop.fs.Path(path)
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def drop_shuffles(spark: SparkSession) -> None:
    """Has Spark delete the shuffle files of frames that are done: it does so when the driver's JVM collects them, which else may take as long as the session."""
    spark._jvm.System.gc()


def materialize(df: DataFrame, tag: str) -> DataFrame:
    """The frame, written to the shared folder and read again: its lineage is cut, and lost executors cost nothing."""
    path = shared_dir(df.sparkSession, tag)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
