"""Places and small helpers that all operators of this subpackage share."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

#: White space as the contracts have it: space, tab, line feed, vertical tab, form feed, carriage return.
BLANKS = " \t\n\x0b\f\r"
#: A word is a run of anything else.
WORD = r"[^\x20\x09-\x0D]+"
WORD_RE = re.compile(WORD)
#: Lower-casing of A-Z alone, for str.translate.
ASCII_LOWER = {c: c + 32 for c in range(ord("A"), ord("Z") + 1)}


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


def materialize(df: DataFrame, tag: str, made: list[str] | None = None) -> DataFrame:
    """The frame, written to the shared folder and read again: its lineage is cut, and lost executors cost nothing.

    The table's folder is added to `made`, by which drop_tables() can delete it.
    """
    path = shared_dir(df.sparkSession, tag)
    if made is not None:
        made.append(path)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def plus(df: DataFrame, **columns: str) -> StructType:
    """The schema of df with further columns; df's own is left as it is."""
    out = StructType(list(df.schema.fields))
    for name, kind in columns.items():
        out.add(name, kind)
    return out


def drop_tables(spark: SparkSession, made: list[str]) -> None:
    """Deletes the tables that materialize() noted in `made`, which is emptied. Nothing may be read from them any more."""
    while made:
        path = spark._jvm.org.apache.hadoop.fs.Path(made.pop())
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def words_of(text):
    """Column: the array of words of a text column; null gives an empty array."""
    return F.regexp_extract_all(F.coalesce(text, F.lit("")), F.lit(WORD), F.lit(0))
