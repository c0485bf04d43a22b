"""Token counts as rollups that are maintained by deltas.

A batch of changes is signed: an insert adds a document's tokens, a delete takes them away, a revision adds the
difference. Each batch is summed by source, language and tokenizer version and written in a folder of its own,
then marked as committed; totals are sums over committed batches, so that a batch that is sent again, or was
broken off and is run again, counts once.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from calib.llm.packing import text_encoder
from calib.llm.shared import materialize, shared_dir, words_of

KEYS = ["source", "lang", "tokenizer"]
SUMS = ["n_docs", "n_tokens"]
SCHEMA = "source string, lang string, tokenizer string, n_docs long, n_tokens long"


class Rollup:
    """Totals in a folder that all executors share. Null sources and languages are groups of their own."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")

    def _fs(self, path: str):
        p = self.spark._jvm.org.apache.hadoop.fs.Path(path)
        return p, p.getFileSystem(self.spark._jsc.hadoopConfiguration())

    def committed(self) -> list[str]:
        """The batches that count, in no set order; those of a compacted base are among them."""
        p, fs = self._fs(f"{self.path}/commits")
        return [s.getPath().getName() for s in fs.listStatus(p)] if fs.exists(p) else []

    def commit(self, batch: str, changes: DataFrame) -> bool:
        """Adds a batch of signed changes (KEYS and SUMS; other columns are ignored). False: it counted already."""
        if batch in self.committed():
            return False
        summed = changes.groupBy(*KEYS).agg(*(F.sum(c).cast("long").alias(c) for c in SUMS)).where("n_docs <> 0 OR n_tokens <> 0")
        summed.select(*KEYS, *SUMS).write.mode("overwrite").parquet(f"{self.path}/deltas/{batch}")
        p, fs = self._fs(f"{self.path}/commits/{batch}")
        fs.create(p, True).close()
        return True

    def _base(self) -> tuple[str | None, list[str]]:
        """The newest compacted base and the batches in it."""
        p, fs = self._fs(f"{self.path}/bases")
        done = sorted(x for s in (fs.listStatus(p) if fs.exists(p) else []) if fs.exists(self._fs(f"{self.path}/bases/{(x := s.getPath().getName())}/batches/_SUCCESS")[0]))
        if not done:
            return None, []
        return done[-1], [r[0] for r in self.spark.read.schema("value string").text(f"{self.path}/bases/{done[-1]}/batches").collect()]

    def totals(self) -> DataFrame:
        """KEYS and SUMS over all committed batches; groups that have come to nothing are left out."""
        base, inside = self._base()
        paths = [f"{self.path}/deltas/{b}" for b in sorted(set(self.committed()) - set(inside))] + ([f"{self.path}/bases/{base}/totals"] if base else [])
        if not paths:
            return self.spark.createDataFrame([], SCHEMA)
        found = self.spark.read.schema(SCHEMA).parquet(*paths)
        return found.groupBy(*KEYS).agg(*(F.sum(c).alias(c) for c in SUMS)).where("n_docs <> 0 OR n_tokens <> 0")

    def compact(self) -> None:
        """Sums what is committed into a new base. It counts once its list of batches is written whole."""
        base, _ = self._base()
        new, batches = f"{int(base or 0) + 1:08d}", sorted(self.committed())
        self.totals().write.mode("overwrite").parquet(f"{self.path}/bases/{new}/totals")
        self.spark.createDataFrame([(b,) for b in batches], "value string").write.mode("overwrite").text(f"{self.path}/bases/{new}/batches")


def inserts(rows: DataFrame, tokens: str) -> DataFrame:
    return rows.select(*KEYS, F.lit(1).alias("n_docs"), F.col(tokens).alias("n_tokens"))


def deletes(rows: DataFrame, tokens: str) -> DataFrame:
    return rows.select(*KEYS, F.lit(-1).alias("n_docs"), (-F.col(tokens)).alias("n_tokens"))


def revisions(rows: DataFrame, old: str, new: str) -> DataFrame:
    return rows.where(F.col(old) != F.col(new)).select(*KEYS, F.lit(0).alias("n_docs"), (F.col(new) - F.col(old)).alias("n_tokens"))


def bpe_counts(docs: DataFrame, columns: list[str], path: str) -> DataFrame:
    """docs with each text column replaced by its number of byte-level BPE ids."""
    rest = [c for c in docs.columns if c not in columns]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = text_encoder(path)
        for b in batches:
            counts = []
            for c in columns:
                first = b.column(columns[0]).to_pylist() if c != columns[0] else None
                texts = b.column(c).to_pylist()
                known = counts[0].to_pylist() if counts else None
                counts.append(pa.array([known[i] if first and first[i] == t else len(encode(t or "")) // 4 for i, t in enumerate(texts)], pa.int64()))
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in rest), *counts], names=[*rest, *columns])

    schema = docs.select(*rest).schema
    for c in columns:
        schema = schema.add(c, "long")
    return docs.select(*rest, *columns).mapInArrow(run, schema)


def maintained(docs: DataFrame, tokenizers: dict[str, str | None]) -> DataFrame:
    """Runs a corpus through its three batches and gives the totals after a replay of the second.

    Load: every document is inserted. Clean: lines that repeat an earlier one of the document are gone, and
    counts are revised. Withdraw: of the documents with one text all but that of the least doc_id are deleted.
    tokenizers: version to vocabulary file, or None for words between white space. Null texts count no tokens
    and are withdrawn as copies of each other.
    """
    spark = docs.sparkSession
    text = F.col("text").cast("string")
    unique = F.array_join(F.array_distinct(F.split(text, "\n")), "\n")
    rows = docs.select(F.col("doc_id").cast("long"), F.col("source").cast("string"), F.col("lang").cast("string"), F.xxhash64(F.lit(1), text).alias("h1"), F.xxhash64(F.lit(2), text).alias("h2"), text.alias("raw"), unique.alias("clean"))
    plain = [n for n, path in tokenizers.items() if path is None]
    rows = rows.withColumns({f"{n} {c}": F.size(words_of(F.col(c))).cast("long") for n in plain for c in ("raw", "clean")})
    for name, path in tokenizers.items():
        if path is not None:
            rows = bpe_counts(rows.withColumns({f"{name} {c}": F.col(c) for c in ("raw", "clean")}), [f"{name} {c}" for c in ("raw", "clean")], path)
    rows = materialize(rows.drop("raw", "clean"), "counts")
    versions = F.explode(F.array(*(F.struct(F.lit(n).alias("tokenizer"), F.col(f"`{n} raw`").alias("raw"), F.col(f"`{n} clean`").alias("clean")) for n in tokenizers)))
    each = rows.select("doc_id", "source", "lang", "h1", "h2", versions.alias("x")).select("doc_id", "source", "lang", "h1", "h2", "x.*")
    first = each.groupBy("h1", "h2").agg(F.min("doc_id").alias("first"))
    copies = each.join(first, ["h1", "h2"]).where(~F.col("doc_id").eqNullSafe(F.col("first")))
    rollup = Rollup(spark, shared_dir(spark, "rollup"))
    rollup.commit("load", inserts(each, "raw"))
    rollup.commit("clean", revisions(each, "raw", "clean"))
    rollup.commit("withdraw", deletes(copies, "clean"))
    rollup.commit("clean", revisions(each, "raw", "clean"))
    return rollup.totals()
