"""Exact top-k search by distributed histogram selection over integer inner products."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from calib.llm.shared import materialize

#: Queries that are broadcast together, and bins of one histogram round (a power of two).
QUERY_BLOCK, BINS = 4096, 256
#: Rows of one score matrix.
ROWS = 512
FOUND = "query_id long, rank int, vec_id long, score long"


def quantised(table: DataFrame, scale: int = 64) -> DataFrame:
    """vec_id and v, floor(scale * x) for every component x as double. Vectors that are null, or hold a null or non-finite component, are left out."""
    x = F.transform(F.col("embedding"), lambda c: c.cast("double"))
    whole = F.col("embedding").isNotNull() & F.forall(F.col("embedding"), lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c.cast("double")) != float("inf")))
    return table.where(F.col("vec_id").isNotNull()).where(F.coalesce(whole, F.lit(False))).select(F.col("vec_id").cast("long"), F.transform(x, lambda c: F.floor(c * scale)).alias("v"))


def _matrix(column: pa.ChunkedArray | pa.Array, dim: int) -> np.ndarray:
    """int64 rows; shorter vectors are filled up with zeros, which add nothing to a product."""
    values, at = column.values.to_numpy(zero_copy_only=False), column.offsets.to_numpy()
    if len(values[at[0] : at[-1]]) == dim * len(column) and (np.diff(at) == dim).all():
        return values[at[0] : at[-1]].reshape(-1, dim).astype(np.int64)
    out = np.zeros((len(column), dim), dtype=np.int64)
    for i, (a, b) in enumerate(zip(at[:-1], at[1:])):
        out[i, : b - a] = values[a:b][:dim]
    return out


def products(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Exact integer inner products; by floating-point matrix products while their size leaves every sum exact."""
    most = max(1, int(np.abs(a).max(initial=0))) * max(1, int(np.abs(b).max(initial=0))) * max(1, a.shape[1])
    kind = np.float32 if most < 1 << 24 else np.float64 if most < 1 << 53 else np.int64
    return (a.astype(kind) @ b.astype(kind).T).astype(np.int64)


def search(table: DataFrame, queries: DataFrame, k: int = 20, scale: int = 64) -> DataFrame:
    """query_id, rank, vec_id, score: the k best rows of `table` for every row of `queries`, its own vec_id left out.

    Both have vec_id and embedding. Every query is scored against every row in blocks. Histograms of the scores,
    counted from the top by task and added up, narrow down each query's k-th score until it is known exactly; a
    last pass keeps what lies above it and, of its equals, the smallest vec_ids. Rows that repeat a vec_id count
    one by one; queries that repeat one are answered once. An empty side gives an empty result. Sums beyond 64 bits wrap.
    """
    spark = table.sparkSession
    rows = materialize(quantised(table, scale), "vectors")
    asked = materialize(quantised(queries, scale).groupBy("vec_id").agg(F.min("v").alias("v")), "queries")
    dims, n = (x or 0 for x in asked.agg(F.max(F.size("v")), F.count("*")).first())
    blocks = -(-n // QUERY_BLOCK)
    out = None
    for block in range(blocks):
        part = asked.where(F.pmod(F.xxhash64("vec_id"), F.lit(blocks)) == block).toArrow().combine_chunks()
        if part.num_rows:
            found = _block(spark, rows, part.column("vec_id").to_numpy(), _matrix(part.column("v").combine_chunks(), dims), k)
            out = found if out is None else out.union(found)
    return out if out is not None else spark.createDataFrame([], FOUND)


def _scores(ids: np.ndarray, vectors: np.ndarray):
    """A function that gives (vec_ids, scores by query and row, which of them count) of each slice of a batch."""

    def run(batches: Iterator[pa.RecordBatch]):
        for b in batches:
            for at in range(0, b.num_rows, ROWS):
                s = b.slice(at, ROWS)
                own = s.column("vec_id").to_numpy(zero_copy_only=False)
                yield own, products(vectors, _matrix(s.column("v"), vectors.shape[1])), ids[:, None] != own[None, :]

    return run


def _block(spark: SparkSession, rows: DataFrame, ids: np.ndarray, vectors: np.ndarray, k: int) -> DataFrame:
    sent = spark.sparkContext.broadcast((ids, vectors))

    def extremes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        low, high, seen = None, None, np.zeros(len(ids), np.int64)
        for _, s, use in _scores(*sent.value)(batches):
            lo, hi = np.where(use, s, np.iinfo(np.int64).max).min(axis=1), np.where(use, s, np.iinfo(np.int64).min).max(axis=1)
            low, high = (lo, hi) if low is None else (np.minimum(low, lo), np.maximum(high, hi))
            seen += use.sum(axis=1)
        if low is not None:
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(ids))), pa.array(low), pa.array(high), pa.array(seen)], names=["q", "low", "high", "n"])

    found = rows.mapInArrow(extremes, "q long, low long, high long, n long").groupBy("q").agg(F.min("low").alias("low"), F.max("high").alias("high"), F.sum("n").alias("n")).toArrow().sort_by("q")
    if not found.num_rows:
        return spark.createDataFrame([], FOUND)
    low, high, n = (found.column(c).to_numpy() for c in ("low", "high", "n"))
    live = n > 0
    low, high = np.where(live, low, 0), np.where(live, high, 0)
    need = np.minimum(n, k)  # places that the bins below `top` still have to fill
    top = high + 1
    width = np.maximum(1, -(-(top - low) // BINS))
    while True:
        state = spark.sparkContext.broadcast((top, width, need))

        def counted(batches: Iterator[pa.RecordBatch], state=state) -> Iterator[pa.RecordBatch]:
            top, width, need = state.value
            total = np.zeros((len(top), BINS), np.int64)
            for _, s, use in _scores(*sent.value)(batches):
                bin_ = (top[:, None] - 1 - s) // width[:, None]
                ok = use & (s < top[:, None]) & (bin_ < BINS)
                q, _ = np.nonzero(ok)
                total += np.bincount(q * BINS + bin_[ok], minlength=total.size).reshape(total.shape)
            before = np.cumsum(total, axis=1) - total
            q, at = np.nonzero((total > 0) & (before < need[:, None]))  # lower bins cannot hold the place sought
            yield pa.RecordBatch.from_arrays([pa.array(q), pa.array(at), pa.array(total[q, at])], names=["q", "bin", "n"])

        t = rows.mapInArrow(counted, "q long, bin long, n long").groupBy("q", "bin").agg(F.sum("n").alias("n")).toArrow()
        total = np.zeros((len(ids), BINS), np.int64)
        total[t.column("q").to_numpy(), t.column("bin").to_numpy()] = t.column("n").to_numpy()
        sums = np.cumsum(total, axis=1)
        at = (sums < need[:, None]).sum(axis=1)
        at = np.where(live, np.minimum(at, BINS - 1), 0)
        above = np.where(at > 0, sums[np.arange(len(at)), np.maximum(at - 1, 0)], 0)
        need = need - np.where(live, above, 0)
        top = top - at * width
        if (width == 1).all():
            break
        width = np.maximum(1, -(-width // BINS))
    state = spark.sparkContext.broadcast((np.where(live, top - 1, np.iinfo(np.int64).max), need))

    def kept(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kth, need = state.value
        ties: list[tuple[np.ndarray, np.ndarray]] = []
        for own, s, use in _scores(*sent.value)(batches):
            q, r = np.nonzero(use & (s > kth[:, None]))
            yield pa.RecordBatch.from_arrays([pa.array(ids[q]), pa.array(own[r]), pa.array(s[q, r]), pa.array(np.zeros(len(q), bool))], names=["query_id", "vec_id", "score", "tie"])
            q, r = np.nonzero(use & (s == kth[:, None]))
            ties = [_least(np.concatenate([*(t[0] for t in ties), q]), np.concatenate([*(t[1] for t in ties), own[r]]), need)]
        if ties:
            q, v = ties[0]
            yield pa.RecordBatch.from_arrays([pa.array(ids[q]), pa.array(v), pa.array(kth[q]), pa.array(np.ones(len(q), bool))], names=["query_id", "vec_id", "score", "tie"])

    best = rows.mapInArrow(kept, "query_id long, vec_id long, score long, tie boolean").drop("tie")
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return best.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def _least(q: np.ndarray, v: np.ndarray, need: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of each query's vec_ids the smallest, as many as it needs."""
    order = np.lexsort((v, q))
    q, v = q[order], v[order]
    first = np.searchsorted(q, q)
    keep = np.arange(len(q)) - first < need[q]
    return q[keep], v[keep]
