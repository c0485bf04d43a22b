"""Quality classifier from weak labels.

Heuristic labellers vote good, bad or nothing on each document. Expectation-maximisation over the votes of all
documents estimates, without any given label, how often each labeller votes what on good and on bad ones. The
posterior of a document's votes then is its soft label, and a hashed linear scorer learns from those.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from calib.llm.rules import STOP_WORDS
from calib.llm.shared import WORD, WORD_RE, words_of

#: Documents that the scorer is trained on at most, chosen by a hash of the id; the votes of all documents are counted.
TRAIN_DOCS = 6000
#: Size of the scorer's table, a power of two.
ROWS = 1 << 16
#: P(good) from which a document is kept; doubt is for the document.
KEEP = 0.4


def counts_of(text: Column) -> dict[str, Column]:
    """What the labellers compare, from the columns _w (words) and _l (lines) of a text."""
    body = F.coalesce(text, F.lit(""))
    left = lambda chars: F.length(F.regexp_replace(body, f"[^{chars}]+", ""))
    return {
        "n": F.size("_w"),
        "solid": F.length(F.regexp_replace(body, r"[\x20\x09-\x0D]+", "")),
        "letters": left(r"\p{L}"),
        "upper": left(r"\p{Lu}"),
        "symbols": left("#*$%&|<>"),
        "marks": left("!?"),
        "same": F.size(F.filter("_w", lambda w, i: w.eqNullSafe(F.get("_w", i + 1)))),
        "stops": F.size(F.filter("_w", lambda w: F.lower(w).isin(STOP_WORDS))),
        "distinct": F.size(F.array_distinct("_w")),
        "n_lines": F.size("_l"),
        "distinct_lines": F.size(F.array_distinct("_l")),
    }


#: name, part, whole, least whole that counts, and tests of the part's share: bad, good. A share of too little gives no vote.
LABELLERS = [
    ("symbols", "symbols", "n", 1, lambda x: x > 0.2, lambda x: x < 0.02),
    ("letters", "letters", "solid", 1, lambda x: x < 0.7, lambda x: x > 0.85),
    ("case", "upper", "letters", 1, lambda x: x > 0.4, lambda x: x < 0.12),
    ("marks", "marks", "n", 1, lambda x: x > 0.4, lambda x: x < 0.05),
    ("variety", "distinct", "n", 20, lambda x: x < 0.3, lambda x: x > 0.45),
    ("repeats", "same", "n", 1, lambda x: x > 0.3, lambda x: x < 0.08),
    ("lines", "distinct_lines", "n_lines", 1, lambda x: x < 0.3, lambda x: x > 0.7),
    ("stop_words", "stops", "n", 40, lambda x: x < 0.004, lambda x: x > 0.05),
]


def with_votes(docs: DataFrame) -> DataFrame:
    """docs with `votes`: for each labeller + (good), - (bad) or 0 (nothing). Null texts are empty ones, on which nobody votes.

    The counts leave their projection by a generator, or each branch of a vote would count anew.
    """
    text = F.col("text").cast("string")
    lines = F.filter(F.split(F.coalesce(text, F.lit("")), "\n"), lambda x: x.rlike(WORD))
    rows = docs.withColumn("_row", F.struct(*docs.columns)).withColumn("_w", words_of(text)).withColumn("_l", lines)
    rows = rows.select("_row", F.explode(F.array(F.struct(*(c.alias(k) for k, c in counts_of(text).items())))).alias("_c"))

    def vote(part: str, whole: str, least: int, bad, good) -> Column:
        share = F.col(f"_c.{part}") / F.col(f"_c.{whole}")
        return F.when(F.col(f"_c.{whole}") < least, "0").when(bad(share), "-").when(good(share), "+").otherwise("0")

    return rows.select("_row.*", F.concat(*(vote(*x) for _, *x in LABELLERS)).alias("votes"))


#: What is held of any labeller before votes are seen, P(vote | class) by class (bad, good) and vote (-, 0, +), and how many documents that weighs.
PRIOR, PRIOR_DOCS = np.array([[0.4, 0.2, 0.4], [0.02, 0.08, 0.9]]), 20.0


def expectation_maximisation(counts: dict[str, int], rounds: int = 200, smooth: float = 1.0) -> tuple[float, np.ndarray, dict[str, float]]:
    """Share of good documents, P(vote | class) by labeller (bad, good by -, 0, +), and P(good) of each vote pattern.

    The prior settles what a class of few documents leaves open; many votes outweigh it.
    """
    patterns = sorted(counts)
    v = np.array([["-0+".index(x) for x in p] for p in patterns])
    w = np.array([counts[p] for p in patterns], dtype=float)
    good = np.choose(np.minimum(2, (v == 0).sum(axis=1)), [0.95, 0.6, 0.05])  # to begin with, two bad votes outweigh any good ones
    hot = np.eye(3)[v]
    for _ in range(rounds):
        share = (w @ good + smooth) / (w.sum() + 2 * smooth)
        table = np.stack([np.einsum("p,plv->lv", w * g, hot) + PRIOR_DOCS * prior for g, prior in zip((1 - good, good), PRIOR)])
        table /= table.sum(axis=2, keepdims=True)
        ll = np.log(table)[:, np.arange(v.shape[1]), v].sum(axis=2) + np.log([[1 - share], [share]])
        new = 1 / (1 + np.exp(np.clip(ll[0] - ll[1], -500, 500)))
        if np.abs(new - good).max() < 1e-9:
            break
        good = new
    return float(share), table.transpose(1, 0, 2), dict(zip(patterns, good.tolist()))


def _shape(w: str) -> str:
    out = ""
    for c in w:
        k = "a" if c.islower() else "A" if c.isupper() else "0" if c.isdigit() else "x" if c.isalpha() else c
        if out[-1:] != k:
            out += k
    return out[:8]


class Features:
    """Hashed shares of words, word shapes and repeats in a text. A word's share says less than its shape's, and a short text says little."""

    WORD_SHARE = 0.2

    def __init__(self):
        self.forget()

    def forget(self) -> None:
        self.number: dict[str, int] = {}
        self.rows = np.zeros((0, 2), np.int64)  # of word and shape

    def found(self, text: str | None) -> tuple[np.ndarray, float, float]:
        """Rows of each word and its shape; shares of words that repeat the one before, and of those that are not new."""
        import xxhash

        words = WORD_RE.findall(text) if text else []
        new = sorted(set(words).difference(self.number))
        if new:
            if len(self.number) > 200_000:
                self.forget()
                new = sorted(set(words))
            self.number.update(zip(new, range(len(self.number), len(self.number) + len(new))))
            rows = [(xxhash.xxh32_intdigest("w" + w.lower()) % (ROWS - 8) + 8, xxhash.xxh32_intdigest("s" + _shape(w)) % (ROWS - 8) + 8) for w in new]
            if len(self.number) > len(self.rows):
                self.rows = np.concatenate([self.rows, np.zeros((max(1024, len(self.rows), len(new)), 2), np.int64)])
            self.rows[len(self.number) - len(new) : len(self.number)] = rows
        n = len(words)
        ids = self.rows[np.fromiter(map(self.number.__getitem__, words), np.int64, n)]
        again = float((ids[1:, 0] == ids[:-1, 0]).mean()) if n > 1 else 0.0
        old = 1 - len(np.unique(ids[:, 0])) / n if n else 0.0
        return ids, again * min(1, n / 20), old * min(1, n / 100)

    def of(self, text: str | None) -> tuple[np.ndarray, np.ndarray]:
        """Places and values of what is not zero."""
        ids, again, old = self.found(text)
        at, place = np.unique(ids, return_inverse=True)
        x = np.bincount(place.ravel(), np.tile([self.WORD_SHARE, 1.0], len(ids)), len(at)) / max(len(ids), 20)
        return np.concatenate([[0, 1, 2], at]), np.concatenate([[1.0, again, old], x]).astype(np.float32)

    def score(self, text: str | None, weights: np.ndarray) -> float:
        """The product of features and weights."""
        ids, again, old = self.found(text)
        parts = weights[ids].sum(axis=0, dtype=np.float64) if len(ids) else (0.0, 0.0)
        return float(weights[0] + again * weights[1] + old * weights[2] + (self.WORD_SHARE * parts[0] + parts[1]) / max(len(ids), 20))


def train(rows: list[tuple[np.ndarray, np.ndarray]], target: np.ndarray, epochs: int = 12, rate: float = 1.0) -> np.ndarray:
    """Logistic regression on soft labels by adaptive gradient steps over small batches."""
    weights, square, r = np.zeros(ROWS), np.full(ROWS, 1e-6), np.random.default_rng(7)
    for _ in range(epochs):
        order = r.permutation(len(rows))
        for a in range(0, len(order), 16):
            g = np.zeros(0)
            at, x = [], []
            for i in order[a : a + 16]:
                k, v = rows[i]
                d = (1 / (1 + np.exp(-np.clip(weights[k] @ v, -30, 30))) - target[i])
                at.append(k)
                x.append(d * v)
            at, place = np.unique(np.concatenate(at), return_inverse=True)
            g = np.bincount(place, np.concatenate(x)) / 16 + 1e-6 * weights[at]
            square[at] += g * g
            weights[at] -= rate * 0.3 * g / np.sqrt(square[at])
    return weights


def fit(docs: DataFrame) -> np.ndarray:
    """The scorer's weights. All documents are voted on; the driver gets the count of each vote pattern, at most 3^8, and TRAIN_DOCS texts."""
    voted = with_votes(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")))
    counts = {r["votes"]: r["count"] for r in voted.groupBy("votes").count().collect()}
    if not counts:
        return np.zeros(ROWS)
    posterior = expectation_maximisation(counts)[2]
    share = min(1.0, TRAIN_DOCS / sum(counts.values()))
    sample = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).where(F.pmod(F.xxhash64("doc_id", F.lit("scorer")), F.lit(1 << 30)) < int(share * (1 << 30)))
    sent = docs.sparkSession.sparkContext.broadcast(posterior)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make = Features()
        for b in batches:
            rows = [make.of(t) for t in b.column("text").to_pylist()]
            y = [sent.value.get(v, 0.5) for v in b.column("votes").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array([k.tolist() for k, _ in rows], pa.list_(pa.int32())), pa.array([x.tolist() for _, x in rows], pa.list_(pa.float32())), pa.array(y, pa.float64())], names=["doc_id", "at", "x", "y"])

    found = with_votes(sample).mapInArrow(run, "doc_id long, at array<int>, x array<float>, y double").toArrow().sort_by("doc_id").combine_chunks()
    at, x = (found.column(c).combine_chunks() for c in ("at", "x"))
    rows = [(at[i].values.to_numpy(), x[i].values.to_numpy()) for i in range(found.num_rows)]
    return train(rows, found.column("y").to_numpy())


def score(docs: DataFrame, weights: np.ndarray) -> DataFrame:
    """doc_id and score, P(good), of every whole text; a text without words has the score of the bias alone."""
    sent = docs.sparkSession.sparkContext.broadcast(weights.astype(np.float32))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make, w = Features(), sent.value
        for b in batches:
            s = [make.score(t, w) for t in b.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(1 / (1 + np.exp(-np.clip(np.array(s, dtype=float), -60, 60))))], names=["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, score double")


def judge(docs: DataFrame) -> DataFrame:
    """doc_id, score and kept of every row, from its whole text. Repeated rows get the same score; null and empty texts that of the bias alone; an empty table gives an empty result."""
    return score(docs, fit(docs)).select("doc_id", "score", (F.col("score") >= KEEP).alias("kept"))


def keep_good(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """The rows of docs that the scorer keeps, with their columns and whatever these hold."""
    sent = spark.sparkContext.broadcast(fit(docs).astype(np.float32))
    names = docs.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make, w, least = Features(), sent.value, np.log(KEEP / (1 - KEEP))
        for b in batches:
            good = [make.score(t, w) >= least for t in b.column("text").to_pylist()]
            yield b.filter(pa.array(good, pa.bool_()))

    return docs.select(names).mapInArrow(run, docs.schema)
