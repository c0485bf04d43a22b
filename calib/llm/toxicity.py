"""Toxicity: a bidirectional gated recurrent network over words, with attention pooling, in numpy.

A word enters as a hashed embedding of itself beside the mean of hashed embeddings of its character trigrams.
The network reads windows of a text that overlap by half; attention pools the states of both directions, and
a text's score is that of its most toxic window. Training picks that window anew in every step.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

WINDOW, STRIDE = 32, 16
WORD_ROWS, CHAR_ROWS, DIM, HIDDEN, ATTENTION = 1 << 14, 1 << 13, 12, 12, 8
#: Labelled documents to train on at most, of label 1 and 0, and windows of one of them.
POSITIVES, NEGATIVES, TRAIN_WINDOWS = 1200, 2400, 24
THRESHOLD = 0.7
_WORDS = re.compile(r"[^\W_]+")
#: Distinct words that a task keeps before it starts afresh.
VOCABULARY = 100_000


def words_of_text(text: str | None) -> list[str]:
    return _WORDS.findall(text.lower()) if text else []


def hashed(words: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Row of each word in the word table; rows of all trigrams in the character table, and where each word's begin."""
    code = np.frombuffer("".join(f"<{w}>" for w in words).encode("utf-32-le", "surrogatepass"), dtype="<u4").astype(np.uint64)
    sizes = np.array([len(w) + 2 for w in words], dtype=np.int64)
    starts = np.cumsum(sizes) - sizes
    place = np.arange(len(code)) - np.repeat(starts, sizes)
    with np.errstate(over="ignore"):
        power = np.cumprod(np.full(int(sizes.max()), 0x9E3779B97F4A7C15, dtype=np.uint64))
        whole = np.add.reduceat(code * power[place], starts)
        tri = code[:-2] * np.uint64(0x9E3779B97F4A7C15) + code[1:-1] * np.uint64(0xC2B2AE3D27D4EB4F) + code[2:] * np.uint64(0x165667B19E3779F9)
        tri = tri[(place < np.repeat(sizes, sizes) - 2)[:-2]]
    top = lambda x, n: ((x ^ x >> np.uint64(29)) * np.uint64(0xBF58476D1CE4E5B9) >> np.uint64(40)).astype(np.int64) % n
    return top(whole, WORD_ROWS), top(tri, CHAR_ROWS), np.cumsum(sizes - 2) - (sizes - 2)


def initial(seed: int = 7) -> dict[str, np.ndarray]:
    r = np.random.default_rng(seed)
    f = lambda *s, scale: (r.standard_normal(s) * scale).astype(np.float32)
    p = {"word": f(WORD_ROWS, DIM, scale=0.1), "char": f(CHAR_ROWS, DIM, scale=0.3), "A": f(2 * HIDDEN, ATTENTION, scale=0.3), "a": f(ATTENTION, scale=0.3), "o": f(2 * HIDDEN, scale=0.3), "c": np.full(1, -1.0, np.float32)}
    for d in "fb":
        p |= {f"W{d}": f(2 * DIM, 3 * HIDDEN, scale=0.3), f"U{d}": f(HIDDEN, 3 * HIDDEN, scale=0.25), f"v{d}": np.zeros(3 * HIDDEN, np.float32)}
    return p


def inputs(p: dict, words: list[str]) -> np.ndarray:
    """The network's input for each word, in single precision."""
    rows, tri, starts = hashed(words)
    sizes = np.diff(np.append(starts, len(tri))).astype(np.float32)
    return np.concatenate([p["word"].take(rows, axis=0), np.add.reduceat(p["char"].take(tri, axis=0), starts) / sizes[:, None]], axis=1)


def windows(n: int) -> np.ndarray:
    """Places of the words in each overlapping window of a text of n words; -1 beyond its end."""
    at = np.arange(0, max(1, n - STRIDE), STRIDE)[:, None] + np.arange(WINDOW)
    return np.where(at < n, at, -1)


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * np.tanh(0.5 * x) + np.float32(0.5)


def _gates(p: dict, d: str, x: np.ndarray, h: np.ndarray, live: np.ndarray):
    u = h @ p[f"U{d}"]
    zr = sigmoid(x[:, : 2 * HIDDEN] + u[:, : 2 * HIDDEN])
    z, r = zr[:, :HIDDEN], zr[:, HIDDEN:]
    n = np.tanh(x[:, 2 * HIDDEN :] + r * u[:, 2 * HIDDEN :])
    z = np.where(live, z, np.float32(1))  # beyond the text's end the state stays
    return z, r, n, u[:, 2 * HIDDEN :]


def logits(p: dict, x: np.ndarray, at: np.ndarray) -> np.ndarray:
    """The score before the sigmoid of each window; x: inputs of words, at: rows of x, -1 for none.

    Windows lie along the last axis, so that each operation runs over long rows. The weights of both sigmoids are
    halved beforehand (exactly), and attention pools what the states add to the score instead of the states.
    """
    at = np.ascontiguousarray(at.T)
    b, gone = at.shape[1], at < 0
    ragged = gone.any(axis=1)
    states, gx, u = np.empty((WINDOW, 2 * HIDDEN, b), np.float32), *np.empty((2, 3 * HIDDEN, b), np.float32)
    z, r, zr, n, un = gx[:HIDDEN], gx[HIDDEN : 2 * HIDDEN], gx[: 2 * HIDDEN], gx[2 * HIDDEN :], u[2 * HIDDEN :]
    half = np.repeat(np.array([0.5, 0.5, 1], np.float32), HIDDEN)
    for d, order, part in (("f", range(WINDOW), slice(0, HIDDEN)), ("b", range(WINDOW - 1, -1, -1), slice(HIDDEN, None))):
        w, uw, v = (np.ascontiguousarray((p[k + d] * half).T) for k in "WUv")
        h = np.zeros((HIDDEN, b), np.float32)
        for t in order:
            np.matmul(w, x.take(at[t], axis=0).T, out=gx)
            np.matmul(uw, h, out=u)
            gx += v[:, None]
            zr += u[: 2 * HIDDEN]
            np.tanh(zr, out=zr)
            zr *= np.float32(0.5)
            zr += np.float32(0.5)
            un *= r
            n += un
            np.tanh(n, out=n)
            if ragged[t]:
                np.maximum(z, gone[t], out=z)  # beyond the text's end the state stays
            new = states[t, part]
            np.subtract(h, n, out=new)
            new *= z
            new += n
            h = new
    e, adds, aw = np.empty((WINDOW, b), np.float32), p["o"] @ states, np.ascontiguousarray(p["A"].T)
    for t in range(WINDOW):
        e[t] = p["a"] @ np.tanh(aw @ states[t])
    e[gone] = -1e9
    e -= e.max(axis=0)
    np.exp(e, out=e)
    return np.einsum("tb,tb->b", e, adds) / e.sum(axis=0) + p["c"][0]


def gate_inputs(p: dict, x: np.ndarray) -> dict[str, np.ndarray]:
    return {d: x @ p[f"W{d}"] + p[f"v{d}"] for d in "fb"}


def gradient(p: dict, words: list[str], at: np.ndarray, y: np.ndarray) -> tuple[float, dict]:
    """Loss and gradient of windows (rows of `words`, -1 for none) against labels, by backpropagation through time."""
    b, (rows, tri, starts) = len(at), hashed(words)
    sizes = np.diff(np.append(starts, len(tri)))
    x = np.concatenate([p["word"][rows], np.add.reduceat(p["char"][tri], starts) / sizes[:, None]], axis=1)
    gx = gate_inputs(p, x)
    live = at >= 0
    states, kept = np.empty((WINDOW, b, 2 * HIDDEN), np.float32), {}
    parts = (("f", list(range(WINDOW)), slice(0, HIDDEN)), ("b", list(range(WINDOW - 1, -1, -1)), slice(HIDDEN, None)))
    for d, order, part in parts:
        h = np.zeros((b, HIDDEN), np.float32)
        for t in order:
            step = _gates(p, d, gx[d][at[:, t]], h, live[:, t, None])
            kept[d, t] = (h, *step)
            z, _, n, _ = step
            h = n + z * (h - n)
            states[t, :, part] = h
    s = np.tanh(states @ p["A"])
    e = np.where(live.T, s @ p["a"], np.float32(-1e9))
    e = np.exp(e - e.max(axis=0))
    e /= e.sum(axis=0)
    pooled = np.einsum("tb,tbh->bh", e, states)
    q = 1 / (1 + np.exp(-(pooled @ p["o"] + p["c"][0])))
    loss = float(-np.mean(y * np.log(q + 1e-7) + (1 - y) * np.log(1 - q + 1e-7)))
    dq = ((q - y) / b).astype(np.float32)
    g = {"o": pooled.T @ dq, "c": dq.sum(keepdims=True)}
    dpool = dq[:, None] * p["o"]
    dstates = e[:, :, None] * dpool
    de = np.einsum("tbh,bh->tb", states, dpool)
    de = e * (de - (e * de).sum(axis=0))
    g["a"] = np.einsum("tb,tbk->k", de, s)
    ds = de[:, :, None] * p["a"] * (1 - s * s)
    g["A"] = np.einsum("tbh,tbk->hk", states, ds)
    dstates += ds @ p["A"].T
    dx = np.zeros_like(x)
    for d, order, part in parts:
        dgx, dh = np.zeros_like(gx[d]), np.zeros((b, HIDDEN), np.float32)
        g[f"U{d}"] = np.zeros_like(p[f"U{d}"])
        for t in reversed(order):
            h, z, r, n, un = kept[d, t]
            dh = dh + dstates[t, :, part]
            dn = dh * (1 - z) * (1 - n * n)
            dz = dh * (h - n) * z * (1 - z) * live[:, t, None]
            dr = dn * un * r * (1 - r)
            du = np.concatenate([dz, dr, dn * r], axis=1)
            np.add.at(dgx, at[live[:, t], t], np.concatenate([dz, dr, dn], axis=1)[live[:, t]])
            g[f"U{d}"] += h.T @ du
            dh = dh * z + du @ p[f"U{d}"].T
        g[f"W{d}"], g[f"v{d}"] = x.T @ dgx, dgx.sum(axis=0)
        dx += dgx @ p[f"W{d}"].T
    g["word"], g["char"] = np.zeros_like(p["word"]), np.zeros_like(p["char"])
    np.add.at(g["word"], rows, dx[:, :DIM])
    np.add.at(g["char"], tri, np.repeat(dx[:, DIM:] / sizes[:, None], sizes, axis=0))
    return loss, g


def train(texts: list[str], labels: list[int], epochs: int = 8, batch: int = 48, rate: float = 0.01, seed: int = 7) -> dict[str, np.ndarray]:
    """Adam on the most toxic window of each text. Without both labels the untrained network is returned."""
    p, r = initial(seed), np.random.default_rng(seed)
    if len(set(labels)) < 2:
        return p
    vocabulary: dict[str, int] = {}
    docs = []
    for t in texts:
        ids = np.array([vocabulary.setdefault(w, len(vocabulary)) for w in words_of_text(t)], dtype=np.int64)
        at = windows(len(ids))
        at = at[np.sort(r.permutation(len(at))[:TRAIN_WINDOWS])]
        docs.append(np.where(at >= 0, ids[np.maximum(at, 0)] if len(ids) else 0, -1))
    words, y = list(vocabulary), np.array(labels, dtype=np.float32)
    if not words:
        return p
    m, v, k = {n: np.zeros_like(x) for n, x in p.items()}, {n: np.zeros_like(x) for n, x in p.items()}, 0
    for epoch in range(epochs):
        order = r.permutation(len(docs))
        for a in range(0, len(order), batch):
            mine = order[a : a + batch]
            at = np.concatenate([docs[i] for i in mine])
            used, local = np.unique(at[at >= 0], return_inverse=True)
            if not len(used):
                continue
            names = [words[i] for i in used]
            own = np.full(at.shape, -1)
            own[at >= 0] = local
            score = logits(p, inputs(p, names), own)
            ends = np.cumsum([len(docs[i]) for i in mine])
            best = np.array([e - len(docs[i]) + int(np.argmax(score[e - len(docs[i]) : e])) for i, e in zip(mine, ends)])
            chosen = own[best]
            used, local = np.unique(chosen[chosen >= 0], return_inverse=True)
            if not len(used):
                continue
            at = np.full(chosen.shape, -1)
            at[chosen >= 0] = local
            _, g = gradient(p, [names[i] for i in used], at, y[mine])
            k += 1
            size = np.sqrt(sum(float((x * x).sum()) for x in g.values()))
            step = rate * (1 if epoch < epochs - 3 else 0.3) * np.sqrt(1 - 0.999**k) / (1 - 0.9**k)
            for n in p:
                x = g[n] * np.float32(min(1, 5 / (size + 1e-9)))
                m[n] += 0.1 * (x - m[n])
                v[n] += 0.001 * (x * x - v[n])
                p[n] -= (step * m[n] / (np.sqrt(v[n]) + 1e-8)).astype(np.float32)
            p["word"] *= np.float32(1 - 1e-3)
    return p


class Scorer:
    """Scores whole texts; keeps the inputs of the words that it has met."""

    def __init__(self, p: dict):
        self.p = p
        self.forget()

    def forget(self) -> None:
        self.rows: dict[str, int] = {}
        self.x = np.zeros((0, 2 * DIM), np.float32)

    def scores(self, texts: list[str | None]) -> list[float]:
        split = [words_of_text(t) for t in texts]
        new = [w for w in dict.fromkeys(w for ws in split for w in ws) if w not in self.rows]
        if len(self.rows) + len(new) > VOCABULARY:
            self.forget()
            new = list(dict.fromkeys(w for ws in split for w in ws))
        if new:
            self.rows.update(zip(new, range(len(self.rows), len(self.rows) + len(new))))
            self.x = np.concatenate([self.x, inputs(self.p, new)])
        x = self.x if len(self.x) else np.zeros((1, 2 * DIM), np.float32)
        held, out = [], np.full(len(texts), -np.inf)
        for ws in split:
            ids = np.fromiter(map(self.rows.__getitem__, ws), np.int64, len(ws))
            at = windows(len(ids))
            held.append(np.where(at >= 0, ids[np.maximum(at, 0)] if len(ids) else 0, -1))
        at, owner = np.concatenate(held), np.repeat(np.arange(len(texts)), [len(x) for x in held])
        for a in range(0, len(at), 2048):
            np.maximum.at(out, owner[a : a + 2048], logits(self.p, x, at[a : a + 2048]))
        return (1 / (1 + np.exp(-np.clip(out, -60, 60)))).tolist()


def fit(docs: DataFrame, labels: DataFrame) -> dict[str, np.ndarray]:
    """Trains on at most POSITIVES and NEGATIVES labelled documents, chosen by a hash of their ids; labels has doc_id and toxic."""
    known = labels.where(F.col("doc_id").isNotNull() & F.col("toxic").isin(0, 1)).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    pick = lambda y, n: known.where(F.col("toxic") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(n)
    chosen = F.broadcast(pick(1, POSITIVES).union(pick(0, NEGATIVES)))
    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).join(chosen, "doc_id").toPandas().sort_values(["doc_id", "text"])
    return train(rows["text"].tolist(), rows["toxic"].tolist())


def score(docs: DataFrame, p: dict) -> DataFrame:
    """doc_id and score of every row, from its whole text alone; null and empty texts get the score of a window without words."""
    sent = docs.sparkSession.sparkContext.broadcast(p)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(sent.value)
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                b = batch.slice(at, 256)
                yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(scorer.scores(b.column("text").to_pylist()))], names=["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, score double")


def held_out(doc_id: Column) -> Column:
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % 3 == 1


def judge(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score and predicted of every document; labels of held-out ones are not read."""
    p = fit(docs, labels.where(~held_out(F.col("doc_id"))))
    return score(docs, p).select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
