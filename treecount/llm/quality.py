"""Quality: random-indexing word vectors pooled per document, a two-layer network in numpy, temperature-calibrated."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import commit, held_out, keep_rows, raw_bytes, ready, slices
from .minhash import BYTE, mix, powers
from .toxicity import labelled_sample

U = np.uint64


@dataclass(frozen=True)
class Settings:
    """Words are hashed to ``1 << bits`` rows; each row has a fixed sparse index vector of ``dims`` with ``nonzero`` signs.

    A row's context vector sums the index vectors of all words within ``reach`` places, over every
    document of the corpus. The network learns from at most ``most_docs`` labelled texts and about
    ``most_chars`` characters in all of each label; one in five of them sets the temperature.
    """

    bits: int = 13
    dims: int = 48
    nonzero: int = 4
    reach: int = 2
    hidden: int = 32
    most_docs: int = 4000
    most_chars: int = 12_000_000
    epochs: int = 60
    rate: float = 0.01
    decay: float = 1e-4
    seed: int = 11


LOW = np.arange(256, dtype=np.uint8)
LOW[65:91] = np.arange(97, 123)
#: Upper case, lower case with all bytes beyond ASCII, digits; other bytes are their own class.
CLASS = np.arange(256, dtype=np.uint8)
CLASS[65:91], CLASS[97:123], CLASS[128:], CLASS[48:58] = 65, 97, 97, 48


def tokens(texts: list[bytes], s: Settings) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows of all words (lower-cased A-Z), rows of their shapes (runs of character classes), and where each text's words begin."""
    lines = [b" ".join(t.split()) for t in texts]
    raw = np.frombuffer(b" ".join(lines) + b" ", np.uint8) if lines else np.zeros(0, np.uint8)
    gaps = raw == 32
    start = np.flatnonzero(~gaps & np.concatenate([[True], gaps[:-1]]))
    end = np.flatnonzero(gaps & np.concatenate([[False], ~gaps[:-1]]))
    up, down = powers(len(raw) + 1)
    sums = np.concatenate([np.zeros(1, U), np.cumsum(BYTE[LOW[raw]] * up[: len(raw)], dtype=U)])
    words = mix((sums[end] - sums[start]) * down[start])
    kind = CLASS[raw]
    fresh = np.concatenate([[True], kind[1:] != kind[:-1]])
    run = np.cumsum(fresh)
    sums = np.concatenate([np.zeros(1, U), np.cumsum(np.where(fresh, BYTE[kind] * up[run], U(0)), dtype=U)])
    shapes = mix((sums[end] - sums[start]) * down[run[start]] + U(1))
    shift = U(64 - s.bits)
    # Empty texts add no word but do add a gap.
    begins = np.cumsum([0, *(len(x) + 1 for x in lines)])
    return (words >> shift).astype(np.int64), (shapes >> shift).astype(np.int64), np.searchsorted(start, begins)


def index_vectors(s: Settings) -> tuple[np.ndarray, np.ndarray]:
    """For each row the places and signs of its index vector."""
    h = mix(np.arange(1, (1 << s.bits) * s.nonzero + 1, dtype=U)).reshape(-1, s.nonzero)
    return (h % U(s.dims)).astype(np.int64), np.where(h >> U(63), 1, -1).astype(np.int64)


def contexts(texts: list[bytes], s: Settings, total: np.ndarray) -> None:
    """Adds to ``total`` (rows x dims, flat, whole numbers) what the words and shapes of these texts meet."""
    place, sign = index_vectors(s)
    words, shapes, first = tokens(texts, s)
    doc = np.repeat(np.arange(len(texts)), np.diff(first))
    for gap in range(1, s.reach + 1):
        near = np.flatnonzero(doc[gap:] == doc[:-gap])
        for left in (words, shapes):
            a, b = left[near], left[near + gap]
            for row, met in ((a, words[near + gap]), (b, words[near]), (a, shapes[near + gap]), (b, shapes[near])):
                total += np.bincount((row[:, None] * s.dims + place[met]).ravel(), sign[met].ravel(), len(total)).astype(np.int64)


def context_table(docs: DataFrame, s: Settings) -> np.ndarray:
    """Context vectors of all rows over the whole corpus, each of length 1. Their size is fixed by the settings."""

    def run(batches):
        total = np.zeros((1 << s.bits) * s.dims, np.int64)
        for batch in batches:
            for some in slices(batch, "text", 1 << 20):
                contexts(raw_bytes(some.column(0)), s, total)
        rows = total.reshape(-1, s.dims)
        used = np.flatnonzero(rows.any(1))
        if len(used):
            yield pa.RecordBatch.from_arrays([pa.array(used), pa.array(list(rows[used]), pa.list_(pa.int64()))], names=["row", "v"])

    part = docs.select(F.col("text").cast("string").alias("text")).mapInArrow(run, "row long, v array<long>")
    sums = commit(part.groupBy("row").agg(*[F.sum(F.get("v", F.lit(k))).alias(f"v{k}") for k in range(s.dims)]), "contexts")
    table = np.zeros((1 << s.bits, s.dims), np.float32)
    found = sums.toPandas()
    table[found["row"].to_numpy()] = found[[f"v{k}" for k in range(s.dims)]].to_numpy()
    norm = np.linalg.norm(table, axis=1, keepdims=True)
    return table / np.maximum(norm, 1e-9)


def index_table(s: Settings) -> np.ndarray:
    place, sign = index_vectors(s)
    table = np.zeros((1 << s.bits, s.dims), np.float32)
    for k in range(s.nonzero):
        np.add.at(table, (np.arange(1 << s.bits), place[:, k]), sign[:, k])
    return table


def pool(texts: list[bytes], table: np.ndarray, s: Settings) -> np.ndarray:
    """Means over a text's words and over their shapes of index and context vectors, then the logarithms of the
    lengths of both mean index vectors (repetition keeps them long) and of the number of words. Zeros without words."""
    words, shapes, first = tokens(texts, s)
    n = np.diff(first)
    out = np.zeros((len(texts), width(table)), np.float32)
    there = np.flatnonzero(n)
    if len(there):
        for k, rows in enumerate((words, shapes)):
            sums = np.stack([np.add.reduceat(column[rows], first[there]) for column in table.T], 1)
            out[there, k * table.shape[1] : (k + 1) * table.shape[1]] = sums / n[there, None]
            start = k * table.shape[1]
            out[there, k - 3] = np.log(np.linalg.norm(out[there, start : start + table.shape[1] // 2], axis=1) + 1e-3)
        out[there, -1] = np.log1p(n[there])
    return out


def width(table: np.ndarray) -> int:
    return 2 * table.shape[1] + 3


@dataclass
class Network:
    mean: np.ndarray
    scale: np.ndarray
    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: float
    temperature: float
    shift: float

    def logits(self, x: np.ndarray) -> np.ndarray:
        return np.tanh((x - self.mean) / self.scale @ self.w1 + self.b1) @ self.w2 + self.b2

    def score(self, x: np.ndarray) -> np.ndarray:
        z = self.logits(x) / self.temperature + self.shift
        return 1 / (1 + np.exp(-np.clip(z, -50, 50)))


def train(x: np.ndarray, y: np.ndarray, prior: float, s: Settings) -> Network:
    """Adam steps on four of five rows, a temperature from the fifth, and a shift from the sample's share of label 1 to the prior."""
    rng = np.random.default_rng(s.seed)
    dims = x.shape[1]
    if len(set(y.tolist())) < 2:
        rate = min(max(float(np.mean(y)) if len(y) else 0.5, 1e-3), 1 - 1e-3)
        return Network(np.zeros(dims), np.ones(dims), np.zeros((dims, 1)), np.zeros(1), np.zeros(1), 0.0, 1.0, float(np.log(rate / (1 - rate))))
    order = rng.permutation(len(y))
    test, fit = order[: len(y) // 5], order[len(y) // 5 :]
    mean, scale = x[fit].mean(0), x[fit].std(0) + 1e-6
    p = [rng.normal(0, dims**-0.5, (dims, s.hidden)), np.zeros(s.hidden), rng.normal(0, s.hidden**-0.5, s.hidden), np.zeros(1)]
    m, v = [np.zeros_like(a) for a in p], [np.zeros_like(a) for a in p]
    step = 0
    for epoch in range(s.epochs):
        rate = s.rate * (1 - epoch / s.epochs) + 1e-4
        fit = rng.permutation(fit)
        for at in range(0, len(fit), 128):
            rows = fit[at : at + 128]
            z = (x[rows] - mean) / scale
            h = np.tanh(z @ p[0] + p[1])
            err = (1 / (1 + np.exp(-np.clip(h @ p[2] + p[3], -50, 50))) - y[rows]) / len(rows)
            back = np.outer(err, p[2]) * (1 - h * h)
            grads = [z.T @ back + s.decay * p[0], back.sum(0), h.T @ err + s.decay * p[2], err.sum(keepdims=True)]
            step += 1
            for a, g, mm, vv in zip(p, grads, m, v, strict=True):
                mm += 0.1 * (g - mm)
                vv += 0.001 * (g * g - vv)
                a -= rate * (mm / (1 - 0.9**step)) / (np.sqrt(vv / (1 - 0.999**step)) + 1e-8)
    net = Network(mean, scale, p[0], p[1], p[2], float(p[3][0]), 1.0, 0.0)
    if len(test):
        z, t = net.logits(x[test]), y[test]
        grid = np.geomspace(0.2, 20, 200)
        net.temperature = float(min(grid, key=lambda c: np.mean(np.logaddexp(0, np.where(t == 1, -z, z) / c))))
    share = float(np.mean(y))
    net.shift = float(np.log(prior / (1 - prior)) - np.log(share / (1 - share)))
    return net


def fit(docs: DataFrame, labels: DataFrame, table: np.ndarray, s: Settings) -> Network:
    sample = labelled_sample(docs, labels, "quality", s.most_docs, s.most_chars)
    counts = {r.quality: r["count"] for r in labels.where(F.col("quality").isin(0, 1) & ~held_out(F.col("doc_id"))).groupBy("quality").count().collect()}
    prior = (counts.get(1, 0) + 1) / (sum(counts.values()) + 2)
    x = [pool([t for t, _ in sample[k : k + 200]], table, s) for k in range(0, len(sample), 200)]
    return train(np.concatenate(x) if x else np.zeros((0, width(table)), np.float32), np.array([k for _, k in sample], np.int64), prior, s)


def tables(docs: DataFrame, s: Settings) -> np.ndarray:
    return np.concatenate([index_table(s), context_table(docs, s)], axis=1)


def score_documents(docs: DataFrame, net: Network, table: np.ndarray, s: Settings, threshold: float = 0.3) -> DataFrame:
    """doc_id, held_out, score and predicted of each row. Null and empty texts pool to zeros and are scored as such."""
    sent = docs.sparkSession.sparkContext.broadcast((net, table))  # fixed by the settings, a few MB

    def run(batches):
        net, table = sent.value
        for batch in batches:
            for some in slices(batch, "text", 1 << 20):
                score = net.score(pool(raw_bytes(some.column(1)), table, s)).astype(np.float64)
                yield pa.RecordBatch.from_arrays([some.column(0), some.column(2), pa.array(score), pa.array((score >= threshold).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), held_out(F.col("doc_id")).alias("held_out"))
    return rows.mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")


def op1(spark: SparkSession, docs: DataFrame, labels: DataFrame, s: Settings = Settings()) -> DataFrame:
    ready(spark)
    table = tables(docs, s)
    return score_documents(docs, fit(docs, labels, table, s), table, s)


def keep_good(docs: DataFrame, net: Network, table: np.ndarray, s: Settings, threshold: float = 0.3) -> DataFrame:
    """The documents, with all their columns, that score at least the threshold."""
    sent = docs.sparkSession.sparkContext.broadcast((net, table))
    return keep_rows(docs, lambda texts: sent.value[0].score(pool(texts, sent.value[1], s)), at_least=threshold)
