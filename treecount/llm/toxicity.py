"""Toxicity: embeddings of hashed character n-grams, averaged by word and then over a text's most toxic words into a linear softmax, trained together in numpy."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import held_out, keep_rows, raw_bytes, ready, slices


@dataclass(frozen=True)
class Settings:
    """Subwords are runs of ``shortest`` to ``longest`` characters inside a word with its boundaries.

    A word is the average of its subwords, a text the average of its ``top`` most toxic words, so a
    long text doesn't dilute a short insult and one odd word doesn't condemn a text; the logarithm of
    a text's number of words is a further input, as longer texts have odder words. The labelled
    sample has at most ``most_docs`` rows and about ``most_chars`` characters in all for each class;
    ``start`` weighs the odds that bucket vectors begin with.
    """

    shortest: int = 3
    longest: int = 6
    bits: int = 18
    dims: int = 8
    top: int = 3
    most_docs: int = 4000
    most_chars: int = 6_000_000
    epochs: int = 8
    rate: float = 0.5
    start: float = 4.0
    seed: int = 7


#: What each ASCII character counts as: letters as themselves in lower case, anything else as a boundary. Characters beyond stand for themselves.
FOLD = np.full(128, 32, np.uint32)
FOLD[97:123] = FOLD[65:91] = np.arange(97, 123)


def subwords(raw: np.ndarray, s: Settings) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of all subwords of folded characters, and the position that each begins at."""
    n = len(raw)
    inside = raw != 32
    h = np.zeros(n, np.uint32)
    valid = np.ones(n, bool)
    buckets, places = [], []
    for k in range(s.longest):
        if n <= k:
            break
        h = h[: n - k] * np.uint32(0x01000193) + raw[k:] + np.uint32(1)
        if k >= 2:
            valid = valid[: n - k] & inside[k - 1 : n - 1]
        else:
            valid = valid[: n - k]
        if k + 1 >= s.shortest:
            at = np.flatnonzero(valid)
            x = h[at] ^ (h[at] >> np.uint32(15))
            x *= np.uint32(0x2C1B3C6D)
            x ^= x >> np.uint32(12)
            x *= np.uint32(0x297A2D39)
            buckets.append(x >> np.uint32(32 - s.bits))
            places.append(at)
    if not buckets:
        return np.zeros(0, np.uint32), np.zeros(0, np.int64)
    return np.concatenate(buckets), np.concatenate(places)


def bags(texts: list[bytes], s: Settings) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Buckets, the word of each, and each word's text. Case is folded first; every character beyond ASCII belongs to a word."""
    pieces = [f" {t.decode().lower()} " for t in texts]
    raw = np.frombuffer("".join(pieces).encode("utf-32-le"), np.uint32)
    raw = np.where(raw < 128, FOLD[np.minimum(raw, 127)], raw)
    gap = raw == 32
    starts = np.flatnonzero(gap[:-1] & ~gap[1:])  # the boundary before each word
    owner = np.searchsorted(np.cumsum([len(p) for p in pieces]), starts, side="right")
    buckets, places = subwords(raw, s)
    return buckets, np.searchsorted(starts, places, side="right") - 1, owner


def highest(z: np.ndarray, owner: np.ndarray, texts: int, top: int) -> np.ndarray:
    """The ``top`` words of each text with the highest z (of equal ones the first), in the order of the text; owner is ascending."""
    words = np.bincount(owner, minlength=texts)
    words = words[words > 0]
    left, picked = np.array(z, np.float64), [np.zeros(0, np.int64)]
    starts = np.cumsum(words) - words
    for _ in range(top if len(words) else 0):
        at = np.flatnonzero(left == np.repeat(np.maximum.reduceat(left, starts), words))
        at = at[np.concatenate([[True], owner[at[1:]] != owner[at[:-1]]])]
        at = at[left[at] > -np.inf]
        left[at] = -np.inf
        picked.append(at)
    return np.sort(np.concatenate(picked))


class Model:
    """logits: for each bucket the difference that its vector makes between the two softmax outputs; with the bias and
    the slope for the logarithm of the number of words all that scoring needs."""

    def __init__(self, logits: np.ndarray, bias: float, slope: float = 0.0):
        self.logits, self.bias, self.slope = logits, bias, slope

    def score(self, texts: list[bytes], s: Settings) -> np.ndarray:
        """Probability of label 1 for each text. A text without words gets what the bias says."""
        if not texts:
            return np.zeros(0)
        buckets, word, owner = bags(texts, s)
        n, words = len(texts), np.bincount(owner, minlength=len(texts))
        z = np.bincount(word, self.logits[buckets], len(owner)) / np.maximum(1, np.bincount(word, minlength=len(owner)))
        pick = highest(z, owner, n, s.top)
        mean = np.bincount(owner[pick], z[pick], n) / np.maximum(1, np.minimum(words, s.top))
        return 1 / (1 + np.exp(-np.clip(mean + self.bias + self.slope * np.log1p(words), -50, 50)))


def train(texts: list[bytes], toxic: np.ndarray, s: Settings, prior: float | None = None) -> Model:
    """Bucket vectors and softmax weights together, by adaptive gradient steps on each text's most toxic words so far.

    The bias is shifted from the texts' share of label 1 to the prior, where one is given.
    """
    rng = np.random.default_rng(s.seed)
    size = 1 << s.bits
    if not len(texts) or len(set(toxic.tolist())) < 2:
        rate = float(np.mean(toxic)) if len(texts) else 0.0
        return Model(np.zeros(size, np.float32), float(np.log((rate + 1e-3) / (1 - rate + 1e-3))))
    vectors = rng.uniform(-1, 1, (size, s.dims)).astype(np.float32) / s.dims
    weights = np.zeros((s.dims, 2), np.float32)
    weights[:, 1] = rng.normal(0, 0.5, s.dims)
    weights[:, 0] = -weights[:, 1]
    flat, edges, owner = flattened(texts, s)
    lens, words = np.diff(edges), np.log1p(np.bincount(owner, minlength=len(texts)))
    center = float(words.mean())
    far = (words - center).astype(np.float32)
    lean = weights[:, 1] - weights[:, 0]
    vectors += np.outer(odds(flat, edges, owner, toxic, size), lean) * (s.start / np.sum(lean**2))
    outer = [weights, np.zeros(2, np.float32), np.zeros(2, np.float32)]  # weights, bias, slope
    seen = [np.full(size, 1e-8, np.float32), *(np.full_like(x, 1e-8) for x in outer)]
    for epoch in range(s.epochs):
        step = s.rate * (1 - epoch / (s.epochs + 1))
        z = vectors @ (outer[0][:, 1] - outer[0][:, 0])
        means = np.concatenate([np.add.reduceat(z[flat[edges[a] : edges[b]]], edges[a:b] - edges[a]) for a, b in spans(edges)] or [np.zeros(0)]) / lens
        pick = highest(means, owner, len(texts), s.top)
        first = np.searchsorted(owner[pick], np.arange(len(texts) + 1))
        order = rng.permutation(np.flatnonzero(np.diff(first)))
        for at in range(0, len(order), 128):
            batch = order[at : at + 128]
            y, held = toxic[batch], np.diff(first)[batch]
            chosen = np.concatenate([pick[first[t] : first[t + 1]] for t in batch])
            of = np.repeat(np.arange(len(batch)), held)
            grams = np.concatenate([flat[edges[w] : edges[w + 1]] for w in chosen])
            share = np.repeat(1 / lens[chosen] / held[of], lens[chosen])  # what a subword counts for in its text
            mean = np.add.reduceat(vectors[grams] * share[:, None], np.concatenate([[0], np.cumsum(lens[chosen])])[np.concatenate([[0], np.cumsum(held)[:-1]])], axis=0)
            logit = mean @ outer[0] + outer[1] + far[batch, None] * outer[2]
            err = np.exp(logit - logit.max(1, keepdims=True))
            err /= err.sum(1, keepdims=True)
            err[np.arange(len(y)), y] -= 1
            back = (err @ outer[0].T)[np.repeat(of, lens[chosen])] * share[:, None]
            used, inverse = np.unique(grams, return_inverse=True)
            grad = np.stack([np.bincount(inverse, back[:, k], len(used)) for k in range(s.dims)], 1).astype(np.float32)
            seen[0][used] += (grad**2).mean(1)
            vectors[used] -= step * grad / np.sqrt(seen[0][used])[:, None]
            for x, g, total in zip(outer, (mean.T @ err / len(y), err.mean(0), (far[batch, None] * err).mean(0)), seen[1:], strict=True):
                total += g**2
                x -= 0.3 * step * g / np.sqrt(total)
    weights, bias, slope = outer
    tilt = float(slope[1] - slope[0])
    return Model((vectors @ (weights[:, 1] - weights[:, 0])).astype(np.float32), float(bias[1] - bias[0]) - tilt * center + shift(float(np.mean(toxic)), prior), tilt)


def shift(share: float, prior: float | None) -> float:
    """What the log odds of label 1 lack when a model has learnt from that share of it."""
    return 0.0 if prior is None or not 0 < prior < 1 else float(np.log(prior / (1 - prior)) - np.log(share / (1 - share)))


def odds(flat: np.ndarray, edges: np.ndarray, owner: np.ndarray, toxic: np.ndarray, size: int) -> np.ndarray:
    """Smoothed log odds of label 1 for texts that have a bucket, against all texts: where vectors begin, so that
    the first choice of words already is a sensible one."""
    share, n = float(toxic.mean()), [np.zeros(size), np.zeros(size)]
    first = edges[np.searchsorted(owner, np.arange(len(toxic) + 1))]
    for d in range(len(toxic)):
        n[toxic[d]][np.unique(flat[first[d] : first[d + 1]])] += 1
    return (np.log((n[1] + 4 * share) / (n[0] + 4 * (1 - share))) - np.log(share / (1 - share))).astype(np.float32)


def flattened(texts: list[bytes], s: Settings) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Buckets of all words that have any, one word after the other; where each word begins; the text of each word."""
    # Filled in place: only what is written takes memory.
    flat = np.empty(sum(len(t) + 2 for t in texts) * (s.longest - s.shortest + 1), np.uint32)
    counts, owners, used = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], 0
    for at in range(0, len(texts), 64):
        buckets, word, owner = bags(texts[at : at + 64], s)
        flat[used : used + len(buckets)] = buckets[np.argsort(word, kind="stable")]
        used += len(buckets)
        n = np.bincount(word, minlength=len(owner))
        counts.append(n[n > 0])
        owners.append(owner[n > 0] + at)
    return flat[:used], np.concatenate([[0], np.cumsum(np.concatenate(counts))]), np.concatenate(owners)


def spans(edges: np.ndarray, most: int = 4 << 20):
    """Ranges of words that hold about ``most`` subwords."""
    group = edges[:-1] // most
    cuts = [0, *(np.flatnonzero(np.diff(group)) + 1).tolist(), len(group)]
    return [(a, b) for a, b in zip(cuts, cuts[1:], strict=False) if b > a]


def learnable(labels: DataFrame, column: str) -> DataFrame:
    """(doc_id, label) of the ids that may be learnt from. A doc_id with contradicting labels teaches nothing."""
    return labels.where(F.col(column).isin(0, 1) & ~held_out(F.col("doc_id"))).groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.min(column).alias("low"), F.max(column).alias("label")).where("low = label").select("doc_id", "label")


def with_text(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).where(F.length("text") > 0)


def labelled_sample(docs: DataFrame, labels: DataFrame, column: str, most_docs: int, most_chars: int) -> list:
    """(text, label) of rows that may be learnt from, in the order of a hash of their id: for each label at most
    ``most_docs`` rows, up to the one that brings them to ``most_chars`` characters in all. Length alone leaves no text out."""
    known = learnable(labels, column)
    # A quarter more, as some ids have no text. Rows and characters are both bounded.
    ids = [known.where(F.col("label") == k).orderBy(F.xxhash64("doc_id"), "doc_id").limit(most_docs + most_docs // 4) for k in (0, 1)]
    chosen = ids[0].union(ids[1]).select("doc_id", "label", F.xxhash64("doc_id").alias("place"))
    found = with_text(docs).join(F.broadcast(chosen), "doc_id")
    earlier = Window.partitionBy("label").orderBy("place", "doc_id", "text").rowsBetween(Window.unboundedPreceding, -1)
    found = found.withColumn("chars", F.coalesce(F.sum(F.length("text")).over(earlier), F.lit(0))).withColumn("rows", F.count("*").over(earlier))
    found = found.where((F.col("chars") < most_chars) & (F.col("rows") < most_docs)).select("label", "place", "doc_id", "text").collect()
    return [(r.text.encode(), r.label) for r in sorted(found)]


def share_of_label(docs: DataFrame, labels: DataFrame, column: str) -> float | None:
    """The share of label 1 among all rows that :func:`labelled_sample` draws from."""
    n = {r.label: r["count"] for r in with_text(docs).select("doc_id").join(learnable(labels, column), "doc_id").groupBy("label").count().collect()}
    return n.get(1, 0) / sum(n.values()) if n else None


def score_documents(docs: DataFrame, model: Model, s: Settings, threshold: float = 0.5) -> DataFrame:
    """doc_id, held_out, score and predicted of each row.

    Null and empty texts get the score of the bias alone; rows that repeat get equal scores; a very long text is
    scored whole, by its most toxic words; an empty table gives no rows; other columns of ``docs`` are not looked at.
    """
    sent = docs.sparkSession.sparkContext.broadcast((model.logits, model.bias, model.slope))  # 4 bytes for each bucket: a fixed size

    def run(batches):
        m = Model(*sent.value)
        for batch in batches:
            for some in slices(batch, "text", 1 << 20):
                score = m.score(raw_bytes(some.column(1)), s)
                yield pa.RecordBatch.from_arrays([some.column(0), some.column(2), pa.array(score), pa.array((score >= threshold).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), held_out(F.col("doc_id")).alias("held_out"))
    return rows.mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")


def fit(docs: DataFrame, labels: DataFrame, s: Settings = Settings()) -> Model:
    sample = labelled_sample(docs, labels, "toxic", s.most_docs, s.most_chars)
    prior = share_of_label(docs, labels, "toxic")
    return train([t for t, _ in sample], np.array([k for _, k in sample], np.int64), s, prior)


def op2(spark: SparkSession, docs: DataFrame, labels: DataFrame, s: Settings = Settings()) -> DataFrame:
    """Learns from the rows of ``labels`` (doc_id, toxic) that are not held out, and scores every row of ``docs``.

    Null labels and ids that are labelled both ways teach nothing; without labels of both kinds every text gets the
    share of label 1. Else as :func:`score_documents`.
    """
    ready(spark)
    return score_documents(docs, fit(docs, labels, s), s)


def drop_toxic(docs: DataFrame, model: Model, s: Settings, threshold: float = 0.5) -> DataFrame:
    """The documents, with all their columns, that score below the threshold."""
    sent = docs.sparkSession.sparkContext.broadcast((model.logits, model.bias, model.slope))
    return keep_rows(docs, lambda texts: Model(*sent.value).score(texts, s), below=threshold)
