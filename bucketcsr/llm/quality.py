"""Supervised subword embeddings for text quality.

Words, word pairs and the character n-grams of each word are hashed to learned vectors; a text is the mean of its
features' vectors, and a softmax layer turns the mean into class probabilities. NumPy stochastic gradient descent
trains vectors and output layer on a bounded, documented sample of labelled rows (`sample` rows, the smallest hashes).
Because the mean is linear, each feature's vector can be replaced by its logit before scoring: executors get one
number for each of the `buckets` features, and score whole texts in one Arrow pass without a shuffle.

Null and empty texts have no features and get the output layer's bias alone. Null labels, labels other than
0 and 1 and labels without a document are ignored; repeated labels count as often as they occur. Without two
classes the score is the smoothed share of label 1. Empty table: empty result.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F, types as T

from . import words as W
from .shared import fresh, map_text


@dataclass(frozen=True)
class Subwords:
    buckets: int = 1 << 16
    shortest: int = 3
    longest: int = 5
    width: int = 16
    epochs: int = 8
    rate: float = 0.4
    sample: int = 3000  # labelled rows at most
    seed: int = 7


@dataclass
class Model:
    logits: np.ndarray  # of label 1 against label 0, by bucket
    bias: float


def _features(texts: pa.Array, spec: Subwords) -> tuple[W.Words, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Words; each word's number; by number: word bucket; all n-gram buckets in a row and their n + 1 offsets."""
    words = W.split(*W.flat(texts))
    ids, distinct = words.encoded()
    points, offsets = W.code_points(distinct)
    lengths = np.diff(offsets) + 2
    edges = np.zeros(len(lengths) + 1, np.int64)
    np.cumsum(lengths, out=edges[1:])
    framed = np.empty(edges[-1], np.uint64)
    framed[edges[:-1]] = 1  # marks where a word begins
    framed[edges[1:] - 1] = 2
    inside = np.ones(len(framed), bool)
    inside[edges[:-1]] = inside[edges[1:] - 1] = False
    framed[inside] = points
    owner = np.repeat(np.arange(len(lengths)), lengths)
    place = np.arange(len(framed)) - edges[owner]
    total = np.zeros(len(framed) + 1, np.uint64)
    np.cumsum(W.mixed(framed + (place.astype(np.uint64) << np.uint64(24))), out=total[1:])
    word_hash = W.mixed(total[edges[1:]] - total[edges[:-1]])
    grams, owners = [], []
    mask = np.uint64(spec.buckets - 1)
    for n in range(spec.shortest, spec.longest + 1):
        at = np.flatnonzero(place + n <= lengths[owner])
        h = np.full(len(at), n, np.uint64)
        for k in range(n):
            h = h * np.uint64(0x9E3779B97F4A7C15) + framed[at + k]
        grams.append((W.mixed(h) & mask).astype(np.int64))
        owners.append(owner[at])
    gram, own = np.concatenate(grams), np.concatenate(owners)
    order = np.argsort(own, kind="stable")
    gram_offsets = np.zeros(len(lengths) + 1, np.int64)
    np.cumsum(np.bincount(own, minlength=len(lengths)), out=gram_offsets[1:])
    return words, ids, word_hash, gram[order], gram_offsets


def _pairs(words: W.Words, ids: np.ndarray, word_hash: np.ndarray, spec: Subwords) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of neighbouring words, and the first pair of each text (n + 1).

    A word that follows itself gives, whatever the word, the one pair "again".
    """
    if len(ids) < 2:
        return np.zeros(0, np.int64), np.zeros(len(words.first), np.int64)
    h = word_hash[ids]
    doc = words.doc
    same = doc[1:] == doc[:-1]
    pair = np.where(ids[1:] == ids[:-1], np.uint64(0xA6A1), h[:-1] * np.uint64(3) + h[1:])
    bucket = (W.mixed(pair) & np.uint64(spec.buckets - 1)).astype(np.int64)[same]
    return bucket, np.searchsorted(doc[1:][same], np.arange(len(words.first)))


def sparse(texts: pa.Array, spec: Subwords) -> list[tuple[np.ndarray, np.ndarray]]:
    """(buckets, counts) of each text."""
    words, ids, word_hash, gram, at = _features(texts, spec)
    pair, pair_at = _pairs(words, ids, word_hash, spec)
    own = (word_hash & np.uint64(spec.buckets - 1)).astype(np.int64)
    out = []
    for i in range(len(words.first) - 1):
        number, n = np.unique(ids[words.first[i] : words.first[i + 1]], return_counts=True)
        size = at[number + 1] - at[number]
        spans = np.repeat(at[number] - np.concatenate(([0], np.cumsum(size)[:-1])), size) + np.arange(size.sum()) if len(number) else np.zeros(0, np.int64)
        feats = np.concatenate((own[number], gram[spans], pair[pair_at[i] : pair_at[i + 1]]))
        times = np.concatenate((n, np.repeat(n, size), np.ones(pair_at[i + 1] - pair_at[i], np.int64)))
        counts = np.bincount(feats, weights=times, minlength=0)
        some = np.flatnonzero(counts)
        out.append((some, counts[some]))
    return out


def train(rows: list[tuple[np.ndarray, np.ndarray]], labels: np.ndarray, spec: Subwords) -> Model:
    """Stochastic gradient descent over (buckets, counts) rows; steps are normalised by each row's own length."""
    share = (labels.sum() + 1) / (len(labels) + 2)
    prior = float(np.log(share / (1 - share)))
    if len(np.unique(labels)) < 2:
        return Model(np.zeros(spec.buckets, np.float32), prior)
    rng = np.random.default_rng(spec.seed)
    vectors = rng.uniform(-1 / spec.width, 1 / spec.width, (spec.buckets, spec.width)).astype(np.float32)
    out = rng.normal(0, 0.5, (2, spec.width)).astype(np.float32)
    bias = np.array([0.0, prior])
    steps, done = spec.epochs * len(rows), 0
    for _ in range(spec.epochs):
        for i in rng.permutation(len(rows)):
            rate = spec.rate * (1 - done / steps)
            done += 1
            at, counts = rows[i]
            if not len(at):
                continue
            weight = (counts / counts.sum()).astype(np.float32)
            hidden = weight @ vectors[at]
            z = out @ hidden + bias
            p = np.exp(z - z.max())
            p /= p.sum()
            p[labels[i]] -= 1
            back = out.T @ p.astype(np.float32)
            out -= rate * np.outer(p, hidden).astype(np.float32)
            bias -= 0.1 * rate * p
            vectors[at] -= (rate / float(weight @ weight)) * np.outer(weight, back)
    return Model((vectors @ (out[1] - out[0])).astype(np.float32), float(bias[1] - bias[0]))


def scores(texts: pa.Array, model: Model, spec: Subwords) -> np.ndarray:
    """Probability of label 1 for each text."""
    words, ids, word_hash, gram, at = _features(texts, spec)
    pair, pair_at = _pairs(words, ids, word_hash, spec)
    own = (word_hash & np.uint64(spec.buckets - 1)).astype(np.int64)
    logits = model.logits.astype(np.float64)
    by_word = logits[own] + W.sums(logits[gram], at)
    size = 1 + np.diff(at)
    total = W.sums(by_word[ids], words.first) + W.sums(logits[pair], pair_at)
    n = W.sums(size[ids], words.first) + np.diff(pair_at)
    return 1 / (1 + np.exp(-np.clip(model.bias + total / np.maximum(n, 1), -60, 60)))


def remainder(doc_id: Column, by: int) -> Column:
    """crc32 of the id as text, modulo `by`; null for a null id."""
    return F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(by))


def fit(docs: DataFrame, labels: DataFrame, learn: Column, doc_id: str = "doc_id", text: str = "text", label: str = "quality", spec: Subwords = Subwords()) -> Model:
    """Learns from labelled rows where `learn` (over a column `k`, the id) holds; at most spec.sample rows reach the driver."""
    rank = F.xxhash64(F.lit(spec.seed), F.col("k"))
    chosen = labels.select(F.col(f"`{doc_id}`").alias("k"), F.col(f"`{label}`").cast("int").alias("y")).where(F.col("y").isin(0, 1) & F.col("k").isNotNull() & learn)
    chosen = chosen.orderBy(rank, "k", "y").limit(spec.sample)
    rows = docs.select(F.col(f"`{doc_id}`").alias("k"), F.col(f"`{text}`").alias("t")).join(F.broadcast(chosen), "k")
    fields = [T.StructField("at", T.BinaryType()), T.StructField("counts", T.BinaryType())]

    def make(texts: pa.Array) -> list[pa.Array]:
        made = sparse(texts, spec)
        return [pa.array([a.astype(np.uint32).tobytes() for a, _ in made], pa.binary()), pa.array([c.astype(np.float32).tobytes() for _, c in made], pa.binary())]

    table = map_text(rows, "t", fields, make, ["k", "y"]).orderBy(rank, "k", "y", F.xxhash64("at", "counts")).limit(spec.sample).toArrow()
    y = np.array(table.column("y").to_pylist(), np.int64)
    pairs = [(np.frombuffer(a, np.uint32).astype(np.int64), np.frombuffer(c, np.float32)) for a, c in zip(table.column("at").to_pylist(), table.column("counts").to_pylist(), strict=True)]
    return train(pairs, y, spec)


def classify(docs: DataFrame, model: Model, text: str = "text", keep: list[str] | None = None, spec: Subwords = Subwords()) -> DataFrame:
    """keep columns (default: all of docs) + score (double)."""
    keep = [c for c in (docs.columns if keep is None else keep) if c.lower() != "score"]
    return map_text(docs, text, [T.StructField("score", T.DoubleType())], lambda t: [pa.array(scores(t, model, spec))], keep)


def score_documents(docs: DataFrame, labels: DataFrame, doc_id: str = "doc_id", spec: Subwords = Subwords()) -> DataFrame:
    """doc_id, held_out, score, predicted: learns from rows whose id's crc32 mod 3 is not 1, scores every row."""
    model = fit(docs, labels, remainder(F.col("k"), 3) != 1, doc_id, spec=spec)
    scored = classify(docs, model, keep=[doc_id], spec=spec)
    held = F.coalesce(remainder(F.col(f"`{doc_id}`"), 3) == 1, F.lit(False))
    return scored.select(F.col(f"`{doc_id}`"), held.alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
