"""Toxicity scores from subword-bag embeddings averaged into a linear softmax.

A word is the bag of its character n-grams (with word borders), each n-gram is a row of a hashed embedding table, and a
window of consecutive words is the average of its n-gram vectors, read by a two-class linear softmax.  Table and softmax
are trained together in numpy on a bounded sample of labelled rows.  A document is as toxic as its most toxic window, so
a few words count in a long text.  Unseen misspellings share most n-grams with their originals and hence their vectors.

Because the softmax is linear, a trained model folds into one number per n-gram bucket; scoring is array code over whole
batches.

Defined cases: null or empty text scores the model's prior below the decision threshold; repeated rows score alike;
no usable labels give 0.5 for every row; extra columns of the inputs are ignored.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ratiobin.llm import textgrid as tg
from ratiobin.llm.common import crc_mod, table

#: Most labelled rows of each class that training reads (the sample is the lowest hashes of doc_id).
SAMPLE_PER_CLASS = 1200
BUCKET_BITS = 20
DIMENSIONS = 8
GRAM_SIZES = (3, 4, 5, 6)
WINDOW_WORDS = 16
EPOCHS = 30
THRESHOLD = 0.7


@dataclass(frozen=True)
class FoldedModel:
    """Log-odds per n-gram bucket, bias, and score of a text without words."""

    weights: np.ndarray
    bias: float
    empty_score: float


class GramText:
    """Documents of a batch as padded bytes with word spans, for n-gram positions."""

    def __init__(self, column: pa.Array):
        words = tg.Words(column, tg.NOT_ALNUM)
        shift = np.repeat(np.arange(words.n_docs), words.counts) + 1
        lengths = np.diff(words.offsets)
        data = np.full(len(words.data) + words.n_docs + 8, 0x20, dtype=np.uint8)
        move = np.repeat(np.arange(words.n_docs) + 1, lengths) + np.arange(len(words.data))
        data[move] = np.where(tg.NOT_ALNUM[words.data], np.uint8(0x20), words.data)
        self.starts, self.ends = words.starts + shift, words.ends + shift
        self.first, self.counts, self.n_docs = words.first, words.counts, words.n_docs
        if len(self.starts):  # a word that follows itself counts once, else one repeated word fills a window
            hashes, owner = words.hashes(), words.doc_of_word()
            keep = np.r_[True, (hashes[1:] != hashes[:-1]) | (owner[1:] != owner[:-1])]
            self.starts, self.ends = self.starts[keep], self.ends[keep]
            self.counts = np.bincount(owner[keep], minlength=self.n_docs)
            self.first = np.concatenate(([0], np.cumsum(self.counts)))
        self._hasher = tg.SpanHasher(data)
        self._size = len(data)

    def buckets(self, n: int) -> np.ndarray:
        at = np.arange(self._size - n + 1)
        return (self._hasher.spans(at, at + n) >> np.uint64(64 - BUCKET_BITS)).astype(np.int32)

    def word_grams(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        """First n-gram position of each word and number of its n-grams (borders count as characters)."""
        return self.starts - 1, np.maximum(self.ends - self.starts + 3 - n, 0)


def window_edges(counts: np.ndarray, first: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Word ranges of half-overlapping windows that cover every word, and the windows of each document."""
    step = size // 2
    n_windows = np.where(counts > 0, np.maximum(-(-(counts - size) // step), 0) + 1, 0)
    doc = np.repeat(np.arange(len(counts)), n_windows)
    rank = np.arange(len(doc)) - np.repeat(np.cumsum(n_windows) - n_windows, n_windows)
    begin = np.asarray(first)[doc] + rank * step
    return begin, np.minimum(begin + size, first[doc] + counts[doc]), doc


def doc_scores(column: pa.Array, model: FoldedModel) -> np.ndarray:
    text = GramText(column)
    out = np.full(text.n_docs, model.empty_score)
    if not len(text.starts):
        return out
    total = np.zeros(len(text.starts))
    grams = np.zeros(len(text.starts))
    for n in GRAM_SIZES:
        running = np.concatenate(([0.0], np.cumsum(model.weights[text.buckets(n)], dtype=np.float64)))
        at, size = text.word_grams(n)
        at = np.minimum(at, len(running) - 1)
        total += running[np.minimum(at + size, len(running) - 1)] - running[at]
        grams += size
    begin, end, doc = window_edges(text.counts, text.first, WINDOW_WORDS)
    sums = np.concatenate(([0.0], np.cumsum(total)))
    sizes = np.concatenate(([0.0], np.cumsum(grams)))
    logit = (sums[end] - sums[begin]) / np.maximum(sizes[end] - sizes[begin], 1.0) + model.bias
    best = np.full(text.n_docs, -np.inf)
    np.maximum.at(best, doc, logit)
    has = text.counts > 0
    out[has] = 1.0 / (1.0 + np.exp(-np.clip(best[has], -60, 60)))
    return out


def _training_docs(texts: list[str]) -> list[tuple[np.ndarray, np.ndarray]]:
    """For each text its n-gram buckets in word order and the offset of each word."""
    docs = []
    for text in texts:
        grid = GramText(pa.array([text]))
        parts, owner = [], []
        for n in GRAM_SIZES:
            at, size = grid.word_grams(n)
            word = np.repeat(np.arange(len(at)), size)
            inner = np.arange(len(word)) - np.repeat(np.cumsum(size) - size, size)
            parts.append(grid.buckets(n)[at[word] + inner])
            owner.append(word)
        owner = np.concatenate(owner)
        order = np.argsort(owner, kind="stable")
        docs.append((np.concatenate(parts)[order], np.searchsorted(owner[order], np.arange(len(grid.starts) + 1))))
    return docs


def train(texts: list[str], labels: list[int], seed: int = 7) -> FoldedModel:
    """Fit embedding table and softmax together; windows with the highest score stand for their documents."""
    size = 1 << BUCKET_BITS
    keep = [i for i, t in enumerate(texts) if t]
    y = np.array([labels[i] for i in keep], dtype=np.int64)
    if len(set(y.tolist())) < 2:
        return FoldedModel(np.zeros(size, dtype=np.float32), 0.0, 0.5)
    docs = _training_docs([texts[i] for i in keep])
    usable = [i for i, (_, w) in enumerate(docs) if len(w) > 1]
    docs, y = [docs[i] for i in usable], y[usable]

    rng = np.random.default_rng(seed)
    seen = np.zeros((2, size))
    for (ids, _), label in zip(docs, y, strict=True):
        seen[label, np.unique(ids)] += 1
    share = (seen + 0.5) / (np.bincount(y, minlength=2)[:, None] + 1.0)
    table_ = rng.normal(0, 0.05, (size, DIMENSIONS)).astype(np.float32)
    table_[:, 0] += np.log(share[1] / share[0])
    soft = rng.normal(0, 0.05, (DIMENSIONS, 2))
    soft[0] = (-2.0, 2.0)
    bias = np.zeros(2)
    square = np.full((size, DIMENSIONS), 1e-2, dtype=np.float32)
    soft_square, bias_square = np.full_like(soft, 1e-2), np.full(2, 1e-2)

    edges = [window_edges(np.array([len(w) - 1]), np.array([0]), WINDOW_WORDS)[:2] for _, w in docs]
    rate, decay, balance = 0.5, 1e-5, len(y) / (2.0 * np.bincount(y, minlength=2))
    for _ in range(EPOCHS):
        fold = table_ @ (soft[:, 1] - soft[:, 0]).astype(np.float32)
        chosen = []
        for (ids, w), (begin, end) in zip(docs, edges, strict=True):
            sums = np.concatenate(([0.0], np.cumsum(fold[ids], dtype=np.float64)))
            i = int(np.argmax((sums[w[end]] - sums[w[begin]]) / np.maximum(w[end] - w[begin], 1)))
            chosen.append(ids[w[begin[i]] : w[end[i]]])
        for batch in np.array_split(rng.permutation(len(docs)), max(1, len(docs) // 64)):
            ids = np.concatenate([chosen[i] for i in batch])
            sizes = np.array([len(chosen[i]) for i in batch])
            mean = np.add.reduceat(table_[ids], np.cumsum(sizes) - sizes) / sizes[:, None]
            z = mean @ soft + bias
            p = np.exp(z - z.max(1, keepdims=True))
            p /= p.sum(1, keepdims=True)
            p[np.arange(len(batch)), y[batch]] -= 1
            p *= balance[y[batch]][:, None] / len(batch)
            g_soft, g_bias = mean.T @ p + decay * soft, p.sum(0)
            g_rows = np.repeat((p @ soft.T) / sizes[:, None] * len(batch), sizes, axis=0).astype(np.float32)
            rows, inverse = np.unique(ids, return_inverse=True)
            g = np.zeros((len(rows), DIMENSIONS), dtype=np.float32)
            np.add.at(g, inverse, g_rows)
            square[rows] += g * g
            table_[rows] -= rate * g / np.sqrt(square[rows])
            soft_square += g_soft**2
            soft -= 0.1 * g_soft / np.sqrt(soft_square)
            bias_square += g_bias**2
            bias -= 0.1 * g_bias / np.sqrt(bias_square)
    fold = (table_ @ (soft[:, 1] - soft[:, 0])).astype(np.float32)
    fold[(seen.sum(0) == 0)] = 0.0
    prior = float(y.mean())
    return FoldedModel(fold, float(bias[1] - bias[0]), min(prior, THRESHOLD / 2))


def labelled_sample(docs: DataFrame, labels: DataFrame, per_class: int = SAMPLE_PER_CLASS) -> tuple[list[str], list[int]]:
    """At most per_class labelled texts of each class outside the held-out third, the lowest id hashes first.

    Of several texts with one id the first in order of their bytes is taken; an id with both labels counts as toxic.
    """
    one = (
        labels.where((crc_mod("doc_id", 3) != 1) & F.col("toxic").isNotNull())
        .groupBy("doc_id").agg(F.max(F.col("toxic").cast("int")).alias("toxic"))
    )
    order = F.xxhash64("doc_id")
    picks = one.where("toxic = 1").orderBy(order, "doc_id").limit(per_class).unionByName(one.where("toxic = 0").orderBy(order, "doc_id").limit(per_class))
    texts = docs.select("doc_id", "text").join(F.broadcast(picks), "doc_id").groupBy("doc_id", "toxic").agg(F.min("text").alias("text"))
    rows = texts.collect()  # 2 * per_class rows at most
    rows = sorted(rows, key=lambda r: r["doc_id"])
    return [r["text"] or "" for r in rows], [r["toxic"] for r in rows]


def fit(docs: DataFrame, labels: DataFrame, per_class: int = SAMPLE_PER_CLASS) -> FoldedModel:
    return train(*labelled_sample(docs, labels, per_class))


def scorer(model: FoldedModel, name: str = "score") -> Callable:
    """mapInArrow function: adds a score to whole rows that have a `text` column."""

    def run(batches):
        for batch in tg.slices(batches):
            score = pa.array(doc_scores(batch.column(batch.schema.get_field_index("text")), model), pa.float64())
            yield pa.RecordBatch.from_arrays([*batch.columns, score], [*batch.schema.names, name])

    return run


def score(docs: DataFrame, model: FoldedModel, name: str = "score") -> DataFrame:
    """docs plus a score column; one output row for each input row."""
    schema = T.StructType([*docs.schema.fields, T.StructField(name, T.DoubleType())])
    return docs.mapInArrow(scorer(model, name), schema)


def op3_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = fit(docs, table(spark, sf_dir, "labels").select("doc_id", "toxic"))
    scored = score(docs, model)
    return scored.select(
        "doc_id", (crc_mod("doc_id", 3) == 1).alias("held_out"), "score",
        (F.col("score") >= THRESHOLD).cast("int").alias("predicted"),
    )
