"""Quality classifier on supervised subword embeddings.

Words, their character n-grams and pairs of neighbouring words have hashed vectors; a word's vector is the mean of its
features', a document's the mean of its words' and that of its pairs'.  A softmax over two labels follows.  A pair hashes as
the exclusive or of its words' hashes, so order doesn't count, and all pairs of a word with itself share one vector.  All is
learned by stochastic gradient descent in numpy.  Since the output
is linear in the document's vector, a feature's share of the margin is one number, which is all that scoring needs.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corpusdedup.llm.common import marked_draw, slices, text_bytes
from corpusdedup.llm.language import fold
from corpusdedup.llm.subword import BUCKETS, Features, tokens

#: Labelled documents drawn of each label, and bytes of their texts, at most; the size of a vector.
PER_LABEL, BYTES_PER_LABEL, WIDTH = 2000, 6 << 20, 8
THRESHOLD = 0.7


@dataclass
class Scorer:
    grams: np.ndarray  # a feature's share of the margin between the labels
    words: np.ndarray
    pairs: np.ndarray
    bias: float

    def scores(self, texts: list[bytes]) -> np.ndarray:
        ids, distinct, counts = tokens(texts)
        margin = np.zeros(len(texts))
        if len(ids):
            feats = Features(distinct)
            each = feats.sums(self.grams, self.words) / feats.number
            margin = means(each[ids], counts)
            bucket, of = pairs(feats.word[ids], counts)
            margin += means(self.pairs[bucket], np.bincount(of, minlength=len(texts)))
        return 1 / (1 + np.exp(-np.clip(margin + self.bias, -700, 700)))


def means(values: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Mean of each run of so many values, 0 for an empty one."""
    before = np.concatenate(([0.0], np.cumsum(values)))
    ends = np.cumsum(counts)
    return (before[ends] - before[ends - counts]) / np.maximum(counts, 1)


def pairs(hashes: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(bucket, text) of every two neighbouring words of a text, given their hashes."""
    of = np.repeat(np.arange(len(counts)), counts)
    both = of[1:] == of[:-1]
    return (hashes[1:] ^ hashes[:-1])[both], of[1:][both]


def _bags(texts: list[bytes], paired: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Features of each text and their weights: n-grams, then words, then pairs, each shifted by the buckets before."""
    which, weights, sizes = [], [], []
    for t in texts:
        ids, distinct, count = tokens([t])
        if not len(ids):
            sizes.append(0)
            continue
        share = np.bincount(ids, minlength=len(distinct)) / len(ids)
        feats = Features(distinct)
        share = share / feats.number
        w, b = feats.pairs()
        two = pairs(feats.word[ids], count)[0] if paired else np.zeros(0, np.int32)
        own, at = np.unique(np.concatenate((b, feats.word + BUCKETS, two + 2 * BUCKETS)), return_inverse=True)
        which.append(own), weights.append(np.bincount(at, np.concatenate((share[w], share, np.full(len(two), 1 / max(1, len(two))))))), sizes.append(len(own))
    cat = lambda x: np.concatenate(x) if x else np.zeros(0)
    return cat(which).astype(np.int64), cat(weights), np.array(sizes, dtype=np.int64)


def train(texts: list[bytes], labels: list[int], width: int = WIDTH, epochs: int = 8, batch: int = 64, rate: float = 2.0, seed: int = 3, paired: bool = True) -> Scorer:
    """Minibatch stochastic gradient descent on the softmax loss; the rate falls linearly to zero.

    Without ``paired``, pairs of words are left out.
    """
    rng = np.random.default_rng(seed)
    y = np.array(labels, dtype=np.int64)
    if len(set(labels)) < 2:
        only = float(np.mean(y)) if len(y) else 0.5
        return Scorer(np.zeros(BUCKETS), np.zeros(BUCKETS), np.zeros(BUCKETS), float(np.clip(np.log((only + 1e-3) / (1 - only + 1e-3)), -7, 7)))
    which, weights, sizes = _bags(texts, paired)
    starts = np.cumsum(sizes) - sizes
    vectors = ((rng.random((3 * BUCKETS, width)) - 0.5) / width).astype(np.float32)
    out, bias = np.zeros((width, 2)), np.zeros(2)
    steps = epochs * -(-len(y) // batch)
    done = 0
    for _ in range(epochs):
        order = rng.permutation(len(y))
        for k in range(0, len(order), batch):
            docs = order[k : k + batch]
            n = sizes[docs]
            row = np.repeat(np.arange(len(docs)), n)
            at = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n) + np.repeat(starts[docs], n)
            f, w = which[at], weights[at]
            hidden = np.zeros((len(docs), width))
            full = n > 0
            hidden[full] = np.add.reduceat(vectors[f] * w[:, None], (np.cumsum(n) - n)[full], axis=0) if full.any() else 0
            z = hidden @ out + bias
            p = np.exp(z - z.max(axis=1, keepdims=True))
            p /= p.sum(axis=1, keepdims=True)
            p[np.arange(len(docs)), y[docs]] -= 1
            lr = rate * (1 - done / steps)
            back = p @ out.T
            out -= lr * hidden.T @ p / len(docs)
            bias -= lr * p.mean(axis=0)
            # A feature steps by its mean over the documents that have it, so that rare features learn and common ones don't overshoot.
            by = np.argsort(f, kind="stable")
            f, w, row = f[by], w[by], row[by]
            first = np.flatnonzero(np.concatenate(([True], f[1:] != f[:-1]))) if len(f) else np.zeros(0, np.int64)
            if len(first):
                g = np.add.reduceat(back[row] * w[:, None], first, axis=0) / (np.add.reduceat(w, first) + 1e-12)[:, None]
                vectors[f[first]] -= (lr * g).astype(np.float32)
            done += 1
    shares = vectors @ (out[:, 1] - out[:, 0])
    grams, words, two = shares.astype(np.float64).reshape(3, BUCKETS)
    return Scorer(grams, words, two if paired else np.zeros(BUCKETS), float(bias[1] - bias[0]))


def fit(docs: DataFrame, labels: DataFrame, learn: Column, per_label: int = PER_LABEL, bytes_each: int = BYTES_PER_LABEL, paired: bool = True) -> Scorer:
    """Train on a draw of each label among the labelled rows for which ``learn`` holds: at most so many documents and bytes of text."""
    marked = labels.where(learn & F.col("quality").isin(0, 1)).select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("label"))
    held = {r["label"]: r["count"] for r in marked.groupBy("label").count().collect()}  # two rows
    rows = marked_draw(docs, marked, per_label, bytes_each, "quality")
    scorer = train([t for *_, t in rows], [q for _, q, _ in rows], paired=paired)
    if len(held) == 2 and len({q for _, q, _ in rows}) == 2:  # the draw evened the labels out
        drawn_ones = sum(q for _, q, _ in rows)
        scorer.bias += float(np.log(held[1] / held[0]) - np.log(drawn_ones / (len(rows) - drawn_ones)))
    return scorer


def score(docs: DataFrame, scorer: Scorer) -> DataFrame:
    """doc_id and score of each whole text."""
    shared = docs.sparkSession.sparkContext.broadcast(scorer)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text"):
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(shared.value.scores(part.column(1).to_pylist()))], names=["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_bytes().alias("text")).mapInArrow(run, "doc_id long, score double")


def classify(docs: DataFrame, labels: DataFrame, learn: Column | None = None, per_label: int = PER_LABEL, threshold: float = THRESHOLD) -> DataFrame:
    """Fit on the labelled rows for which ``learn`` holds (default: doc_id's fold of four isn't 2), score all documents.

    Returns doc_id, held_out, score, predicted.  Null and empty texts get the score of a text without evidence; repeated
    labels count as often as they occur; other columns are not read; an empty table gives an empty result, and without both
    labels every score says which one there was (0.5 if none).
    """
    scorer = fit(docs, labels, fold(4) != 2 if learn is None else learn, per_label)
    return score(docs, scorer).select("doc_id", F.coalesce(fold(4) == 2, F.lit(False)).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
