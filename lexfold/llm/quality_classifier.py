"""Quality classifier by positive-unlabelled learning.

A small network over style features of a text is trained on trusted positives and unlabelled texts. Its
loss is the non-negative unbiased risk: with class prior p, positives' loss as positives weighs p, and
unlabelled texts' loss as negatives, less p times that of positives as negatives, is kept from going
below zero; where it would, its gradient is reversed. The score is the network's probability.

The prior is estimated from positives and unlabelled texts alone: a network is taught to tell the two
apart on half of them, and another on the other half; on the half that each has not seen, the share of unlabelled texts over a cut, divided by the share
of positives over it, is an upper bound of the prior at every cut, and the cut where that bound is least
with a margin for the samples' sizes is taken. Negative labels are never read.

Only the fit works on bounded samples (parameters: most_positive, most_unlabelled), the same on every
run; all documents are scored, over their whole texts. Rows that are held out are in no sample.

Cases. Null and empty texts have features like any other and get a score. Without positives or
unlabelled learning rows every score is 0.5. Rows are returned one for one, null and repeated doc_ids
too; of the rows of a repeated doc_id, samples take what fits their bound. Other columns are ignored;
tables may be empty.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import byte_texts, held_out, mix, parts, slices, table, word_hashes

#: Byte classes, each a feature: its share of the text's bytes.
CLASSES = (b"abcdefghijklmnopqrstuvwxyz", b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"0123456789", b" \t", b"\n\r", b".", b",", b"!?", b"#*$%&", b"|<>", b"\"'()[]{}", b":;/\\=_+-@~^`", bytes(range(128, 256)))
_CLASS = np.full(256, len(CLASSES), np.uint8)
for _k, _c in enumerate(CLASSES):
    _CLASS[list(_c)] = _k
N_FEATURES = len(CLASSES) + 8


def features(texts: list[bytes]) -> np.ndarray:
    """Shares of byte classes, and counts and repetition of words, of whole texts."""
    out = np.zeros((len(texts), N_FEATURES), np.float32)
    for lo, hi in slices([len(t) for t in texts]):
        part = texts[lo:hi]
        size = np.array([len(t) for t in part])
        which = _CLASS[np.frombuffer(b"".join(part), np.uint8)].astype(np.int64)
        doc = np.repeat(np.arange(len(part)), size)
        share = np.bincount(doc * (len(CLASSES) + 1) + which, minlength=len(part) * (len(CLASSES) + 1)).reshape(len(part), -1)[:, : len(CLASSES)]
        words, begins = word_hashes(part)
        n = np.diff(begins)
        x = out[lo:hi]
        x[:, : len(CLASSES)] = share / np.maximum(size, 1)[:, None]
        k = len(CLASSES)
        x[:, k] = np.log1p(size) / 10
        x[:, k + 1] = np.log1p(n) / 10
        x[:, k + 2] = size / np.maximum(n, 1) / 20
        x[:, k + 3] = n == 0
        pairs = mix(words[:-1] + words[1:] * np.uint64(3)) if len(words) > 1 else words[:0]
        for i, (a, b) in enumerate(zip(begins[:-1].tolist(), begins[1:].tolist(), strict=True)):
            if b > a:
                kinds, often = np.unique(words[a:b], return_counts=True)
                x[i, k + 4] = len(kinds) / (b - a)
                x[i, k + 5] = often.max() / (b - a)
                x[i, k + 6] = (words[a + 1 : b] == words[a : b - 1]).sum() / (b - a)
            if b - a > 1:
                x[i, k + 7] = len(np.unique(pairs[a : b - 1])) / (b - a - 1)
    return out


class PuNetwork:
    """One hidden layer; weights are found by Adam on the non-negative unbiased risk."""

    def __init__(self, prior: float, hidden: int = 32, seed: int = 7):
        self.prior, self.hidden, self.seed = prior, hidden, seed
        self.weights: list[np.ndarray] | None = None

    def _forward(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        w1, b1, w2, b2 = self.weights
        h = np.tanh((x - self.mean) / self.std @ w1 + b1)
        return h, h @ w2 + b2[0]

    def score(self, x: np.ndarray) -> np.ndarray:
        if self.weights is None:
            return np.full(len(x), self.prior)
        return 1 / (1 + np.exp(-np.clip(self._forward(x)[1], -40, 40)))

    def fit(self, positive: np.ndarray, unlabelled: np.ndarray, rounds: int = 1500, batch: int = 1024, rate: float = 0.01, decay: float = 1e-4, apart: bool = False) -> PuNetwork:
        """apart: tell positives from unlabelled texts, instead of from negatives."""
        if not len(positive) or not len(unlabelled) or not 0 < self.prior <= 1:
            return self
        rng = np.random.default_rng(self.seed)
        both = np.concatenate((positive, unlabelled)).astype(np.float64)
        self.mean, self.std = both.mean(0), both.std(0) + 1e-3
        self.weights = [rng.normal(0, both.shape[1] ** -0.5, (both.shape[1], self.hidden)), np.zeros(self.hidden), rng.normal(0, self.hidden**-0.5, self.hidden), np.zeros(1)]
        m = [np.zeros_like(w) for w in self.weights]
        v = [np.zeros_like(w) for w in self.weights]
        p = self.prior
        for step in range(1, rounds + 1):
            xp = positive[rng.integers(0, len(positive), batch)]
            xu = unlabelled[rng.integers(0, len(unlabelled), batch)]
            x = np.concatenate((xp, xu)).astype(np.float64)
            h, z = self._forward(x)
            q = 1 / (1 + np.exp(-np.clip(z, -40, 40)))
            if apart:
                g = np.concatenate((q[:batch] - 1, q[batch:])) / batch
            else:
                as_negative = np.logaddexp(0, z)
                rest = as_negative[batch:].mean() - p * as_negative[:batch].mean()
                g_rest = np.concatenate((-p * q[:batch], q[batch:])) / batch
                g = np.concatenate((p * (q[:batch] - 1) / batch, np.zeros(batch))) + g_rest if rest >= 0 else -g_rest
            w1, _, w2, _ = self.weights
            gh = np.outer(g, w2) * (1 - h * h)
            grads = [((x - self.mean) / self.std).T @ gh + decay * w1, gh.sum(0), h.T @ g + decay * w2, np.array([g.sum()])]
            now = rate * (1 - step / rounds) + 1e-4
            for k, d in enumerate(grads):
                m[k] = 0.9 * m[k] + 0.1 * d
                v[k] = 0.999 * v[k] + 0.001 * d * d
                self.weights[k] = self.weights[k] - now * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.999**step)) + 1e-8)
        return self


def least_ratio(positive: np.ndarray, unlabelled: np.ndarray, margin: float = 0.1) -> float:
    """Upper bound of the share of positives among unlabelled rows, from scores that are higher for positives.

    Over any cut, unlabelled rows are at least as many as the prior times the share of positives there. The
    cut is the one where that ratio is least when both shares may be off by as much as samples of their
    sizes are with probability 1 - margin.
    """
    cuts = np.unique(np.concatenate((positive, unlabelled)))
    over = lambda x: 1 - np.searchsorted(np.sort(x), cuts) / len(x)
    of_positive, of_unlabelled = over(positive), over(unlabelled)
    off = sum(math.sqrt(math.log(4 / margin) / (2 * len(x))) for x in (positive, unlabelled))
    ok = of_positive > 0
    at = np.argmin((of_unlabelled[ok] + off) / of_positive[ok])
    return float(min(1.0, of_unlabelled[ok][at] / of_positive[ok][at]))


def estimated_prior(positive: np.ndarray, unlabelled: np.ndarray, rounds: int = 300, decay: float = 0.03) -> float:
    """Share of positives among the unlabelled; 0.5 where there is too little to learn from."""
    if len(positive) < 2 or len(unlabelled) < 2:
        return 0.5
    scores: list[tuple[np.ndarray, np.ndarray]] = []
    for k in (0, 1):  # each half is scored by a network that has seen the other
        told = PuNetwork(0.5).fit(positive[k::2], unlabelled[k::2], rounds, decay=decay, apart=True)
        scores.append((told.score(positive[1 - k :: 2]), told.score(unlabelled[1 - k :: 2])))
    return max(1e-3, least_ratio(*map(np.concatenate, zip(*scores, strict=True))))


def risk(z_positive: np.ndarray, z_unlabelled: np.ndarray, prior: float) -> float:
    """Non-negative unbiased risk of these outputs under the logistic loss."""
    rest = np.logaddexp(0, z_unlabelled).mean() - prior * np.logaddexp(0, z_positive).mean()
    return float(prior * np.logaddexp(0, -z_positive).mean() + max(0.0, rest))


def _sampled(docs: DataFrame, ids: DataFrame, most: int) -> np.ndarray:
    """Features of at most `most` rows of docs with these ids, by hash order."""
    chosen = ids.select("doc_id").distinct().orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in parts(batches):
            x = features(byte_texts(part.column(1)))
            flat = pa.array(x.ravel())
            yield pa.RecordBatch.from_arrays([part.column(0), pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1) * N_FEATURES, pa.int32()), flat)], ["doc_id", "x"])

    made = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").mapInArrow(run, "doc_id long, x array<float>")
    rows = made.orderBy(F.xxhash64("doc_id"), "doc_id", "x").limit(most).collect()
    return np.array([r.x for r in rows], np.float32).reshape(-1, N_FEATURES)


def train(docs: DataFrame, labels: DataFrame, most_positive: int = 6_000, most_unlabelled: int = 12_000) -> PuNetwork:
    """Fit on learning rows alone (those not held out); of labels (doc_id, quality) only the good ones are read."""
    trusted = labels.where("quality = 1 and doc_id is not null").where(~held_out())
    positive = _sampled(docs, trusted, most_positive)
    unlabelled = _sampled(docs, docs.select("doc_id").where("doc_id is not null").where(~held_out()), most_unlabelled)
    return PuNetwork(estimated_prior(positive, unlabelled)).fit(positive, unlabelled)


def score(docs: DataFrame, model: PuNetwork) -> DataFrame:
    """doc_id and score of every row of docs (doc_id, text)."""
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in parts(batches):
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sent.value.score(features(byte_texts(part.column(1)))).astype(np.float64))], ["doc_id", "score"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, score double")


def op2_quality_classifier(spark: SparkSession, sf_dir: str, least: float = 0.3) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = train(docs, table(spark, sf_dir, "labels"))
    return score(docs, model).select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= least).cast("int").alias("predicted"))
