"""Linear text scores over hashed word and character n-gram features: training in numpy, scoring in Arrow batches.

A text's words are its runs of non-space characters. Features: each word, each pair of neighbouring words, and each
character n-gram of "<word>"; all hashed into one table. Both trained models here end up as one number a feature, so
a word's share of a score is worked out once and kept by word; a text costs one lookup for each of its words.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Words, fold, mix64

MUL = np.uint64(0x9E3779B97F4A7C15)
#: Words whose shares a worker keeps; beyond that it starts anew. Bounds memory, changes no result.
MAX_KEPT = 400_000


def word_hashes(words: list[bytes], orders: tuple[int, ...]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(hash of each word, word number of each n-gram, hash of each n-gram) for n in orders, over "<word>"."""
    text = "".join(f"<{w.decode('utf-8', 'replace')}>" for w in words)
    codes = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    lengths = np.fromiter((len(w.decode("utf-8", "replace")) + 2 for w in words), np.int64, len(words))
    starts = np.cumsum(lengths) - lengths
    # a word's hash: sum of its mixed (character, place) values, mixed once more
    place = np.arange(len(codes), dtype=np.int64) - np.repeat(starts, lengths)
    each = mix64((codes << np.uint64(32)) ^ place.astype(np.uint64) * MUL)
    whole = mix64(np.add.reduceat(each, starts)) if len(words) else np.zeros(0, np.uint64)
    of = np.repeat(np.arange(len(words)), lengths)
    left = np.repeat(starts + lengths, lengths) - np.arange(len(codes))  # characters from here to the word's end
    nums, grams = [], []
    for n in orders:
        at = np.flatnonzero(left >= n)
        h = np.full(len(at), n, np.uint64)
        for k in range(n):
            h = (h ^ codes[at + k]) * MUL
            h ^= h >> np.uint64(29)
        nums.append(of[at])
        grams.append(mix64(h))
    empty = np.zeros(0, np.int64)
    return whole, np.concatenate(nums) if nums else empty, np.concatenate(grams) if grams else empty.astype(np.uint64)


def pair_hashes(h: np.ndarray) -> np.ndarray:
    """Hash of each word and the next; a word before itself is one feature whatever the word."""
    return np.where(h[:-1] == h[1:], MUL, mix64(h[:-1] * MUL + h[1:]))


def features(words: list[bytes], orders: tuple[int, ...], buckets: int) -> tuple[np.ndarray, np.ndarray]:
    """(bucket, count) of a text's features."""
    if not words:
        return np.zeros(0, np.int64), np.zeros(0)
    own = Words()
    ids = own.ids(words)
    whole, of, grams = word_hashes(list(own), orders)
    times = np.bincount(ids, minlength=len(own))
    at = np.concatenate([whole, grams, pair_hashes(whole[ids])]) % np.uint64(buckets)
    n = np.concatenate([times, times[of], np.ones(max(len(ids) - 1, 0), np.int64)])
    found, inverse = np.unique(at.astype(np.int64), return_inverse=True)
    return found, np.bincount(inverse, n, len(found))


@dataclass(frozen=True)
class Model:
    """One weight a bucket; a text's raw score is bias + the mean weight of its features ("features") or their sum by word ("words")."""

    weights: np.ndarray
    bias: float
    orders: tuple[int, ...]
    mean_over: str
    slope: float = 1.0
    shift: float = 0.0

    def probability(self, raw: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.slope * raw + self.shift, -40, 40)))


@dataclass
class Scorer:
    """Raw scores of texts under a model, with the shares of words seen kept."""

    model: Model
    words: Words = field(default_factory=Words)

    def __post_init__(self) -> None:
        self._clear()

    def _clear(self) -> None:
        self.words = Words()
        self.hash, self.share, self.n = np.zeros(0, np.uint64), np.zeros(0), np.zeros(0)

    def begin(self) -> None:
        """Call before a batch: word numbers hold until the next call."""
        if len(self.words) > MAX_KEPT:
            self._clear()

    def _learn(self) -> None:
        new = self.words.fresh()
        for i in range(0, len(new), 50_000):  # bounds the arrays
            some = new[i : i + 50_000]
            whole, of, grams = word_hashes(some, self.model.orders)
            w, b = self.model.weights, np.uint64(len(self.model.weights))
            share = w[(whole % b).astype(np.int64)] + np.bincount(of, w[(grams % b).astype(np.int64)], len(some))
            self.hash = np.concatenate([self.hash, whole])
            self.share = np.concatenate([self.share, share])
            self.n = np.concatenate([self.n, 1 + np.bincount(of, minlength=len(some))])

    def raw(self, ids: np.ndarray) -> float:
        if len(self.share) < len(self.words):
            self._learn()
        if not len(ids):
            return self.model.bias
        pairs = self.model.weights[(pair_hashes(self.hash[ids]) % np.uint64(len(self.model.weights))).astype(np.int64)]
        total = self.share[ids].sum() + pairs.sum()
        return float(self.model.bias + total / (len(ids) if self.model.mean_over == "words" else self.n[ids].sum() + len(pairs)))


def _calibrated(model: Model, raw: np.ndarray, y: np.ndarray) -> Model:
    """Platt's slope and shift by Newton steps, with his smoothed targets; a slope below zero is not used."""
    if len(set(y)) < 2:
        return model
    mid, wide = raw.mean(), raw.std() or 1.0
    raw, t = (raw - mid) / wide, np.where(y > 0, (y.sum() + 1) / (y.sum() + 2), 1 / (len(y) - y.sum() + 2))
    a, b = 1.0, 0.0
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(a * raw + b, -40, 40)))
        g = np.array([((p - t) * raw).sum() + 1e-2 * (a - 1), (p - t).sum()])
        v = p * (1 - p) + 1e-9
        hess = np.array([[(v * raw * raw).sum() + 1e-2, (v * raw).sum()], [(v * raw).sum(), v.sum() + 1e-4]])
        step = np.linalg.solve(hess, g)
        step /= max(1.0, np.abs(step).max())
        a, b = a - step[0], b - step[1]
        if np.abs(step).max() < 1e-9:
            break
    return Model(model.weights, model.bias, model.orders, model.mean_over, a / wide, b - a * mid / wide) if a > 0 else model


def _split(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Every fifth row calibrates."""
    at = np.arange(n)
    return at[at % 5 != 4], at[at % 5 == 4]


def train_logistic(texts: list[bytes], y: np.ndarray, orders: tuple[int, ...] = (3, 4), buckets: int = 1 << 18, rounds: int = 80, rate: float = 0.7, l2: float = 1e-6) -> Model:
    """Logistic regression by full-batch AdaGrad on feature counts by word, then Platt calibration on rows held back."""
    rows = [features(t.split(), orders, buckets) for t in texts]
    n = np.array([max(len(t.split()), 1) for t in texts])
    w, bias = np.zeros(buckets), 0.0
    fit, held = _split(len(texts))
    if len(fit) and len(set(y[fit])) == 2:
        at = np.concatenate([rows[i][0] for i in fit])
        x = np.concatenate([rows[i][1] / n[i] for i in fit])
        row = np.repeat(np.arange(len(fit)), [len(rows[i][0]) for i in fit])
        target, seen, seen_b = y[fit], np.full(buckets, 1e-8), 1e-8
        for _ in range(rounds):
            p = 1 / (1 + np.exp(-np.clip(bias + np.bincount(row, w[at] * x, len(fit)), -40, 40)))
            e = (p - target) / len(fit)
            g = np.bincount(at, e[row] * x, buckets) + l2 * w
            seen += g * g
            seen_b += e.sum() ** 2
            w -= rate * g / np.sqrt(seen)
            bias -= rate * e.sum() / np.sqrt(seen_b)
    elif len(texts):
        bias = float(np.log((y.sum() + 1) / (len(y) - y.sum() + 1)))
    model = Model(w.astype(np.float32), float(bias), orders, "words")
    raw = np.array([bias + (w[rows[i][0]] * rows[i][1]).sum() / n[i] for i in held])
    return _calibrated(model, raw, y[held].astype(float)) if len(held) else model


def train_embeddings(texts: list[bytes], y: np.ndarray, orders: tuple[int, ...] = (3, 4), buckets: int = 1 << 17, dims: int = 8, rounds: int = 6, rate: float = 0.5, seed: int = 7) -> Model:
    """Vectors of hashed words, word pairs and character n-grams, averaged over a text, under a two-class softmax.

    Stochastic gradient descent, a text at a time, with a rate that falls in a line to zero; a text's step is scaled so
    that its own mean vector moves by the rate, whatever its number of features. A softmax over a mean of vectors is a
    logistic curve over a mean of numbers, so the trained model is handed over in that shorter form.
    """
    rng = np.random.default_rng(seed)
    vec, out, bias = rng.uniform(-0.1 / dims, 0.1 / dims, (buckets, dims)), rng.normal(0, 1 / np.sqrt(dims), (2, dims)), np.zeros(2)
    rows = [features(t.split(), orders, buckets) for t in texts]
    fit, held = _split(len(texts))
    both = len(set(y[fit])) == 2
    steps, done = max(1, rounds * len(fit)), 0
    for _ in range(rounds if both else 0):
        for i in rng.permutation(fit):
            at, c = rows[i]
            done += 1
            if not len(at):
                continue
            x = c / c.sum()
            mean = x @ vec[at]
            z = out @ mean + bias
            p = np.exp(z - z.max())
            p /= p.sum()
            p[int(y[i])] -= 1
            if np.abs(p).max() < 0.01:
                continue
            step = rate * (1 - done / steps)
            back = p @ out
            out -= 0.05 * step * np.outer(p, mean)
            bias -= 0.02 * step * p
            vec[at] -= np.outer(x / (x @ x), step * back)
    if len(texts) and not both:
        bias[1] = np.log((y.sum() + 1) / (len(y) - y.sum() + 1))
    w, b = vec @ (out[1] - out[0]), float(bias[1] - bias[0])
    model = Model(w.astype(np.float32), b, orders, "features")
    raw = np.array([b + ((w[rows[i][0]] * rows[i][1]).sum() / rows[i][1].sum() if len(rows[i][0]) else 0.0) for i in held])
    return _calibrated(model, raw, y[held].astype(float)) if len(held) else model


def labelled_sample(docs: DataFrame, labels: DataFrame, most: int, most_chars: int = 200_000) -> tuple[list[bytes], np.ndarray]:
    """Texts and quality of at most `most` labelled documents of folds 0, 1 and 3, in order of a hash of their id.

    The bound is a parameter of fitting only: longer texts than most_chars, null texts and null labels are not learnt from.
    """
    ids = labels.select("doc_id", "quality").where((fold(F.col("doc_id")) != 2) & F.col("quality").isin(0, 1)).dropDuplicates(["doc_id"])
    ids = ids.withColumn("__order", F.xxhash64("doc_id")).orderBy("__order", "doc_id").limit(most)
    rows = docs.select("doc_id", "text").where(F.col("text").isNotNull() & (F.length("text") <= most_chars)).join(F.broadcast(ids), "doc_id")
    got = sorted((r["__order"], r["doc_id"], r["text"], r["quality"]) for r in rows.collect())
    return [r[2].encode("utf-8", "replace") for r in got], np.array([r[3] for r in got], np.int64)
