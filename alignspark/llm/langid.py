"""Language identification by one interpolated Kneser-Ney character model for each language.

A model reads lower-case words (runs of letters) with marked beginnings and ends, so a text's cross-entropy is a sum over
its words and each distinct word is scored once. The n-grams of all languages share one sorted array of 64-bit hashes
for each order, beside a matrix of log probabilities with a column for each language; one binary search serves all.
The language of the least cross-entropy per character wins; its score is a softmax whose temperature is fitted on
texts kept back, and `accepted` tells whether the cross-entropy is within what such texts show.

Fitting uses a bounded sample (a parameter) of the labelled documents of folds 0, 1 and 3; prediction reads whole texts.
Edge cases: a null or empty text, or one without a letter, is "und" with score 0; ties go to the first language in
code-point order; no learnt language at all gives "und"; a null doc_id is not held out and never learnt from; repeated
rows are predicted alike; extra columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import Words, fold, mix64, tidy
from .textscore import MAX_KEPT, MUL

ORDER, PER_LANGUAGE, MOST_DOCS, MOST_CHARS = 4, 150, 20_000, 200_000
LETTERS = re.compile(r"[^\W\d_]+")
PAD, END, CHAR = 1, 2, np.uint64(16)


def words_of(text: str | None) -> list[str]:
    found = LETTERS.findall(text.lower()) if text else []
    return found if any(any(map(str.isalpha, w)) for w in found) else []


def grams(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(word number, the last ORDER characters packed by 16 bits each) for each character of each word and its end mark."""
    text = "".join("\x01" * (ORDER - 1) + w + "\x02" for w in words)
    codes = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64) & np.uint64(0xFFFF)
    lengths = np.fromiter((len(w) + ORDER for w in words), np.int64, len(words))
    of = np.repeat(np.arange(len(words)), lengths)
    at = np.flatnonzero(np.arange(len(codes)) - np.repeat(np.cumsum(lengths) - lengths, lengths) >= ORDER - 1)
    packed = np.zeros(len(at), np.uint64)
    for k in range(ORDER - 1, -1, -1):
        packed = (packed << CHAR) | codes[at - k]
    return of[at], packed


def last(packed: np.ndarray, n: int) -> np.ndarray:
    return packed & np.uint64((1 << (16 * n)) - 1)


def hashed(packed: np.ndarray, n: int) -> np.ndarray:
    return mix64(packed + np.uint64(n * int(MUL) & 0xFFFFFFFFFFFFFFFF))


def _sorted(packed: np.ndarray, n: int, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    h = hashed(packed, n)
    order = np.argsort(h)
    return h[order], values[order]


def _find(keys: np.ndarray, h: np.ndarray) -> np.ndarray:
    """Row of each hash in the sorted array, -1 if absent."""
    if not len(keys):
        return np.full(len(h), -1)
    at = np.minimum(np.searchsorted(keys, h), len(keys) - 1)
    return np.where(keys[at] == h, at, -1)


@dataclass
class LanguageModels:
    languages: list[str]
    keys: list[np.ndarray]  # by order from 1: sorted hashes of n-grams
    logs: list[np.ndarray]  # their log probabilities, a column a language
    context_keys: list[np.ndarray]  # by order from 1: sorted hashes of contexts
    context_logs: list[np.ndarray]  # log of the weight left for the lower order
    floor: float
    temperature: float = 1.0
    limit: float = float("inf")

    def of_words(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(log probability of each word by language, characters counted)."""
        of, packed = grams(words)
        total = np.zeros((len(packed), len(self.languages)), np.float32)
        open_, n = np.arange(len(packed)), ORDER
        while n and len(open_):
            p = last(packed[open_], n)
            row = _find(self.keys[n - 1], hashed(p, n))
            hit = row >= 0
            total[open_[hit]] += self.logs[n - 1][row[hit]]
            open_, p = open_[~hit], p[~hit]
            row = _find(self.context_keys[n - 1], hashed(p >> CHAR, n))
            total[open_[row >= 0]] += self.context_logs[n - 1][row[row >= 0]]
            n -= 1
        total[open_] += np.float32(self.floor)
        sums = np.stack([np.bincount(of, total[:, k], len(words)) for k in range(len(self.languages))], 1) if len(words) else np.zeros((0, len(self.languages)))
        return sums, np.bincount(of, minlength=len(words))

    def decide(self, entropy: np.ndarray) -> tuple[int, float, bool]:
        z = -(entropy - entropy.min()) * self.temperature
        p = np.exp(z) / np.exp(z).sum()
        best = int(np.argmin(entropy))
        return best, float(p[best]), bool(entropy[best] <= self.limit)


def train(words_by_language: dict[str, list[list[str]]]) -> LanguageModels:
    """From the words of each training text of each language; every fifth text calibrates."""
    languages = sorted(k for k, v in words_by_language.items() if any(v))
    fit = {k: [w for i, t in enumerate(words_by_language[k]) if i % 5 != 4 or len(words_by_language[k]) < 5 for w in t] for k in languages}
    counted = {}
    for k in languages:
        own = Words()
        times = np.bincount(own.ids(fit[k]), minlength=len(own)) if fit[k] else np.zeros(0, np.int64)
        of, packed = grams(list(own))
        gram, inverse = np.unique(packed, return_inverse=True)
        counted[k] = {ORDER: (gram, np.bincount(inverse, times[of], len(gram)))}
        for n in range(ORDER - 1, 0, -1):  # lower orders count the different characters before
            gram, inverse = np.unique(last(counted[k][n + 1][0], n), return_inverse=True)
            counted[k][n] = gram, np.bincount(inverse).astype(float)
    every = {n: np.unique(np.concatenate([counted[k][n][0] for k in languages] or [np.zeros(0, np.uint64)])) for n in range(1, ORDER + 1)}
    floor = -np.log(len(every[1]) + 1.0)
    keys, logs, context_keys, context_logs, lower = [], [], [], [], None
    for n in range(1, ORDER + 1):
        contexts = np.unique(every[n] >> CHAR)
        prob, left = np.zeros((len(every[n]), len(languages))), np.ones((len(contexts), len(languages)))
        ctx_of = np.searchsorted(contexts, every[n] >> CHAR)
        base = np.full((len(every[n]), len(languages)), np.exp(floor)) if n == 1 else lower[np.searchsorted(every[n - 1], last(every[n], n - 1))]
        for j, k in enumerate(languages):
            gram, c = counted[k][n]
            ones, twos = (c == 1).sum(), (c == 2).sum()
            d = ones / (ones + 2 * twos) if ones and twos else 0.5
            ctx = np.searchsorted(contexts, gram >> CHAR)
            total, kinds = np.bincount(ctx, c, len(contexts)), np.bincount(ctx, minlength=len(contexts))
            left[:, j] = np.where(total > 0, d * kinds / np.maximum(total, 1), 1.0)
            prob[np.searchsorted(every[n], gram), j] = np.maximum(c - d, 0) / total[ctx]
        prob += left[ctx_of] * base
        lower = prob
        for place, (packed, values) in ((keys, (every[n], prob)), (context_keys, (contexts, left))):
            h, v = _sorted(packed, n, np.log(values).astype(np.float32))
            place.append(h)
            (logs if place is keys else context_logs).append(v)
    model = LanguageModels(languages, keys, logs, context_keys, context_logs, float(floor))
    held = [(j, t) for j, k in enumerate(languages) for i, t in enumerate(words_by_language[k]) if i % 5 == 4 and t]
    if held:
        entropy = []
        for _, t in held:
            sums, n = model.of_words(t)
            entropy.append(-sums.sum(0) / n.sum())
        entropy, truth = np.array(entropy), np.array([j for j, _ in held])

        def loss(t: float) -> float:
            z = -entropy * t
            z -= z.max(1, keepdims=True)
            return -(z[np.arange(len(z)), truth] - np.log(np.exp(z).sum(1))).mean()

        model.temperature = float(min(np.geomspace(1, 64, 25), key=loss))
        best = entropy.min(1)
        model.limit = float(np.quantile(best, 0.999) + 2 * best.std() + 0.1)
    return model


def fit(docs: DataFrame, per_language: int = PER_LANGUAGE) -> LanguageModels:
    """From at most per_language texts of each language, chosen by a hash of doc_id among folds 0, 1 and 3."""
    known = docs.select("doc_id", "lang").where(F.col("lang").isNotNull() & F.col("doc_id").isNotNull() & (fold(F.col("doc_id")) != 2))
    known = known.withColumn("__order", F.pmod(F.xxhash64("doc_id"), F.lit(1 << 40)) / float(1 << 40))
    counts = {r["lang"]: r["n"] for r in known.groupBy("lang").agg(F.count("*").alias("n")).collect()}  # a row a language
    if not counts:
        return train({})
    each = max(1, min(per_language, MOST_DOCS // len(counts)))
    share = F.create_map(*[x for k, n in counts.items() for x in (F.lit(k), F.lit(4.0 * each / n))])
    first = known.where(F.col("__order") < share[F.col("lang")]).dropDuplicates(["doc_id"])  # a few times the sample, so no large group is sorted
    ids = first.withColumn("__rank", F.row_number().over(Window.partitionBy("lang").orderBy("__order", "doc_id"))).where(F.col("__rank") <= each).select("doc_id", "__rank")
    texts = docs.select("doc_id", "lang", "text").where(F.length("text") <= MOST_CHARS).join(F.broadcast(ids), "doc_id")
    by: dict[str, list[list[str]]] = {k: [] for k in counts}
    for r in sorted(texts.collect(), key=lambda r: (r["__rank"], r["doc_id"], r["text"])):
        if r["lang"] in by:
            by[r["lang"]].append(words_of(r["text"]))
    return train(by)


def predict(docs: DataFrame, models: LanguageModels) -> DataFrame:
    """doc_id, held_out, lang_pred, score, entropy, accepted of each row; one pass, no shuffle."""
    held = docs.sparkSession.sparkContext.broadcast(models)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = held.value
        words, sums, chars = Words(), np.zeros((0, len(m.languages))), np.zeros(0, np.int64)
        for whole in batches:
            for i in range(0, whole.num_rows, 1000):
                batch = whole.slice(i, 1000)
                if len(words) > MAX_KEPT // 2:
                    words, sums, chars = Words(), np.zeros((0, len(m.languages))), np.zeros(0, np.int64)
                ids = [words.ids(words_of(t)) for t in batch.column(2).to_pylist()]
                new = words.fresh()
                for k in range(0, len(new), 20_000):
                    s, n = m.of_words(new[k : k + 20_000])
                    sums, chars = np.concatenate([sums, s]), np.concatenate([chars, n])
                out = [(m.languages[b[0]], b[1], float(e.min()), b[2]) if len(x) and m.languages and (b := m.decide(e := -sums[x].sum(0) / chars[x].sum())) else ("und", 0.0, None, False) for x in ids]
                lang, score, entropy, accepted = zip(*out, strict=True) if out else ((), (), (), ())
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(lang, pa.string()), pa.array(score, pa.float64()), pa.array(entropy, pa.float64()), pa.array(accepted, pa.bool_())], names=["doc_id", "held_out", "lang_pred", "score", "entropy", "accepted"])

    rows = docs.select(F.col("doc_id").cast("long"), F.coalesce(fold(F.col("doc_id")) == 2, F.lit(False)).alias("held_out"), F.col("text").cast("string"))
    return rows.mapInArrow(tidy(run), "doc_id long, held_out boolean, lang_pred string, score double, entropy double, accepted boolean")
