"""Quality rules (counts with fixed limits, and a calibrated linear model) and the quality classifier (subword embeddings).

Edge cases, for both: a null or empty text has no words; it fails the rules' word minimum, and the classifier gives it
the score of its bias. Ties and repeated rows are scored alike, each for itself. Very long texts are scored whole. A
null doc_id is not held out and never learnt from. Without labels every score is one half. Extra columns are ignored
by the scores, and kept by the filter.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fold, mix64, tidy
from .textscore import Model, Scorer, labelled_sample, train_embeddings, train_logistic

SYMBOLS, SPACES = b"#*$%&|<>", b" \t\n\v\f\r"
MIN_WORDS, MAX_REPEAT_PERCENT, WINDOW = 20, 30, 8
#: Documents that the rules' model rates below this are rejected; above the classifier's, predicted good.
MIN_PROBABILITY, GOOD = 0.5, 0.7
MAX_TRAIN = 2500
_UNCOUNTED = SPACES + bytes(range(0x80, 0xC0))


def repeated_words(ids: np.ndarray, window: int = WINDOW) -> int:
    """Words that lie in a window of that many words which the text holds at least twice."""
    m = len(ids) - window + 1
    if m < 2:
        return 0
    h, mixed = np.zeros(m, np.uint64), mix64(ids.astype(np.uint64) + np.uint64(1))
    for k in range(window):
        h = h * np.uint64(0xD1342543DE82EF95) + mixed[k : k + m]
    order = np.argsort(h, kind="stable")
    same = h[order[1:]] == h[order[:-1]]
    if not same.any():
        return 0
    twice = np.zeros(m, bool)
    twice[order[1:][same]] = twice[order[:-1][same]] = True
    edge = np.zeros(len(ids) + 1, np.int64)
    edge[:m] += twice
    edge[window : window + m] -= twice
    return int((np.cumsum(edge[:-1]) > 0).sum())


def repeated_lines(text: bytes) -> int:
    """Lines with a word that equal an earlier line."""
    if b"\n" not in text:
        return 0
    lines = [x for x in text.split(b"\n") if x.strip(SPACES)]
    return len(lines) - len(set(lines))


def _rate(batches: Iterator[pa.RecordBatch], model: Model, min_probability: float, slice_rows: int = 2000, scorer: Scorer | None = None) -> Iterator[pa.RecordBatch]:
    scorer = scorer or Scorer(model)
    for whole in batches:
        for i in range(0, whole.num_rows, slice_rows):
            batch = whole.slice(i, slice_rows)
            scorer.begin()
            texts = [(x or "").encode("utf-8", "replace") for x in batch.column(1).to_pylist()]
            ids = [scorer.words.ids(t.split()) for t in texts]
            n = np.array([len(x) for x in ids], np.int64)
            chars = np.array([len(t.translate(None, _UNCOUNTED)) for t in texts], np.int64)
            symbols = np.array([len(t) - len(t.translate(None, SYMBOLS)) for t in texts], np.int64)
            lines = np.array([repeated_lines(t) for t in texts], np.int64)
            repeats = np.array([repeated_words(x) for x in ids], np.int64)
            p = model.probability(np.array([scorer.raw(x) for x in ids]))
            failed = (n < MIN_WORDS) | (100 * repeats > MAX_REPEAT_PERCENT * n)
            yield pa.RecordBatch.from_arrays([batch.column(0), *map(pa.array, (n, chars, symbols, lines, repeats, failed, p, ~failed & (p >= min_probability)))], names=RATED_NAMES)


RATED_NAMES = ["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "probability", "kept"]
RATED = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, probability double, kept boolean"


def fit_rules(docs: DataFrame, labels: DataFrame, most: int = MAX_TRAIN) -> Model:
    return train_logistic(*labelled_sample(docs, labels, most))


def rate(docs: DataFrame, model: Model, min_probability: float = MIN_PROBABILITY) -> DataFrame:
    """The rules' counts, the model's probability and the verdict for each row of docs; one pass, no shuffle."""
    held = docs.sparkSession.sparkContext.broadcast(model)
    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(tidy(lambda batches: _rate(batches, held.value, min_probability)), RATED)


def keep_good(docs: DataFrame, model: Model, min_probability: float = MIN_PROBABILITY) -> DataFrame:
    """docs without the rows that the rules reject; each row is judged for itself, in its own batch, with all its columns."""
    held, schema = docs.sparkSession.sparkContext.broadcast(model), docs.schema
    at = docs.columns.index("text")

    def kept(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(held.value)  # one for the task, so that words stay known
        for batch in batches:
            if batch.num_rows:
                judged = pa.RecordBatch.from_arrays([pa.array(np.arange(batch.num_rows)), batch.column(at)], names=["doc_id", "text"])
                verdicts = [x.column(RATED_NAMES.index("kept")) for x in _rate(iter([judged]), held.value, min_probability, scorer=scorer)]
                yield batch.filter(pa.concat_arrays(verdicts))

    return docs.mapInArrow(tidy(kept), schema)


def fit_classifier(docs: DataFrame, labels: DataFrame, most: int = MAX_TRAIN) -> Model:
    return train_embeddings(*labelled_sample(docs, labels, most))


def classify(docs: DataFrame, model: Model, good: float = GOOD) -> DataFrame:
    """doc_id, held_out, score, predicted of each row of docs; one pass, no shuffle."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(held.value)
        for whole in batches:
            for i in range(0, whole.num_rows, 2000):
                batch = whole.slice(i, 2000)
                scorer.begin()
                ids = [scorer.words.ids((x or "").encode("utf-8", "replace").split()) for x in batch.column(2).to_pylist()]
                p = held.value.probability(np.array([scorer.raw(x) for x in ids]))
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(p), pa.array((p >= good).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])

    rows = docs.select(F.col("doc_id").cast("long"), F.coalesce(fold(F.col("doc_id")) == 2, F.lit(False)).alias("held_out"), F.col("text").cast("string"))
    return rows.mapInArrow(tidy(score), "doc_id long, held_out boolean, score double, predicted int")
