"""Benchmark decontamination: a prefix-filtered set join of item-sized word windows with whole documents.

A window is `size` consecutive words of an item (an item of fewer words is one window). Containment must be exact, so the
necessary prefix of a window under an order by rarity is its one rarest word. Word counts come from all documents. A
document looks up each of its words among those prefix words; the word's place bounds where the window can lie, the
window's length bounds the rest, and the words there are compared.

A benchmark of at most `block_chars` characters (counted first) is an index in each task. A larger one is joined: windows
and documents' words are dealt by prefix word, each word with the words around it, so that a window is verified where
the two meet; documents are read three times however long the benchmark is, and their texts are never shuffled, only
words that a filter of FILTER_BITS bits takes for prefix words. Hits are kept by the text's 128-bit digest.

Edge cases: null and empty texts have no words (documents: nothing hit; items: no window); items with equal windows all
count; a null item_id counts no item but its windows hit; repeated rows are judged alike, each for itself; very long
texts are read whole; an empty benchmark hits nothing. Extra columns are ignored by find(), and kept, whatever their
names, by drop_contaminated().
"""

from __future__ import annotations

import hashlib
import zlib
from collections import Counter, defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import cut, free_names, tidy

SIZE, BLOCK_CHARS = 10, 4 << 20
FILTER_BITS = 1 << 20
_TO_WORDS = bytes(c + 32 if 0x41 <= c <= 0x5A else c if 0x30 <= c <= 0x39 or 0x61 <= c <= 0x7A or c >= 0x80 else 0x20 for c in range(256))


def words_of(text: str | None) -> list[bytes]:
    """Lower-case words: runs of digits, A-Z, a-z and all that isn't ASCII."""
    return text.encode("utf-8", "replace").translate(_TO_WORDS).split() if text else []


def windows_of(words: list[bytes], size: int = SIZE) -> list[tuple[bytes, ...]]:
    return [tuple(words[i : i + size]) for i in range(max(1, len(words) - size + 1))] if words else []


def _small(benchmark: DataFrame, most: int) -> bool:
    told = benchmark.agg(F.sum(F.length("text")).alias("chars")).first()
    return (told["chars"] or 0) <= most


def _counts(docs: DataFrame, vocabulary: set[bytes]) -> Counter:
    """How often each word of the vocabulary stands in all documents; summed within tasks before the shuffle."""
    held = docs.sparkSession.sparkContext.broadcast(frozenset(vocabulary))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, wanted = Counter(), held.value
        for batch in batches:
            for text in batch.column(0).to_pylist():
                total.update(filter(wanted.__contains__, words_of(text)))
        yield pa.RecordBatch.from_arrays([pa.array(list(total), pa.binary()), pa.array(list(total.values()), pa.int64())], names=["word", "n"])

    rows = docs.select(F.col("text").cast("string")).mapInArrow(count, "word binary, n long").groupBy("word").agg(F.sum("n").alias("n"))
    return Counter({bytes(r["word"]): r["n"] for r in rows.collect()})  # no more rows than the block has words


def _index(block: list[tuple[str | None, list[bytes]]], counts: Counter, size: int) -> dict[bytes, list[tuple[int, list[bytes], tuple[str, ...]]]]:
    """Windows by prefix word: (place of that word in the window, the window, its items)."""
    items: dict[tuple[bytes, ...], set[str]] = defaultdict(set)
    for item, words in block:
        for w in windows_of(words, size):
            items[w].update([item] if item is not None else [])
    index = defaultdict(list)
    for w, ids in sorted(items.items()):
        rare = min(range(len(w)), key=lambda i: (counts[w[i]], w[i], i))
        index[w[rare]].append((rare, list(w), tuple(sorted(ids))))
    return dict(index)


def match(words: list[bytes], index: dict) -> tuple[list[tuple[int, int]], set[str]]:
    """(start and end of each hit window, items whose windows occur)."""
    spans, items = [], set()
    for i in [i for i, w in enumerate(words) if w in index]:
        for place, window, ids in index[words[i]]:
            start, end = i - place, i - place + len(window)
            if start >= 0 and end <= len(words) and words[start:end] == window:
                spans.append((start, end))
                items.update(ids)
    return spans, items


def covered(spans: np.ndarray, n: int) -> int:
    """Words in any span."""
    edge = np.zeros(n + 1, np.int64)
    np.add.at(edge, spans[0::2], 1)
    np.add.at(edge, spans[1::2], -1)
    return int((np.cumsum(edge[:-1]) > 0).sum())


def _marked(rows: DataFrame, benchmark: DataFrame, size: int, spans: str, items: str) -> DataFrame:
    """rows with two more columns: starts and ends of the windows that occur, and their items. For a small benchmark."""
    block = [(r["item_id"], words_of(r["text"])) for r in _items(benchmark).collect()]
    index = _index(block, _counts(rows, {w for _, words in block for w in words}), size)
    held, at = rows.sparkSession.sparkContext.broadcast(index), rows.columns.index("text")

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = held.value
        for batch in batches:
            found = [match(words_of(text), index) for text in batch.column(at).to_pylist()]
            more = [pa.array([[x for pair in s for x in pair] for s, _ in found], pa.list_(pa.int64())), pa.array([sorted(i) for _, i in found], pa.list_(pa.string()))]
            yield pa.RecordBatch.from_arrays([*batch.columns, *more], names=[*batch.schema.names, spans, items])

    added = T.StructType([T.StructField(spans, T.ArrayType(T.LongType())), T.StructField(items, T.ArrayType(T.StringType()))])
    return rows.mapInArrow(tidy(find), T.StructType([*rows.schema.fields, *added.fields]))


def _items(benchmark: DataFrame) -> DataFrame:
    return benchmark.select(F.col("item_id").cast("string").alias("item_id"), F.col("text").cast("string").alias("text")).where(F.col("text").isNotNull())


def _digest(text):
    return F.md5(F.coalesce(text.cast("string"), F.lit("")).cast("binary"))


def _filter(words: DataFrame) -> np.ndarray:
    """Which of FILTER_BITS values of a word's checksum occur; never more than that to collect."""
    held = np.zeros(FILTER_BITS, bool)
    held[[r["b"] for r in words.select((F.crc32(F.col("word").cast("binary")) % FILTER_BITS).alias("b")).distinct().collect()]] = True
    return np.packbits(held)


def _hits(docs: DataFrame, benchmark: DataFrame, size: int) -> DataFrame:
    """key, spans, items: of each text in which a window occurs, by the text's digest. For a benchmark of any size."""
    context = docs.sparkSession.sparkContext

    def cut_windows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (whole.slice(i, 200) for whole in batches for i in range(0, whole.num_rows, 200)):
            rows = [(b" ".join(w).decode(), item) for item, text in zip(*(c.to_pylist() for c in batch.columns), strict=True) for w in windows_of(words_of(text), size)]
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], pa.string()) for k in (0, 1)], names=["window", "item"])

    windows = cut(_items(benchmark).mapInArrow(tidy(cut_windows), "window string, item string").groupBy("window").agg(F.collect_set("item").alias("items")), "windows")
    placed = windows.select("window", F.posexplode(F.split("window", " ")).alias("place", "word"))
    wanted = context.broadcast(_filter(placed))

    def passes(held: np.ndarray, words: list[bytes]) -> list[bytes]:
        return [w for w in words if held[(b := zlib.crc32(w) % FILTER_BITS) >> 3] >> (7 - (b & 7)) & 1]

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, held = Counter(), bytes(wanted.value)

        def out() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([w.decode() for w in total], pa.string()), pa.array(list(total.values()), pa.int64())], names=["word", "n"])

        for batch in batches:
            for text in batch.column(0).to_pylist():
                total.update(passes(held, words_of(text)))
                if len(total) > 1 << 18:
                    yield out()
                    total = Counter()
        yield out()

    counts = docs.select(F.col("text").cast("string")).mapInArrow(tidy(count), "word string, n long").groupBy("word").agg(F.sum("n").alias("n"))
    rarest = placed.join(counts, "word", "left").groupBy("window").agg(F.min(F.struct(F.coalesce("n", F.lit(0)).alias("n"), "word", "place")).alias("x"))
    index = cut(rarest.select("window", F.col("x.word").alias("word"), F.col("x.place").alias("place"), F.size(F.split("window", " ")).alias("n")), "index")
    prefixes = context.broadcast(_filter(index))

    def probe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = bytes(prefixes.value)
        for batch in (whole.slice(i, 200) for whole in batches for i in range(0, whole.num_rows, 200)):
            rows = []
            for key, text in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                words = words_of(text)
                good = set(passes(held, list(set(words))))
                rows += [(w.decode(), key, i, b" ".join(words[max(0, i - size + 1) : i + size]).decode()) for i, w in enumerate(words) if w in good]
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], t) for k, t in enumerate((pa.string(), pa.string(), pa.int64(), pa.string()))], names=["word", "key", "at", "around"])

    probes = docs.select(_digest(F.col("text")).alias("key"), F.col("text").cast("string")).mapInArrow(tidy(probe), "word string, key string, at long, around string")
    # a place of the word in the window bounds where the window starts among the words around; its length bounds the end
    start = F.least("at", F.lit(size - 1)) - F.col("place")
    around = F.split("around", " ")
    same = (start >= 0) & (start + F.col("n") <= F.size(around)) & (F.array_join(F.slice(around, F.greatest(start, F.lit(0)).cast("int") + 1, F.col("n")), " ") == F.col("window"))
    found = probes.join(index, "word").where(same).select("key", "window", (F.col("at") - F.col("place")).alias("start"), (F.col("at") - F.col("place") + F.col("n")).alias("end")).distinct()
    spans = found.join(windows, "window").groupBy("key").agg(F.flatten(F.collect_set(F.array(F.col("start").cast("long"), F.col("end").cast("long")))).alias("spans"), F.array_sort(F.array_distinct(F.flatten(F.collect_set("items")))).alias("items"))
    return spans


NAMES = ["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated"]


def find(docs: DataFrame, benchmark: DataFrame, size: int = SIZE, block_chars: int = BLOCK_CHARS) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated of each document."""
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))

    def digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = [x if isinstance(x, int) else len(words_of(x)) for x in batch.column(1).to_pylist()]
            hit = [covered(np.array(s, np.int64), k) if s else 0 for s, k in zip(batch.column(2).to_pylist(), n, strict=True)]
            items = [x or [] for x in batch.column(3).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(hit, pa.int64()), pa.array(map(len, items), pa.int64()), pa.array([hashlib.sha256(",".join(x).encode()).hexdigest() for x in items], pa.string()), pa.array([h > 0 for h in hit], pa.bool_())], names=NAMES)

    if _small(benchmark, block_chars):
        rows = _marked(slim, benchmark, size, "spans", "items")
    else:

        def words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([len(words_of(t)) for t in batch.column(1).to_pylist()], pa.int64()), batch.column(2)], names=["doc_id", "n_words", "key"])

        sized = slim.withColumn("key", _digest(F.col("text"))).mapInArrow(tidy(words), "doc_id long, n_words long, key string")
        rows = sized.join(_hits(slim, benchmark, size), "key", "left").select("doc_id", "n_words", "spans", "items")
    return rows.mapInArrow(tidy(digest), "doc_id long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean")


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, size: int = SIZE, block_chars: int = BLOCK_CHARS) -> DataFrame:
    """The rows of docs in which no window occurs, with all their columns."""
    spans, items, key = free_names(docs, "spans", "items", "key")
    if _small(benchmark, block_chars):
        return _marked(docs, benchmark, size, spans, items).where(F.size(spans) == 0).select(*docs.columns)
    hits = _hits(docs, benchmark, size).select(F.col("key").alias(key))
    return docs.join(hits, _digest(docs["text"]) == F.col(key), "left_anti")
