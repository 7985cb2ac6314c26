"""Token ids of whole texts, written in the range coder's file format and read back.

Documents are put into ascending order of doc_id by a range shuffle; each partition (a shard) writes segments: a segment
holds whole documents, their ids and lengths, and the coded ids (see token_coder). Texts become ids in Python, with the
tokenizers library; ids are coded and decoded in Spark's JVMs (see token_jvm). Segments are rows of Parquet, so they lie
wherever Spark can write and are read in parallel. Positions of segments come from two sums, over shards and within
a shard; no document's ids ever meet another's outside a segment.

Edge cases: a null or empty text has the end id alone; a null doc_id comes first; repeated doc_ids follow each other, each
with its own row; very long texts are encoded whole; an empty table writes no segment. Extra columns are ignored.
"""

from __future__ import annotations

import gc
import re
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import Words, new_path, parts_for, tidy
from .token_jvm import DOCS, PACK, register

END_ID, SEGMENT_IDS, MAX_CHUNKS_KEPT = 2, 1 << 21, 250_000
SEGMENT = "shard int, segment int, n_ids long, doc_ids binary, no_id binary, lengths binary, data binary"
#: A segment not yet coded: its ids as little-endian unsigned 32-bit integers.
PLAIN_SEGMENT = SEGMENT.replace("data", "ids")


class CachedTokenizer:
    """The tokenizer's ids of texts, from those of their pieces.

    Only for tokenizers that never join characters across white space and drop it (such as word BPE with word ends);
    anything else must be encoded whole. What is nothing but Latin letters, digits, ASCII signs and white space is cut into
    its words as the tokenizer cuts them, a text at a time, and these go straight to its model; of other texts the chunks
    between white space are told apart alike, and any other chunk goes through the whole tokenizer. Pieces repeat a lot,
    so each is encoded once while it is kept.
    """

    PLAIN = re.compile(r"[!-&(-~\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u00ff]+")
    PLAIN_TEXT = re.compile(r"[\t-\r -&(-~\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u00ff]*")
    WORDS = re.compile(r"[a-z\u00df-\u00f6\u00f8-\u00ff]+|[0-9]|[^a-z0-9\u00df-\u00f6\u00f8-\u00ff\s]+")

    def __init__(self, path: str, end_id: int | None = None) -> None:
        from tokenizers import Tokenizer
        from tokenizers.pre_tokenizers import ByteLevel

        self.tokenizer, self.end_id = Tokenizer.from_file(path), end_id
        # the letter that stands for each byte in the model's alphabet
        letters = ByteLevel(add_prefix_space=False, use_regex=False)
        self.letter = {}
        for c in range(1, 256):
            shown = letters.pre_tokenize_str(chr(c))[0][0]
            for byte, letter in zip(chr(c).encode(), shown, strict=True):
                self.letter[byte] = letter
        self.forget()

    def forget(self) -> None:
        self.chunks = Words()
        self.size, self.start, self.flat, self.used = np.zeros(1024, np.int64), np.zeros(1024, np.int64), np.zeros(4096, np.uint32), 0

    def _learn(self, new: list[str]) -> None:
        """Ids of pieces that come for the first time."""
        found, odd = [], []
        plain, model, letter = self.PLAIN.fullmatch, self.tokenizer.model.tokenize, self.letter
        for k, c in enumerate(new):
            ids: list[int] = []
            if c == "\n":  # stands for the end of a text
                ids = [] if self.end_id is None else [self.end_id]
            elif plain(c) and "<|" not in c:
                ids = [t.id for t in model(c if c.isascii() else c.encode().decode("latin-1").translate(letter))]
            else:
                odd.append(k)
            found.append(ids)
        for k, e in zip(odd, [] if not odd else self.tokenizer.encode_batch([new[k] for k in odd], add_special_tokens=False), strict=True):
            found[k] = e.ids
        sizes = np.fromiter(map(len, found), np.int64, len(found))
        first, more = len(self.chunks) - len(new), int(sizes.sum())
        while first + len(new) > len(self.size):
            self.size, self.start = np.append(self.size, np.zeros_like(self.size)), np.append(self.start, np.zeros_like(self.start))
        while self.used + more > len(self.flat):
            self.flat = np.append(self.flat, np.zeros_like(self.flat))
        self.size[first : first + len(new)] = sizes
        self.start[first : first + len(new)] = self.used + np.cumsum(sizes) - sizes
        self.flat[self.used : self.used + more] = np.fromiter(chain.from_iterable(found), np.uint32, more)
        self.used += more

    def encode(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts one after the other, with the end id after each if there is one, number of ids of each)."""
        if len(self.chunks) > MAX_CHUNKS_KEPT:
            self.forget()
        chunks, ends = [], []
        plain, plain_text, cut = self.PLAIN.fullmatch, self.PLAIN_TEXT.fullmatch, self.WORDS.findall
        for t in texts:
            if plain_text(t) and "<|" not in t:
                chunks += cut(t.lower())
            else:
                # split() would also cut at these four, which the tokenizer keeps
                kept = "\x1c" in t or "\x1d" in t or "\x1e" in t or "\x1f" in t
                for c in (c for line in t.split("\n") for c in line.split(" ")) if kept else t.split():
                    if plain(c) and "<|" not in c:
                        chunks += cut(c.lower())
                    else:
                        chunks.append(c)
            chunks.append("\n")
            ends.append(len(chunks))
        number = self.chunks.ids(chunks)
        if new := self.chunks.fresh():
            self._learn(new)
        n = self.size[number]
        upto = np.cumsum(n)
        of_text = upto[np.array(ends, np.int64) - 1] if ends else np.zeros(0, np.int64)
        ids = self.flat[np.arange(int(upto[-1]) if len(upto) else 0) + np.repeat(self.start[number] - upto + n, n)]
        return ids, np.diff(of_text, prepend=0)


def write(docs: DataFrame, tokenizer_path: str, path: str, end_id: int = END_ID) -> None:
    """Encode all texts and write the segments to path."""
    import os

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        tokenizer, shard = CachedTokenizer(tokenizer_path, end_id), TaskContext.get().partitionId()
        docs, lengths, parts, held, number = [], [], [], 0, 0

        def segment() -> pa.RecordBatch:
            whole = np.concatenate(parts)
            parts.clear()  # not held beside their copy
            ids = pa.chunked_array(docs).combine_chunks()
            known = np.asarray(ids.is_valid())
            row = [shard, number, held, np.asarray(ids.fill_null(0)).astype("<i8").tobytes(), np.packbits(~known).tobytes(), np.concatenate(lengths).astype("<i8").tobytes(), whole.astype("<u4", copy=False).tobytes()]
            return pa.RecordBatch.from_arrays([pa.array([x], t) for x, t in zip(row, (pa.int32(), pa.int32(), pa.int64(), pa.binary(), pa.binary(), pa.binary(), pa.binary()), strict=True)], names=["shard", "segment", "n_ids", "doc_ids", "no_id", "lengths", "ids"])

        gc.disable()  # millions of short lists, none in a cycle
        for batch in (whole.slice(i, 100) for whole in batches for i in range(0, whole.num_rows, 100)):
            ids, sizes = tokenizer.encode([t or "" for t in batch.column(1).to_pylist()])
            docs.append(batch.column(0))
            lengths.append(sizes)
            parts.append(ids)
            held += len(ids)
            if held >= SEGMENT_IDS:
                yield segment()
                docs, lengths, parts, held, number = [], [], [], 0, number + 1
        del tokenizer
        batch = None  # both are large, and no longer needed
        if docs:
            yield segment()
        gc.enable()

    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    rows = rows.repartitionByRange(parts_for(docs), "doc_id").sortWithinPartitions("doc_id")
    register(docs.sparkSession)
    plain = rows.mapInArrow(tidy(encode), PLAIN_SEGMENT)
    plain.withColumn("data", F.call_function(PACK, "ids")).drop("ids").write.parquet(path)


def read(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32, shard, segment of each document in the files at path, from their decoded bytes."""

    register(spark)
    files = spark.read.schema(SEGMENT).parquet(path)
    found = files.select("shard", "segment", F.inline(F.call_function(DOCS, "data", "lengths", "doc_ids", "no_id")))
    sizes = files.groupBy("shard", "segment").agg(F.sum("n_ids").alias("n"))
    shards = sizes.groupBy("shard").agg(F.sum("n").alias("n"))
    before = lambda w, c: F.coalesce(F.sum(c).over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    shards = shards.select("shard", before(Window.orderBy("shard"), "n").alias("shard_start"))
    places = sizes.withColumn("inner", before(Window.partitionBy("shard").orderBy("segment"), "n")).join(shards, "shard").select("shard", "segment", (F.col("inner") + F.col("shard_start")).alias("base"))
    return found.join(places, ["shard", "segment"]).select("doc_id", (F.col("base") + F.col("at")).alias("start"), "n_tokens", "ids_crc32", "shard", "segment")


def round_trip(docs: DataFrame, tokenizer_path: str, path: str | None = None) -> DataFrame:
    path = path or new_path(docs.sparkSession, "tokens")
    write(docs, tokenizer_path, path)
    return read(docs.sparkSession, path)
