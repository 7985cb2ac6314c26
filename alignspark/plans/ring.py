"""Near pairs of texts by their sets of word shingles, found exactly by pigeonring filtering.

Sets of n and m shingles of at least a similarity s differ in D <= (n + m) (1 - s) / (1 + s) shingles. Shingles fall by
hash into boxes on a ring, the number of boxes fixed for each band of the larger set's size, two bands to a power of two. Of the boxes that
aren't empty in both sets, one of the first D + 1 must agree, with no more differences in any number of boxes after it
than there are boxes: else stretches of at least one difference a box would cover all of them. So a set is filed under
its first boxes that aren't empty, as many as its budget of differences and one more, each with sketches of what follows;
two sets meet where a box is equal, the box after it differs in one bit at most, and the next eight in eight, and where
sizes and parities of the whole sets allow it, on 256 bits and then, by bitmaps, on about a bit a shingle, before a pair is
written anywhere. Sets with too few such boxes
are filed by prefix of the hash order as well, which settles pairs of two such sets. What meets is compared by
whole sets.

Equal sets are one node, named by a hash of the set. Nothing is sampled, and no group of sets is left out or cut.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .shared import cut, tidy

#: Parts into which keys are dealt, texts whose keys go into one row for each of them.
BUCKETS, TEXTS = 1024, 2000
#: Nodes whose ids may be broadcast to fetch their texts, and linked nodes with their labels; more are joined.
BROADCAST_ROWS, BROADCAST_LABELS = 1_000_000, 250_000
#: The box that follows: its distance and parities of its shingles on so many bits. FAR: further off, or none.
BITS, FAR = 23, 31
#: Boxes of the ring after a box whose shingles a second sketch holds, on 64 bits; on small rings that of the whole set.
SPAN = 8
#: Parts into which the keys with one least node are dealt, so that no task gets all of a large group's.
TOGETHER = 4
#: Words of 64 bits on which the parities of a whole set are held beside each of its keys.
WHOLE = 4
_ODD = np.uint64(0x9E3779B97F4A7C15)
_LOWER = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")


def mix64(x: np.ndarray) -> np.ndarray:
    """Finalising mix of 64-bit values (the public splitmix64 constants)."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def shingles(text: str | None, words: int) -> np.ndarray:
    """Distinct hashes of a text's shingles, in order: of each run of so many words, or of all if there are fewer."""
    found = text.encode("utf-8", "replace").translate(_LOWER).split() if text else []
    if not found:
        return np.zeros(0, np.uint64)
    h = np.array(list(map(xxhash.xxh64_intdigest, found)), np.uint64)
    k = min(words, len(found))
    total = np.full(len(h) - k + 1, np.uint64(k))
    for i in range(k):  # each place of a shingle has its own mix
        total = mix64((total ^ h[i : len(h) - k + 1 + i]) * _ODD)
    return np.unique(total)


def name_of(g: np.ndarray) -> int:
    return xxhash.xxh64_intdigest(g.tobytes())


def first_of(band: int) -> int:
    """Least size of a band: 2 ** (band / 2), rounded up."""
    return math.isqrt((1 << band) - 1) + 1


def boxes(g: np.ndarray, similarity: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(keys, sketches of the box and of the span of boxes that follow) under which a set is filed."""
    n, keys, after, span = len(g), [np.zeros(0, np.uint64)], [np.zeros(0, np.uint32)], [np.zeros(0, np.uint64)]
    share, most = (1 - similarity) / (1 + similarity), int(len(g) / similarity + 1e-9)
    mixed = mix64(g)
    bit = np.uint32(1) << (mixed % np.uint64(BITS)).astype(np.uint32)
    wide = np.uint64(1) << (mixed >> np.uint64(20) & np.uint64(63))
    band = 2 * n.bit_length() - 2
    while n and most >= first_of(band):  # bands of the larger set's size
        top = first_of(band + 1) - 1
        budget = int((n + min(most, top)) * share + 1e-9)
        salt = np.uint64((2 * band + 1) * int(_ODD) & 0xFFFFFFFFFFFFFFFF)
        band += 1
        if top < n or top < first_of(band - 1) or not budget:  # no such size, or only equal sets are so similar
            continue
        ring = np.uint64(int(2.2 * top * share) + 3)
        at = ((g >> np.uint64(32)) * ring >> np.uint64(32)).astype(np.int64)
        starts = np.flatnonzero(np.append(True, at[1:] != at[:-1]))
        filed = min(len(starts), budget + 1)
        keys.append(mix64(np.add.reduceat(mixed, starts)[:filed] ^ salt))
        far = np.full(len(starts), FAR)
        far[:-1] = np.minimum(np.diff(at[starts]), FAR)
        sketch = np.append(np.bitwise_xor.reduceat(bit, starts)[1:], np.uint32(0))
        small = int(2 * top * share) <= 12
        limit = np.uint32((budget if small else SPAN) << BITS)
        after.append((far.astype(np.uint32) << np.uint32(BITS + 4) | limit | np.where(far < FAR, sketch, 0).astype(np.uint32))[:filed])
        upto = np.append(np.uint64(0), np.bitwise_xor.accumulate(np.bitwise_xor.reduceat(wide, starts)))
        if small:
            span.append(np.full(filed, upto[-1]))
        else:
            span.append((upto[np.searchsorted(at[starts], at[starts] + SPAN, "right")] ^ upto[1:])[:filed])
        if len(starts) <= budget:
            first = g[: n - int(np.ceil(similarity * n - 1e-9)) + 1]
            keys.append(mix64(mix64(first) + salt))
            after.append(np.full(len(first), np.uint32(FAR << BITS + 4 | 15 << BITS)))
            span.append(np.zeros(len(first), np.uint64))
    return np.concatenate(keys), np.concatenate(after), np.concatenate(span)


def may_follow(a: np.ndarray, b: np.ndarray, span_a: np.ndarray, span_b: np.ndarray) -> np.ndarray:
    """Whether what follows may differ in as few shingles as it must, by its sketches."""
    far_a, far_b, bits = a >> np.uint32(BITS + 4), b >> np.uint32(BITS + 4), np.uint32((1 << BITS) - 1)
    most = np.minimum(a >> np.uint32(BITS) & np.uint32(15), b >> np.uint32(BITS) & np.uint32(15))
    next_ = np.where(far_a == far_b, a ^ b, np.where(far_a < far_b, a, b)) & bits
    return ((np.bitwise_count(next_) <= 1) | ((far_a == FAR) & (far_b == FAR))) & (np.bitwise_count(span_a ^ span_b) <= most)


def bitmap(g: np.ndarray) -> bytes:
    """Parities of how many shingles fall on each of 64 or more bits, about a bit a shingle."""
    bits = max(64, 1 << max(0, len(g) - 1).bit_length())
    return np.packbits(np.bincount((g % np.uint64(bits)).astype(np.int64), minlength=bits).astype(np.uint8) & 1).tobytes()


def whole(g: np.ndarray) -> np.ndarray:
    """Parities of how many shingles fall on each of 64 * WHOLE bits."""
    at = (mix64(g) >> np.uint64(33)) % np.uint64(64 * WHOLE)
    return np.packbits(np.bincount(at.astype(np.int64), minlength=64 * WHOLE).astype(np.uint8) & 1).view(np.int64)


def may_be_near(size: np.ndarray, other: int, parities: np.ndarray, of: np.ndarray, similarity: float) -> np.ndarray:
    """Whether sets of these sizes and parities (a row each) can be similar to one of size `other` and parities `of`: every
    shingle of one set alone flips a bit at most, and no more than (n + m) (1 - s) / (1 + s) of them may be."""
    most = (size + other) * ((1 - similarity) / (1 + similarity)) + 1e-9
    apart = np.bitwise_count((parities ^ of).view(np.uint64)).sum(1, dtype=np.int64)
    return (apart <= most) & (np.minimum(size, other) >= similarity * np.maximum(size, other) - 1e-9)


def may_be_similar(a: bytes, b: bytes, n: int, m: int, similarity: float) -> bool:
    """Whether sets of n and m shingles with these bitmaps can be similar: shingles of one set alone flip a bit at most each."""
    x, y = np.frombuffer(a, np.uint8), np.frombuffer(b, np.uint8)
    x, y = (x, y) if len(x) <= len(y) else (y, x)
    y = np.bitwise_xor.reduce(y.reshape(-1, len(x)), axis=0)  # bits that meet modulo the shorter length
    both = (n + m - int(np.bitwise_count(x ^ y).sum())) // 2
    return both >= similarity * (n + m - both) - 1e-9


class Bitmaps:
    """Bitmaps of a task's nodes, a matrix for each length; they come once a node, in rows without a key before all others."""

    def __init__(self) -> None:
        self.node, self.words, self.place, self.rows = [], [], [], {}

    def add(self, node: list[int], bits: list[bytes]) -> None:
        for n, b in zip(node, bits, strict=True):
            mine = self.rows.setdefault(len(b) // 8, [])
            self.node.append(n)
            self.words.append(len(b) // 8)
            self.place.append(len(mine))
            mine.append(b)

    def taken(self, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Take in the rows whose first column is null and hand on the rest; node is the second column, bits the last."""
        for batch in batches:
            if held := batch.column(0).null_count:
                first = batch.slice(0, held)
                self.add(first.column(1).to_pylist(), first.column(batch.num_columns - 1).to_pylist())
            if held < batch.num_rows:
                yield batch.slice(held)

    def ready(self) -> None:
        order = np.argsort(np.array(self.node, np.int64), kind="stable")
        self.node, self.words, self.place = (np.array(x, np.int64)[order] for x in (self.node, self.words, self.place))
        for w, b in self.rows.items():
            self.rows[w] = np.frombuffer(b"".join(b), np.uint64).reshape(-1, w)

    def may_be_similar(self, node: int, size: int, others: np.ndarray, sizes: np.ndarray, similarity: float) -> np.ndarray:
        """As may_be_similar() of `node` with each of the others."""
        if isinstance(self.node, list):
            self.ready()
        i, at = np.searchsorted(self.node, node), np.searchsorted(self.node, others)
        own, mine, words = self.rows[int(self.words[i])][self.place[i]], int(self.words[i]), self.words[at]
        good = np.zeros(len(others), bool)
        for w in np.unique(words).tolist():
            some = np.flatnonzero(words == w)
            bits, of = self.rows[w][self.place[at[some]]], own
            if w > mine:  # bits that meet modulo the shorter length
                bits = np.bitwise_xor.reduce(bits.reshape(len(some), w // mine, mine), axis=1)
            elif w < mine:
                of = np.bitwise_xor.reduce(own.reshape(mine // w, w), axis=0)
            all_ = sizes[some] + size
            both = (all_ - np.bitwise_count(bits ^ of).sum(1, dtype=np.int64)) // 2
            good[some] = both >= similarity * (all_ - both) - 1e-9
        return good


def common(a: np.ndarray, b: np.ndarray) -> int:
    return len(np.intersect1d(a, b, assume_unique=True))


def long_batch(names: str, *columns: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c.view(np.int64)) for c in columns], names=names.split())


_WHOLE = [f"w{i}" for i in range(WHOLE)]


def named(texts: DataFrame, words: int) -> DataFrame:
    """doc_id, key (name of its set), size, bits (bitmap) and w0, w1, ... (whole()) of each row of texts (doc_id, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets = [shingles(t, words) for t in batch.column(1).to_pylist()]
            parities = np.array([whole(g) for g in sets], np.int64).reshape(-1, WHOLE)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.array([name_of(g) for g in sets], np.uint64).view(np.int64)), pa.array([len(g) for g in sets], pa.int64()), pa.array([bitmap(g) for g in sets], pa.binary()), *(pa.array(w) for w in parities.T.copy())], names=["doc_id", "key", "size", "bits", *_WHOLE])

    return texts.select("doc_id", "text").mapInArrow(tidy(run), "doc_id long, key long, size long, bits binary, " + ", ".join(f"{w} long" for w in _WHOLE))


def nodes_of(rows: DataFrame) -> DataFrame:
    """key, rep (least doc_id), size, bits, w0, w1, ... of each node of named()."""
    return cut(rows.groupBy("key").agg(F.min("doc_id").alias("rep"), *(F.first(c).alias(c) for c in ("size", "bits", *_WHOLE))), "nodes")


_ENTRY = np.dtype([("g", "<u8"), ("node", "<i8"), ("after", "<u4"), ("span", "<u8")])


def filed(texts: DataFrame, nodes: DataFrame, words: int, similarity: float) -> DataFrame:
    """least, g, node, after, span, size, w0, w1, ...: keys that more than one node is filed under, with these nodes and the
    least of them, the sketches there and those of the whole sets."""

    def file(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (whole.slice(i, TEXTS) for whole in batches for i in range(0, whole.num_rows, TEXTS)):
            parts = [np.zeros(0, _ENTRY)]
            for text in batch.column(0).to_pylist():
                g = shingles(text, words)
                keys, after, span = boxes(g, similarity)
                rows = np.empty(len(keys), _ENTRY)
                rows["g"], rows["after"], rows["span"], rows["node"] = keys, after, span, np.uint64(name_of(g)).astype(np.int64)
                parts.append(rows)
            rows = np.concatenate(parts)
            bucket = (rows["g"] % np.uint64(BUCKETS)).astype(np.int64)
            order = np.argsort(bucket, kind="stable")
            rows, ends = rows[order], np.cumsum(np.bincount(bucket, minlength=BUCKETS))
            some = np.flatnonzero(np.diff(ends, prepend=0))
            starts = np.append(0, ends)[some]
            yield pa.RecordBatch.from_arrays([pa.array(some, pa.int32()), pa.array([rows[a:b].tobytes() for a, b in zip(starts, ends[some], strict=True)], pa.binary())], names=["bucket", "entries"])

    def meet(table: pa.Table) -> pa.Table:
        rows = np.frombuffer(b"".join(table.column("entries").to_pylist()), _ENTRY)
        order = np.lexsort((rows["node"], rows["g"]))
        g, node, after, span = (rows[c][order] for c in ("g", "node", "after", "span"))
        new = np.append(True, (g[1:] != g[:-1]) | (node[1:] != node[:-1]))  # copies of a set
        g, node, after, span = g[new], node[new], after[new], span[new]
        first = np.flatnonzero(np.append(True, g[1:] != g[:-1])) if len(g) else np.zeros(0, np.int64)
        size = np.diff(np.append(first, len(g)))
        keep = size > 1
        two = first[size == 2]
        keep[size == 2] = may_follow(after[two], after[two + 1], span[two], span[two + 1])
        keep = np.repeat(keep, size)
        least = np.repeat(node[first], size)
        return pa.table({"least": pa.array(least[keep]), "g": pa.array(g[keep].view(np.int64)), "node": pa.array(node[keep]), "after": pa.array(after[keep].astype(np.int64)), "span": pa.array(span[keep].view(np.int64))})

    dealt = texts.select("text").mapInArrow(tidy(file), "bucket int, entries binary")
    met = dealt.groupBy("bucket").applyInArrow(meet, "least long, g long, node long, after long, span long")
    return cut(met.join(nodes.select(F.col("key").alias("node"), "size", *_WHOLE), "node").select("least", "g", "node", "after", "span", "size", *_WHOLE), "filed")


def _pairs(key: np.ndarray, node: np.ndarray, after: np.ndarray, span: np.ndarray, of: np.ndarray, size: np.ndarray, parities: np.ndarray, turn: int, similarity: float, bitmaps: Bitmaps | None = None) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs within groups of one key, sorted by key and node, that their sketches and bitmaps allow and that aren't linked yet.
    turn 0: those with the least node; 1, 2, ...: one of each node, another each turn; below 0: every one."""
    starts = np.flatnonzero(np.append(True, key[1:] != key[:-1])) if len(key) else np.zeros(0, np.int64)
    ends = np.append(starts[1:], len(key))
    several = ends - starts > 1
    for s, e in zip(starts[several].tolist(), ends[several].tolist(), strict=True):
        for i in range(s, s + 1 if turn == 0 else e - 1):
            near = i + 1 + np.flatnonzero((of[i + 1 : e] != of[i]) & may_follow(after[i + 1 : e], after[i], span[i + 1 : e], span[i]))
            if len(near):
                near = near[may_be_near(size[near], size[i], parities[near], parities[i], similarity)]
            if len(near) and bitmaps:
                near = near[bitmaps.may_be_similar(node[i], size[i], node[near], size[near], similarity)]
            if len(to := node[near]):
                to = to[(turn - 1) * 7 % len(to) :][:1] if turn > 0 else to
                yield np.full(len(to), node[i]), to


def _ended(batches: Iterator[pa.RecordBatch], columns: int) -> Iterator[list[np.ndarray]]:
    """Columns of rows that are sorted by the first of them, in parts that never tear one of its values apart."""
    kept: list[list[np.ndarray]] = []
    for batch in batches:
        now = [batch.column(j).to_numpy(zero_copy_only=False).astype(np.int64) for j in range(columns)]
        if not len(now[0]):
            continue
        going = now[0] == now[0][-1]
        if kept and going.all() and now[0][0] == kept[0][0][0]:
            kept.append(now)
            continue
        yield [np.concatenate(x) for x in zip(*kept, [x[~going] for x in now], strict=True)]
        kept = [[x[going] for x in now]]
    if kept:
        yield [np.concatenate(x) for x in zip(*kept, strict=True)]


def candidates(met: DataFrame, nodes: DataFrame, similarity: float, turn: int = -1, linked: DataFrame | None = None) -> DataFrame:
    """a, b: nodes a < b that may be similar; linked: node, label of those that need not meet again."""

    def run(batches: Iterator[pa.RecordBatch], most: int = 1 << 19) -> Iterator[pa.RecordBatch]:
        a, b, n, bitmaps = [], [], 0, Bitmaps()
        for g, node, after, span, size, of, *w in _ended(bitmaps.taken(batches), 6 + WHOLE):
            for x, y in _pairs(g, node, after.astype(np.uint32), span.view(np.uint64), of, size, np.stack(w, 1), turn, similarity, bitmaps):
                a.append(x)
                b.append(y)
                n += len(x)
                if n >= most:
                    yield long_batch("a b", *np.unique(np.stack([np.concatenate(a), np.concatenate(b)]), axis=1))
                    a, b, n = [], [], 0
        if n:
            yield long_batch("a b", *np.unique(np.stack([np.concatenate(a), np.concatenate(b)]), axis=1))

    of = F.col("node")
    if linked is not None:
        of, linked = F.coalesce("label", "node"), linked.select("node", "label")
        met = met.join(F.broadcast(linked) if linked.count() <= BROADCAST_LABELS else linked, "node", "left")
    # keys with one least node mostly hold the same nodes: dealt together, a pair that meets under many is written once, and
    # a node's bitmap goes there once
    part = F.pmod("g", F.lit(TOGETHER)).alias("part")
    rows = met.select("least", part, "g", "node", "after", "span", "size", of.alias("of"), *_WHOLE)
    bits = met.select("least", part, "node").distinct().join(nodes.select(F.col("key").alias("node"), "bits"), "node")
    rows = rows.unionByName(bits, allowMissingColumns=True).repartition("least", "part").drop("least", "part")
    return rows.sortWithinPartitions(F.col("g").asc_nulls_first(), "node").mapInArrow(tidy(run), "a long, b long").distinct()


def similar(pairs: DataFrame, texts: DataFrame, nodes: DataFrame, words: int, similarity: float) -> DataFrame:
    """a, b, jaccard of the pairs (a, b) of nodes that are similar; pairs are those of candidates(), written."""
    need = cut(nodes.join(pairs.select(F.explode(F.array("a", "b")).alias("key")).distinct(), "key").select("key", F.col("rep").alias("doc_id")), "need")
    few = need.count() <= BROADCAST_ROWS

    def spell(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([shingles(t, words).tobytes() for t in batch.column(1).to_pylist()], pa.binary())], names=["key", "set"])

    own = texts.join(F.broadcast(need) if few else need, "doc_id").select("key", "text").dropDuplicates(["key"]).mapInArrow(tidy(spell), "key long, set binary")
    own = cut(own, "sets")

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (whole.slice(i, 500) for whole in batches for i in range(0, whole.num_rows, 500)):
            left, right = ([np.frombuffer(x, np.uint64) for x in batch.column(k).to_pylist()] for k in (2, 3))
            both = np.array([common(x, y) for x, y in zip(left, right, strict=True)], np.int64)
            all_ = np.array([len(x) + len(y) for x, y in zip(left, right, strict=True)], np.int64) - both
            good = pa.array(both >= similarity * all_ - 1e-9)
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(good), batch.column(1).filter(good), pa.array(both / all_).filter(good)], names=["a", "b", "jaccard"])

    return pairs.join(own.toDF("a", "s"), "a").join(own.toDF("b", "t"), "b").select("a", "b", "s", "t").mapInArrow(tidy(verify), "a long, b long, jaccard double")


def forest(edges: DataFrame) -> DataFrame:
    """fewer edges (fp, to) with the same components: a node keeps its least neighbour, to which the others are tied."""
    edges = edges.select(F.least("fp", "to").alias("fp"), F.greatest("fp", "to").alias("to")).where("fp < to").distinct()
    tied = edges.withColumn("least", F.min("fp").over(Window.partitionBy("to")))
    tied = tied.select("least", F.explode(F.array("fp", "to")).alias("to")).where("least < to").select(F.col("least").alias("fp"), "to")
    return tied.distinct()
