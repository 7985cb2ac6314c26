"""SimHash near duplicates: 64-bit fingerprints of word shingles, linked within k differing bits by pigeonring filtering.

The 64 bits lie on a ring of three segments. If two fingerprints differ in at most 2 bits, then from some segment on the
differences summed over 1, 2, 3 segments stay within 2/3, 4/3, 2: that segment agrees, and the next differs in one bit at
most, so one half of it agrees too. A fingerprint is therefore filed under six keys (a segment and a half of the next),
and only pairs with a key in common that keep the whole chain of budgets have their Hamming distance taken.

Equal fingerprints are one node from the start. Pairs are never written out: under each key, links are merged into a
forest where they are found. Under a key with many fingerprints, these are not compared in pairs but filed again with
each open bit flipped; two of them are within two bits exactly if they have a variant in common. Components of the
forests then come from rounds of least labels with pointer jumping, each round written to the shared folder.

Edge cases: null, empty and wordless texts have fingerprint zero and link like any other; texts of fewer words than a
shingle hash their whole sequence; repeated rows share a component; a null doc_id never names a component unless all its
members are null; an empty table gives an empty result; extra columns are ignored by components(), kept by keep_first().
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import LOWER, UPPER, cut, keep_one, tidy

SHINGLE, SEED, DISTANCE = 3, 42, 2
#: The ring: (lowest bit, bits) of its segments; the first half of a segment is its lower bits.
RING = ((0, 22), (22, 21), (43, 21))
#: Fingerprints under one key up to which pairs are compared.
PAIRWISE = 64
_LOWER = bytes.maketrans(UPPER.encode(), LOWER.encode())


def fingerprint(text: str | None, shingle: int = SHINGLE, seed: int = SEED) -> int:
    words = text.encode("utf-8", "replace").translate(_LOWER).split() if text else []
    if not words:
        return 0
    whole = b" ".join(words)
    lengths = np.fromiter(map(len, words), np.int64, len(words))
    ends = np.cumsum(lengths + 1) - 1
    k = min(shingle, len(words))
    digest = xxhash.xxh64_intdigest
    h = np.array([digest(whole[a:b], seed) for a, b in zip((ends - lengths)[: len(words) - k + 1].tolist(), ends[k - 1 :].tolist(), strict=True)], np.uint64)
    ones = np.zeros(64, np.int64)
    for i in range(0, len(h), 1 << 16):
        ones += np.unpackbits(h[i : i + (1 << 16)].astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(((ones * 2 > len(h)).astype(np.uint64) << np.arange(64, dtype=np.uint64)).sum())


def fingerprints(docs: DataFrame, shingle: int = SHINGLE, seed: int = SEED) -> DataFrame:
    """doc_id, fp (the fingerprint as a signed long) of each row; one pass, no shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fp = np.array([fingerprint(t, shingle, seed) for t in batch.column(1).to_pylist()], np.uint64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fp.view(np.int64))], names=["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(tidy(run), "doc_id long, fp long")


def _keys(fp: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    """(key number, key) of each of the six ways to file fingerprints."""
    for i in range(3):
        (a, n), (b, m) = RING[i], RING[(i + 1) % 3]
        segment = (fp >> np.uint64(a)) & np.uint64((1 << n) - 1)
        for half, (at, bits) in enumerate(((b, m // 2), (b + m // 2, m - m // 2))):
            yield 2 * i + half, (segment << np.uint64(bits)) | ((fp >> np.uint64(at)) & np.uint64((1 << bits) - 1))


def _fixed(number: int) -> int:
    """Mask of the bits that fingerprints under one key of this number have in common."""
    i, half = divmod(number, 2)
    (a, n), (b, m) = RING[i], RING[(i + 1) % 3]
    at, bits = ((b, m // 2), (b + m // 2, m - m // 2))[half]
    return ((1 << n) - 1) << a | ((1 << bits) - 1) << at


def chain_holds(x: np.ndarray, number: int, distance: int = DISTANCE) -> np.ndarray:
    """Whether differences x, summed over 1, 2 and 3 segments from the key's segment on, stay within proportional budgets."""
    ok, total = np.ones(len(x), bool), np.zeros(len(x), np.int64)
    for step in range(3):
        a, n = RING[(number // 2 + step) % 3]
        total += np.bitwise_count((x >> np.uint64(a)) & np.uint64((1 << n) - 1))
        ok &= total * 3 <= distance * (step + 1)
    return ok


def _forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(node, its component's least node) of the graph with edges a-b, without the least nodes themselves."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    u, v, label = at[: len(a)], at[len(a) :], np.arange(len(nodes))
    while True:
        least = np.minimum(label[u], label[v])
        new = label.copy()
        np.minimum.at(new, label[u], least)
        np.minimum.at(new, label[v], least)
        while (new[new] != new).any():
            new = new[new]
        new = new[label]
        if (new == label).all():
            break
        label = new
    own = label != np.arange(len(nodes))
    return nodes[own], nodes[label[own]]


def _links(number: np.ndarray, key: np.ndarray, fp: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Forest of links among fingerprints that are sorted by number and key."""
    new = np.ones(len(fp), bool)
    new[1:] = (number[1:] != number[:-1]) | (key[1:] != key[:-1])
    group = np.cumsum(new) - 1
    size = np.bincount(group)[group] if len(fp) else group
    left, right = [], []
    small = np.flatnonzero((size > 1) & (size <= PAIRWISE))
    for step in range(1, PAIRWISE):
        i = small[size[small] > step]
        i = i[i + step < len(fp)]
        i = i[group[i] == group[i + step]]
        if not len(i):
            break
        x = fp[i] ^ fp[i + step]
        for k in range(6):
            mine = number[i] == k
            pick = i[mine][(good := chain_holds(x[mine], k))]
            far = np.bitwise_count(x[mine][good]) > DISTANCE
            left.append(fp[pick[~far]])
            right.append(fp[pick[~far] + step])
    starts = np.flatnonzero(new)
    for s in starts[size[starts] > PAIRWISE]:
        many = np.unique(fp[s : s + size[s]])
        open_ = [1 << b for b in range(64) if not _fixed(int(number[s])) >> b & 1]
        variants = np.concatenate([many, *(many ^ np.uint64(b) for b in open_)])
        of = np.tile(np.arange(len(many)), len(open_) + 1)
        order = np.argsort(variants, kind="stable")
        same = variants[order[1:]] == variants[order[:-1]]
        left.append(many[of[order[1:][same]]])
        right.append(many[of[order[:-1][same]]])
    if not left:
        return fp[:0], fp[:0]
    return _forest(np.concatenate(left), np.concatenate(right))


def links(nodes: DataFrame) -> DataFrame:
    """fp, to: forests whose components are those of the graph that joins fingerprints within two bits."""

    def file(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fp = batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64)
            for number, key in _keys(fp):
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(fp), number, np.int8)), pa.array(key.view(np.int64)), pa.array(fp.view(np.int64))], names=["number", "key", "fp"])

    def link(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept: list[list[np.ndarray]] = []  # parts of the last key's columns, put together once the key has ended

        def out(parts: list[list[np.ndarray]]) -> Iterator[pa.RecordBatch]:
            number, key, fp = (np.concatenate(x) for x in zip(*parts, strict=True))
            a, b = _links(number, key, fp.view(np.uint64))
            if len(a):
                yield pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], names=["fp", "to"])

        for batch in batches:
            now = [batch.column(j).to_numpy(zero_copy_only=False).astype(np.int64) for j in range(3)]
            if not len(now[0]):
                continue
            last = (now[0] == now[0][-1]) & (now[1] == now[1][-1])
            if kept and last.all() and now[0][0] == kept[0][0][0] and now[1][0] == kept[0][1][0]:
                kept.append(now)
                continue
            yield from out([*kept, [x[~last] for x in now]])
            kept = [[x[last] for x in now]]
        if kept:
            yield from out(kept)

    filed = nodes.select("fp").mapInArrow(file, "number byte, key long, fp long")
    return filed.repartition("number", "key").sortWithinPartitions("number", "key").mapInArrow(tidy(link), "fp long, to long").distinct()


def label(edges: DataFrame) -> DataFrame:
    """fp, label of every node of edges (fp, to): the least node of its component, by rounds of least labels and jumps."""
    both = cut(edges.unionByName(edges.select(F.col("to").alias("fp"), F.col("fp").alias("to"))).distinct(), "edges")
    labels = cut(both.groupBy("fp").agg(F.least("fp", F.min("to")).alias("label")), "labels")
    while True:
        near = both.join(labels.select(F.col("fp").alias("to"), "label"), "to").groupBy("fp").agg(F.min("label").alias("near"))
        best = labels.join(near, "fp").select("fp", F.col("label").alias("old"), F.least("label", "near").alias("best"))
        jump = labels.select(F.col("fp").alias("best"), F.col("label").alias("jump"))
        new = cut(best.join(jump, "best", "left").select("fp", "old", F.least("best", F.coalesce("jump", "best")).alias("label")), "labels")
        changed = new.where("label <> old").limit(1).count()
        labels = new.select("fp", "label")
        if not changed:
            return labels


def components(docs: DataFrame, shingle: int = SHINGLE, seed: int = SEED) -> DataFrame:
    """doc_id, fingerprint, component_id of each row of docs."""
    rows = cut(fingerprints(docs, shingle, seed), "fingerprints")
    nodes = cut(rows.groupBy("fp").agg(F.min("doc_id").alias("first")), "nodes")
    labels = label(links(nodes))
    named = nodes.join(labels, "fp", "left").withColumn("label", F.coalesce("label", "fp"))
    least = named.groupBy("label").agg(F.min("first").alias("component_id"))
    named = named.join(least, "label").select(F.col("fp").alias("of"), "component_id")
    return rows.join(named, F.col("fp") == F.col("of")).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def keep_first(docs: DataFrame, **kw) -> DataFrame:
    """docs with one row of each component, as keep_one() chooses it."""
    return keep_one(docs, lambda nodes: components(nodes, **kw).select("doc_id", F.col("component_id").alias("family")))
