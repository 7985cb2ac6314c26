"""Workloads of the experiments: families of near copies, and families grown along a known tree."""

from __future__ import annotations

import random
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import kernels as K
from .plans.components import near_copy_families
from .sources import tables as T

#: Bands of sequence length that the experiments tell apart.
BANDS = {"short": (4, 40), "medium": (40, 500), "large": (500, 1 << 30)}


def near_copy_sequences(spark: SparkSession, sf_dir: str, least: int = 3, words: int = 5, similarity: float = 0.8) -> DataFrame:
    """T5: families of near-copy documents, folded to four letters."""
    families = near_copy_families(T.table(spark, sf_dir, "documents"), words, similarity).select("doc_id", "family")
    big = families.groupBy("family").agg(F.count("*").alias("n")).where(F.col("n") >= least)
    docs = T.documents(spark, sf_dir).select(F.col("seq_id").alias("doc_id"), "seq", "len")
    return families.join(big, "family").join(docs, "doc_id").select(F.col("family").cast("string").alias("family"), F.col("doc_id").alias("seq_id"), "seq", "len")


#: Fixed five-leaf trees: (parent, child, weight); 0-4 are leaves, 8 the root. One is clock-like, one has very unequal rates.
SHAPES = {
    "clock": [(8, 7, 1.0), (8, 5, 2.0), (5, 0, 2.0), (5, 1, 2.0), (7, 2, 3.0), (7, 6, 1.5), (6, 3, 1.5), (6, 4, 1.5)],
    "uneven": [(8, 7, 0.4), (8, 5, 0.4), (5, 0, 0.3), (5, 1, 6.0), (7, 2, 5.0), (7, 6, 0.5), (6, 3, 0.3), (6, 4, 4.0)],
}


def true_tree(shape: str) -> K.Tree:
    kids: dict[int, list[tuple[int, float]]] = {}
    for parent, child, w in SHAPES[shape]:
        kids.setdefault(parent, []).append((child, w))
    return K.Tree(5, [(*(c for c, _ in sorted(kids[k])), k, *(w for _, w in sorted(kids[k])), 0.0) for k in (5, 6, 7, 8)])


def grow(root: str, shape: str, seed: str, rate: float = 0.03) -> tuple[list[str], list[str]]:
    """(leaf sequences, their true alignment): substitutions, deletions and insertions along the shape's branches."""
    order, made = list(range(len(root))), len(root)
    at: dict[int, list[tuple[str, int]]] = {8: list(zip(root, order))}
    for parent, child, weight in SHAPES[shape]:
        rnd = random.Random(zlib.crc32(f"{seed}/{shape}/{parent}/{child}".encode()))
        now: list[tuple[str, int]] = []
        for letter, home in at[parent]:
            x = rnd.random()
            if x < 0.15 * rate * weight:
                continue
            now.append((rnd.choice([c for c in "ACGT" if c != letter]) if x < rate * weight else letter, home))
            if rnd.random() < 0.15 * rate * weight:
                order.insert(order.index(home) + 1, made)
                now.append((rnd.choice("ACGT"), made))
                made += 1
        at[child] = now
    rows = [{home: letter for letter, home in at[leaf]} for leaf in range(5)]
    columns = [h for h in order if any(h in r for r in rows)]
    return ["".join(letter for letter, _ in at[leaf]) for leaf in range(5)], ["".join(r.get(h, K.GAP) for h in columns) for r in rows]


def grown(spark: SparkSession, sf_dir: str, shape: str, rate: float = 0.03) -> DataFrame:
    """T6: family, seq_id, seq, len, aligned (the true row) of five leaves grown from each benchmark item."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for family, root in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                seqs, rows = grow(root, shape, family, rate)
                out += [(family, k, s, len(s), r) for k, (s, r) in enumerate(zip(seqs, rows))]
            types = (pa.string(), pa.int64(), pa.string(), pa.int32(), pa.string())
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], t) for i, t in enumerate(types)], names=["family", "seq_id", "seq", "len", "aligned"])

    return T.benchmark(spark, sf_dir).select("family", "seq").mapInArrow(run, "family string, seq_id bigint, seq string, len int, aligned string")


def true_merges(seqs: DataFrame, shape: str) -> DataFrame:
    """The shape's tree as a merge table for every family of grown()."""
    rows = [(k, *j) for k, j in enumerate(true_tree(shape).joins)]
    tree = seqs.sparkSession.createDataFrame(rows, "step int, left int, right int, node int, left_len double, right_len double, height double")
    families = seqs.select("family").distinct().withColumn("ids", F.array(*[F.lit(i).cast("bigint") for i in range(5)]))
    return families.crossJoin(F.broadcast(tree)).select("family", "step", "left", "right", "node", "left_len", "right_len", "height", "ids")  # 4 rows of tree
