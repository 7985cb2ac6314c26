"""Connected components of an edge table, and near-copy families of texts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import ring
from .shared import cut


def components(edges: DataFrame) -> DataFrame:
    """node, component (its least node) for every node of edges (a, b): rounds of least labels with pointer jumping."""
    both = cut(edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "edges")
    labels = cut(both.groupBy("a").agg(F.least("a", F.min("b")).alias("label")), "labels")
    while True:
        near = both.join(labels.select(F.col("a").alias("b"), "label"), "b").groupBy("a").agg(F.min("label").alias("near"))
        best = labels.join(near, "a").select("a", F.col("label").alias("old"), F.least("label", "near").alias("best"))
        jump = labels.select(F.col("a").alias("best"), F.col("label").alias("jump"))
        new = cut(best.join(jump, "best", "left").select("a", "old", F.least("best", F.coalesce("jump", "best")).alias("label")), "labels")
        changed = new.where("label <> old").limit(1).count()
        labels = new.select("a", "label")
        if not changed:
            return labels.select(F.col("a").alias("node"), F.col("label").alias("component"))


def near_copies(docs: DataFrame, words: int = 5, similarity: float = 0.8) -> tuple[DataFrame, DataFrame]:
    """(a, b, jaccard between class representatives a < b; doc_id, rep membership), exact.

    Texts with equal shingle sets are one class, named by its least doc_id; texts of fewer words are one shingle, texts
    without words have no class. Sets meet by boxes on a ring of their shingles (see ring), then the overlap is taken.
    """
    texts = docs.select(F.col("doc_id").cast("long"), F.lower("text").alias("text"))
    rows = cut(ring.named(texts, words).where("size > 0"), "sketches")
    nodes = ring.nodes_of(rows)
    reps = nodes.select("key", "rep")
    pairs = cut(ring.candidates(ring.filed(texts, nodes, words, similarity), nodes, similarity), "candidates")
    found = cut(ring.similar(pairs, texts, nodes, words, similarity), "found")
    found = found.join(reps.toDF("a", "left"), "a").join(reps.toDF("b", "right"), "b")
    found = found.select(F.least("left", "right").alias("a"), F.greatest("left", "right").alias("b"), "jaccard")
    return found, rows.join(reps, "key").select("doc_id", "rep")


def near_copy_families(docs: DataFrame, words: int = 5, similarity: float = 0.8) -> DataFrame:
    """doc_id, family (least doc_id of its component), links (to other classes), copies (rows with the same shingle set)."""
    found, members = near_copies(docs, words, similarity)
    found = cut(found, "pairs")
    named = components(found.select("a", "b"))
    links = found.select(F.col("a").alias("rep")).unionByName(found.select(F.col("b").alias("rep"))).groupBy("rep").agg(F.count("*").alias("links"))
    copies = members.groupBy("rep").agg(F.count("*").alias("copies"))
    return (
        members.join(named.withColumnRenamed("node", "rep"), "rep", "left").join(links, "rep", "left").join(copies, "rep")
        .select("doc_id", F.coalesce("component", "rep").alias("family"), F.coalesce("links", F.lit(0)).cast("bigint").alias("links"), "copies")
    )
