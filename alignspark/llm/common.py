"""Helpers shared by the training-data operators: cutting lineage, bounded samples, word tables."""

from __future__ import annotations

from operator import itemgetter

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..plans.ring import mix64  # noqa: F401
from ..plans.shared import cut, new_path, release, shared_dir, tidy, written  # noqa: F401

#: Words of the contracts: runs of anything but space, tab, \n, \v, \f and \r.
WORD = r"[^\x20\x09-\x0D]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def free_names(docs: DataFrame, *names: str) -> list[str]:
    """These names, each with as many underscores before it as keep it apart from docs' columns in any case of letters."""
    taken, out = {c.lower() for c in docs.columns}, []
    for name in names:
        while name.lower() in taken:
            name = "_" + name
        out.append(name)
    return out


def ascii_lower(c: Column) -> Column:
    return F.translate(c, UPPER, LOWER)


def fold(doc_id: Column) -> Column:
    """crc32 of the id's text, mod 4; null for a null id."""
    return F.crc32(doc_id.cast("string").cast("binary")) % 4


def parts_for(df: DataFrame, least: int = 0) -> int:
    """Partitions for a shuffle that carries about as much as df's input: the session's number or more."""
    return max(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), least)


class Words(dict):
    """Number of each word seen, given on first sight; fresh() hands over those not yet looked at."""

    def __init__(self) -> None:
        super().__init__()
        self.new = []

    def __missing__(self, w: bytes) -> int:
        i = self[w] = len(self)
        self.new.append(w)
        return i

    def ids(self, words: list[bytes]) -> np.ndarray:
        found = itemgetter(*words)(self) if len(words) > 1 else [self[w] for w in words]
        return np.fromiter(found, np.int32, len(words))

    def fresh(self) -> list[bytes]:
        new, self.new = self.new, []
        return new


def keep_one(docs: DataFrame, families) -> DataFrame:
    """docs with one row of each family: the least doc_id (null last), then the least hash of doc_id and text; of rows
    equal in both, the least hash of the whole row. Columns of docs may have any names.

    families(nodes) gives doc_id, family of nodes (doc_id, text), whose doc_id is a hash of a row's doc_id and text.
    """
    node, row, place, gone_node = free_names(docs, "node", "row", "place", "gone_node")
    hashed = F.xxhash64(F.col("doc_id").isNull(), F.coalesce(F.col("doc_id").cast("long"), F.lit(0)), F.col("text").isNull(), F.coalesce(F.col("text").cast("string"), F.lit("")))
    marked = docs.withColumn(node, hashed)
    slim = docs.select(hashed.alias("node"), F.col("doc_id").cast("long").alias("id"), F.col("text").cast("string").alias("text"))
    mark = written()
    counted = cut(slim.groupBy("node").agg(F.min("id").alias("id"), F.count("*").alias("n")), "nodes")
    of = families(slim.select(F.col("node").alias("doc_id"), "text")).select(F.col("doc_id").alias("node"), "family").distinct()
    of = cut(of.join(counted, "node"), "families")
    first = of.groupBy("family").agg(F.min(F.struct(F.col("id").isNull(), "id", "node"))["node"].alias("first"))
    ranked = of.join(first, "family")
    many = cut(ranked.where("node = first AND n > 1").select(F.col("node").alias(gone_node)), "many")
    gone = cut(ranked.where("node <> first").select(F.col("node").alias(gone_node)).unionByName(many), "gone")
    release(docs.sparkSession, mark, gone, many)
    kept = marked.join(gone, F.col(node) == F.col(gone_node), "left_anti")
    if many.limit(1).count():
        ranks = F.row_number().over(Window.partitionBy(node).orderBy(row))
        equal = marked.join(many, F.col(node) == F.col(gone_node), "left_semi").withColumn(row, F.xxhash64(*(F.col(f"`{c}`") for c in docs.columns))).withColumn(place, ranks).where(F.col(place) == 1)
        kept = kept.select(*docs.columns).unionByName(equal.select(*docs.columns))
    return kept.select(*docs.columns)
