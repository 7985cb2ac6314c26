"""Pairwise global alignment as columns and tables over Arrow batches."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.columns import global_score_sql, score_upper_bound
from ..functions.scoring import Scoring
from ..plans.shared import cut
from . import kernels as K
from .jvm import EDIT_SUMS, register

__all__ = ["all_optimal", "banded_score", "count_optimal", "distinct_pairs", "edit_distance", "global_align", "global_score", "global_score_sql", "pairs", "score_table", "score_upper_bound"]


def global_score(a: Column | str, b: Column | str, scoring: Scoring) -> Column:
    kind = "long" if scoring.is_whole else "double"

    @F.pandas_udf(kind)
    def score(x: pd.Series, y: pd.Series) -> pd.Series:
        return pd.Series(K.scores(list(zip(x.fillna(""), y.fillna(""))), scoring))

    return score(a, b)


def banded_score(a: Column | str, b: Column | str, scoring: Scoring) -> Column:
    """The same score from a band about the diagonal that doubles until it is proved wide enough; for near copies."""

    @F.pandas_udf("double")
    def score(x: pd.Series, y: pd.Series) -> pd.Series:
        return pd.Series([K.banded_score(p, q, scoring)[0] for p, q in zip(x, y)], dtype=float)

    return score(a, b)


def global_align(a: Column | str, b: Column | str, scoring: Scoring, tie: str = "dul", limit: int = 4_000_000) -> Column:
    """struct(aligned_a, aligned_b, score, ops) of one optimum; above `limit` cells in linear memory."""

    @F.pandas_udf("aligned_a string, aligned_b string, score double, ops string")
    def align(x: pd.Series, y: pd.Series) -> pd.DataFrame:
        out = []
        for p, q in zip(x.fillna(""), y.fillna("")):
            moves, score = K.align_moves(p, q, scoring, tie, limit)
            out.append((*K.spell(p, q, moves), float(score), moves))
        return pd.DataFrame(out, columns=["aligned_a", "aligned_b", "score", "ops"])

    return align(a, b)


def count_optimal(a: Column | str, b: Column | str, scoring: Scoring) -> Column:
    @F.pandas_udf("long")
    def count(x: pd.Series, y: pd.Series) -> pd.Series:
        return pd.Series([K.count_optimal(p, q, scoring) for p, q in zip(x, y)], dtype="int64")

    return count(a, b)


def edit_distance(a: Column | str, b: Column | str, threshold: int | None = None, counts: tuple[Column | str, Column | str] | None = None) -> Column:
    """Edits between two strings; with counts, of arrays of strings and how often each is there: their sum over all pairs."""
    return F.levenshtein(a, b, threshold) if counts is None else F.call_function(EDIT_SUMS, a, counts[0], b, counts[1])


def score_table(df: DataFrame, scoring: Scoring) -> DataFrame:
    """Rows family, i, j (place in the table), score of each pair's whole table; df has family, a, b."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for family, a, b in zip(*(batch.column(k).to_pylist() for k in range(3))):
                h = K.table(K.substitution(a, b, scoring), scoring.gap)
                n, m = h.shape
                yield pa.RecordBatch.from_arrays([pa.array([family] * n * m), pa.array([i for i in range(n) for _ in range(m)], pa.int32()), pa.array(list(range(m)) * n, pa.int32()), pa.array([int(v) for v in h.ravel()], pa.int64())], names=["family", "i", "j", "score"])

    return df.select("family", "a", "b").mapInArrow(run, "family string, i int, j int, score bigint")


def all_optimal(df: DataFrame, scoring: Scoring, limit: int) -> DataFrame:
    """Rows family, k, aligned_a, aligned_b: up to `limit` optima of each pair."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [(f, k, *ab) for f, a, b in zip(*(batch.column(k).to_pylist() for k in range(3))) for k, ab in enumerate(K.all_optimal(a, b, scoring, limit))]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate((pa.string(), pa.int32(), pa.string(), pa.string()))], names=["family", "k", "aligned_a", "aligned_b"])

    return df.select("family", "a", "b").mapInArrow(run, "family string, k int, aligned_a string, aligned_b string")


def distinct_pairs(seqs: DataFrame, block: int = 1000, together: int = 0) -> DataFrame:
    """family, a, b, n: pairs a < b of a family's different sequences, and of how many pairs of its rows each is.

    Equal sequences are counted first, so that copies are never paired off. Sequences are dealt as in pairs(plan="blocked").
    together: a row for all pairs of so many blocks and so many others instead, family, a, na, b, nb, twice: both sides'
    sequences and how often each is there, for edit_distance(counts=); twice 1 if both are the same, which has each pair
    in both orders, else 0.
    """
    kinds = seqs.groupBy("family", "seq").agg(F.count("*").alias("n"))
    size = kinds.groupBy("family").agg(F.count("*").alias("kinds"))
    if together:
        register(seqs.sparkSession)
        groups = F.greatest(F.ceil(F.col("kinds") / (block * together)), F.lit(1)).cast("int")
        dealt = kinds.join(size, "family").groupBy("family", F.pmod(F.xxhash64("seq"), groups).cast("int").alias("p"))
        dealt = cut(dealt.agg(F.collect_list("seq").alias("a"), F.collect_list("n").alias("na")), "blocks")
        both = dealt.join(dealt.select("family", F.col("p").alias("q")), "family").where("p <= q")
        both = both.join(dealt.toDF("family", "q", "b", "nb"), ["family", "q"])
        conf = seqs.sparkSession.conf.get("spark.sql.shuffle.partitions")
        both = both.repartition(max(int(conf), 8 * seqs.sparkSession.sparkContext.defaultParallelism))
        return both.select("family", "a", "na", "b", "nb", F.expr("int(p = q)").alias("twice"))
    blocks = F.greatest(F.ceil(F.col("kinds") / block), F.lit(1)).cast("int")
    dealt = kinds.join(size, "family").select("family", "seq", "n", F.pmod(F.xxhash64("seq"), blocks).cast("int").alias("p"), F.explode(F.sequence(F.lit(0), blocks - 1)).alias("q"))
    left = dealt.select("family", F.col("seq").alias("a"), F.col("n").alias("na"), F.col("p").alias("pa"), F.least("p", "q").alias("lo"), F.greatest("p", "q").alias("hi"))
    right = left.select("family", F.col("a").alias("b"), F.col("na").alias("nb"), F.col("pa").alias("pb"), "lo", "hi")
    joined = left.join(right, ["family", "lo", "hi"]).where("a < b AND (pa <> pb OR lo = hi)")
    return joined.select("family", "a", "b", (F.col("na") * F.col("nb")).alias("n"))


def pairs(seqs: DataFrame, plan: str = "auto", block: int = 1000) -> DataFrame:
    """family, i, j, a, b for i < j in each family.

    shuffle: an equi-join on family with i < j left over. auto: that, or blocked if a count finds a family of more than
    `block` sequences. blocked: for giant families; sequences get a block number, each pair of blocks is one key, and a sequence is sent to the keys of its block only, so no task holds more
    than two blocks of a family.
    """
    a = seqs.select("family", F.col("seq_id").alias("i"), F.col("seq").alias("a"))
    b = seqs.select("family", F.col("seq_id").alias("j"), F.col("seq").alias("b"))
    if plan == "auto" and seqs.groupBy("family").agg(F.count("*").alias("n")).where(F.col("n") > block).limit(1).count():
        plan = "blocked"
    if plan != "blocked":
        joined = a.join(b if plan == "auto" else b.hint("shuffle_hash"), "family").where("i < j")
        return joined.select("family", "i", "j", "a", "b")
    size = seqs.groupBy("family").agg(F.count("*").alias("n"))
    blocks = F.greatest(F.ceil(F.col("n") / block), F.lit(1)).cast("int")
    dealt = seqs.join(size, "family").select("family", "seq_id", "seq", F.pmod(F.xxhash64("seq_id"), blocks).cast("int").alias("p"), blocks.alias("k"))
    left = dealt.select("family", F.col("seq_id").alias("i"), F.col("seq").alias("a"), F.col("p").alias("pa"), F.explode(F.sequence(F.lit(0), F.col("k") - 1)).alias("q"))
    left = left.withColumns({"lo": F.least("pa", "q"), "hi": F.greatest("pa", "q")})
    right = left.select("family", F.col("i").alias("j"), F.col("a").alias("b"), "lo", "hi", F.col("pa").alias("pb"))
    joined = left.join(right, ["family", "lo", "hi"]).where("i < j AND (pa <> pb OR lo = hi)")
    return joined.select("family", "i", "j", "a", "b")
