"""Measures of alignments: sum-of-pairs score, costs, accuracy against a reference, summaries."""

from __future__ import annotations

import time
from statistics import median

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.scoring import Scoring
from ..sources.sinks import to_noop
from .pairwise import global_score, pairs
from .profile import GAP, cells


def column_pairs(aligned: DataFrame) -> DataFrame:
    """family, matches, mismatches, gaps over all row pairs and columns, from symbol counts by column: no pair is formed."""
    rows = aligned.groupBy("family").agg(F.count("*").alias("rows"))
    n = cells(aligned).where(F.col("symbol") != GAP).groupBy("family", "pos", "symbol").agg(F.count("*").alias("c"))
    col = n.groupBy("family", "pos").agg(F.sum("c").alias("full"), F.sum(F.expr("c * (c - 1) div 2")).alias("same"))
    by = col.join(rows, "family").groupBy("family").agg(F.sum("same").alias("matches"), F.sum(F.expr("full * (full - 1) div 2 - same")).alias("mismatches"), F.sum(F.expr("full * (rows - full)")).alias("gaps"))
    return rows.select("family").join(by, "family", "left").fillna(0)


def sum_of_pairs(aligned: DataFrame, s: Scoring) -> DataFrame:
    return column_pairs(aligned).select("family", (F.col("matches") * s.match + F.col("mismatches") * s.mismatch + F.col("gaps") * s.gap).cast("bigint").alias("score"))


def sum_of_pairs_bruteforce(aligned: DataFrame, s: Scoring) -> DataFrame:
    """The same score from each pair of rows, column by column."""
    a = cells(aligned)
    b = a.select("family", "pos", F.col("seq_id").alias("other"), F.col("symbol").alias("theirs"))
    points = F.when((F.col("symbol") == GAP) & (F.col("theirs") == GAP), 0).when((F.col("symbol") == GAP) | (F.col("theirs") == GAP), s.gap).when(F.col("symbol") == F.col("theirs"), s.match).otherwise(s.mismatch)
    return a.join(b, ["family", "pos"]).where("seq_id < other").groupBy("family").agg(F.sum(points).cast("bigint").alias("score"))


def total_cost(aligned: DataFrame, s: Scoring) -> DataFrame:
    """Lower is better: score = match * (rows - 1) * letters / 2 - cost."""
    return column_pairs(aligned).select("family", (F.col("mismatches") * float(s.match - s.mismatch) + F.col("gaps") * (s.match / 2 - s.gap)).alias("cost"))


def unit_cost(aligned: DataFrame) -> DataFrame:
    return column_pairs(aligned).select("family", (F.col("mismatches") + F.col("gaps")).alias("cost"))


def cost_identity(aligned: DataFrame, s: Scoring) -> DataFrame:
    """family, holds: whether score and cost agree by the identity."""
    letters = aligned.groupBy("family").agg(F.count("*").alias("rows"), F.sum(F.length(F.translate("aligned", GAP, ""))).alias("letters"))
    x = sum_of_pairs(aligned, s).join(total_cost(aligned, s), "family").join(letters, "family")
    return x.select("family", (F.abs(s.match * (F.col("rows") - 1) * F.col("letters") / 2 - F.col("cost") - F.col("score")) < 1e-6).alias("holds"))


def summary(aligned: DataFrame) -> DataFrame:
    """family, rows, width, letters, gap_share, full_columns, identical_columns."""
    by_col = cells(aligned).groupBy("family", "pos").agg(F.sum((F.col("symbol") == GAP).cast("int")).alias("gaps"), F.countDistinct("symbol").alias("kinds"), F.count("*").alias("rows"))
    return by_col.groupBy("family").agg(
        F.max("rows").alias("rows"), F.count("*").cast("int").alias("width"), F.sum(F.col("rows") - F.col("gaps")).alias("letters"),
        F.round(F.sum("gaps") / F.sum("rows"), 6).alias("gap_share"), F.sum((F.col("gaps") == 0).cast("int")).alias("full_columns"), F.sum(((F.col("gaps") == 0) & (F.col("kinds") == 1)).cast("int")).alias("identical_columns"),
    )


def pair_bound(seqs: DataFrame, s: Scoring) -> DataFrame:
    """family, bound: no alignment's sum-of-pairs score is above the sum of the optimal pair scores."""
    return pairs(seqs).select("family", global_score("a", "b", s).alias("s")).groupBy("family").agg(F.sum("s").cast("bigint").alias("bound"))


def optimality_gap(aligned: DataFrame, seqs: DataFrame, s: Scoring) -> DataFrame:
    return sum_of_pairs(aligned, s).join(pair_bound(seqs, s), "family").withColumn("behind", F.col("bound") - F.col("score"))


def _letters(aligned: DataFrame) -> DataFrame:
    from .profile import coordinate_map

    return coordinate_map(aligned).where("letter IS NOT NULL").select("family", "pos", "seq_id", "letter")


def pair_recall(aligned: DataFrame, truth: DataFrame) -> DataFrame:
    """family, recall: share of the truth's aligned letter pairs that the alignment has too."""

    def together(x: DataFrame) -> DataFrame:
        a = _letters(x)
        b = a.select("family", "pos", F.col("seq_id").alias("s2"), F.col("letter").alias("l2"))
        return a.join(b, ["family", "pos"]).where("seq_id < s2").select("family", "seq_id", "letter", "s2", "l2")

    t, found = together(truth), together(aligned).withColumn("hit", F.lit(1))
    return t.join(found, ["family", "seq_id", "letter", "s2", "l2"], "left").groupBy("family").agg(F.avg(F.coalesce("hit", F.lit(0))).alias("recall"))


def column_recall(aligned: DataFrame, truth: DataFrame) -> DataFrame:
    """family, recall: share of the truth's columns (of two letters or more) that the alignment has whole."""
    key = lambda x: _letters(x).groupBy("family", "pos").agg(F.array_sort(F.collect_list(F.struct("seq_id", "letter"))).alias("col")).where(F.size("col") > 1).select("family", F.to_json("col").alias("col"))
    t, found = key(truth), key(aligned).withColumn("hit", F.lit(1))
    return t.join(found, ["family", "col"], "left").groupBy("family").agg(F.avg(F.coalesce("hit", F.lit(0))).alias("recall"))


def work(seqs: DataFrame) -> DataFrame:
    """family, sequences, pairs, cells: what the distance stage does."""
    p = pairs(seqs).groupBy("family").agg(F.count("*").alias("pairs"), F.sum((F.length("a") + 1).cast("bigint") * (F.length("b") + 1)).alias("cells"))
    return seqs.groupBy("family").agg(F.count("*").alias("sequences")).join(p, "family", "left").fillna(0)


def timed(stage: str, make, repeats: int = 3) -> tuple[str, float, float, float]:
    """(stage, median, least, most seconds) of running the plan that make() returns."""
    took = []
    for _ in range(repeats):
        t = time.perf_counter()
        to_noop(make())
        took.append(time.perf_counter() - t)
    return stage, median(took), min(took), max(took)
