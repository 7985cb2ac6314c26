"""Mixing sources to target weights by Pareto order sampling, with certain whole copies first.

Each source gets a target number of words; every document of it is taken floor(target / source size) whole times, and
what is left of the target is filled by ranking the documents by the odds of a random number divided by the odds of
their inclusion, and taking them in that order up to the document boundary nearest to the target.

The random number is a hash of seed and doc_id, so reruns, retries and any partitioning agree. Edge cases: a null text
or one without words has size 0; sources of size 0 have target 0; null is a source of its own, after all others;
repeated doc_ids rank next to each other and each row is taken or left for itself; a null doc_id hashes as an empty
string. An empty table gives an empty result. Extra columns are ignored by plan(), and kept by mix().
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD, cut, free_names

WEIGHTS, SHARE, MOST, BINS, SEED = (5.0, 2.0, 1.0), 1.5, 2.0, 4096, "mix-1"


def targets(sized: DataFrame, weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, most: float = MOST) -> DataFrame:
    """source, source_size, target: share of all words dealt by weight, no source above most times its own size.

    Dealing the excess anew until none is above ends at min(most * size, level * weight) with one level for all, which
    one pass in order of most * size / weight finds. One row a source.
    """
    by = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    place = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    by = by.withColumn("weight", F.element_at(F.array(*map(F.lit, weights)), (place % len(weights) + 1).cast("int")))
    by = by.withColumns({"cap": F.col("source_size") * most, "ratio": F.col("source_size") * most / F.col("weight")})
    order = Window.orderBy("ratio", F.col("source").asc_nulls_last())
    before, after, every = order.rowsBetween(Window.unboundedPreceding, -1), order.rowsBetween(0, Window.unboundedFollowing), Window.partitionBy()
    by = by.withColumn("level", (F.sum("source_size").over(every) * share - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / F.sum("weight").over(after))
    level = F.min(F.when(F.col("ratio") > F.col("level"), F.struct("ratio", "level"))).over(every)["level"]
    return by.withColumn("all", level).select("source", "source_size", F.least("cap", F.coalesce(F.col("all") * F.col("weight"), F.col("cap"))).alias("target"))


def uniform(doc_id, seed: str = SEED):
    """A number in (0, 1) from seed and doc_id."""
    text = F.concat(F.lit(f"{seed}:"), F.coalesce(doc_id.cast("string"), F.lit("")))
    return (F.conv(F.substring(F.md5(text.cast("binary")), 1, 12), 16, 10).cast("double") + 0.5) / float(1 << 48)


def plan(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, most: float = MOST, seed: str = SEED, importance: str | None = None, bins: int = BINS) -> DataFrame:
    """doc_id, source, size, source_size, target, copies, taken of every document.

    importance: a column of positive numbers by which inclusion odds differ within a source; equal if None.
    The documents of a source are never sorted together: words are summed by bins of the rank, and only the bin in
    which the target falls is put in order; no bin is where whole copies fill the target.
    """
    weight = F.lit(1.0) if importance is None else F.greatest(F.coalesce(F.col(importance).cast("double"), F.lit(1.0)), F.lit(1e-9))
    size = F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long")
    sized = docs.select("doc_id", "source", size.alias("size"), weight.alias("weight"))
    sized = cut(sized, "sizes")
    goal = targets(sized, weights, share, most).withColumn("ratio", F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0))
    goal = goal.withColumns({"whole": F.floor("ratio").cast("long")}).withColumns({"part": F.col("ratio") - F.col("whole"), "rest": F.col("target") - F.col("whole") * F.col("source_size")})
    goal = goal.select(F.col("source").alias("of"), "source_size", "target", "whole", "part", "rest")
    u, p = F.col("u"), F.col("p")
    ranked = sized.join(goal, F.col("source").eqNullSafe(F.col("of"))).drop("of").withColumn("u", uniform(F.col("doc_id"), seed))
    ranked = ranked.withColumn("p", F.least(F.greatest(F.col("part") * F.col("weight"), F.lit(1e-12)), F.lit(1 - 1e-12)))
    ranked = ranked.withColumn("rank", u / (1 - u) / (p / (1 - p))).withColumn("bin", F.least(F.floor(F.col("rank") / (1 + F.col("rank")) * bins), F.lit(bins - 1)).cast("long"))
    by_bin = ranked.groupBy("source", "bin").agg(F.sum("size").alias("words"), F.first("rest").alias("rest"))
    upto = Window.partitionBy("source").orderBy("bin").rowsBetween(Window.unboundedPreceding, 0)
    edge = by_bin.withColumn("upto", F.sum("words").over(upto)).where((F.col("rest") > 0) & (F.col("upto") >= F.col("rest")))
    edge = edge.groupBy("source").agg(F.min_by(F.struct(F.col("bin").alias("edge"), (F.col("upto") - F.col("words")).alias("got")), "bin").alias("x"))
    edge = edge.select(F.col("source").alias("of"), "x.edge", "x.got")
    ranked = ranked.join(edge, F.col("source").eqNullSafe(F.col("of")), "left").drop("of")
    inner = Window.partitionBy("source").orderBy("rank", "doc_id", "size").rowsBetween(Window.unboundedPreceding, 0)
    on_edge = F.coalesce(F.col("bin") == F.col("edge"), F.lit(False))
    cols = ["doc_id", "source", "size", "source_size", "target", "whole"]
    sure = ranked.where(~on_edge).select(*cols, F.coalesce(F.col("bin") < F.col("edge"), (F.col("rest") > 0) | (F.col("source_size") == 0)).cast("long").alias("more"))
    near = ranked.where(on_edge).withColumn("upto", F.col("got") + F.sum("size").over(inner))
    near = near.select(*cols, (F.col("upto") - F.col("size") / 2 <= F.col("rest")).cast("long").alias("more"))
    return sure.unionByName(near).withColumn("copies", F.col("whole") + F.col("more")).select(*cols[:-1], "copies", (F.col("copies") * F.col("size")).alias("taken"))


def mix(docs: DataFrame, **kw) -> DataFrame:
    """docs with every row as many times as the plan takes it, in all columns, whatever their names.

    Rows that agree in doc_id, source and size share their copies: each gets the same number, and the first of them, by
    a hash of the whole row, one more where the copies don't divide evenly. Only such rows are put in order.
    """
    size, id_, of, words, copies, rows, place, turn = free_names(docs, "size", "id", "of", "words", "copies", "rows", "place", "turn")
    kept = plan(docs.select("doc_id", "source", "text", *([kw["importance"]] if kw.get("importance") else [])), **kw)
    kept = kept.groupBy("doc_id", "source", "size").agg(F.sum("copies").alias(copies), F.count("*").alias(rows)).toDF(id_, of, words, copies, rows).where(F.col(copies) > 0)
    mine = docs.withColumn(size, F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long"))
    same = F.col("doc_id").eqNullSafe(F.col(id_)) & F.col("source").eqNullSafe(F.col(of)) & (F.col(size) == F.col(words))
    found = mine.join(kept, same)
    each, left = F.floor(F.col(copies) / F.col(rows)).cast("int"), F.pmod(copies, rows)
    ranks = F.row_number().over(Window.partitionBy(id_, of, words).orderBy(F.xxhash64(*(F.col(f"`{c}`") for c in docs.columns))))
    even = found.where(left == 0).withColumn(place, each)
    odd = found.where(left > 0).withColumn(place, each + (ranks <= left).cast("int"))
    return even.unionByName(odd).withColumn(turn, F.explode(F.array_repeat(F.lit(1), F.col(place)))).select(*docs.columns)
