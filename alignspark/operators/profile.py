"""Frequency profiles of aligned rows, consensus with its tie rules, and what is read off columns."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .kernels import DRAW_MOD, DRAW_MUL

GAP = "_"


def cells(aligned: DataFrame) -> DataFrame:
    """family, seq_id, pos (from 0), symbol."""
    return aligned.select("family", "seq_id", F.posexplode(F.split("aligned", "")).alias("pos", "symbol")).where("symbol <> ''")


def build(aligned: DataFrame, min_rows: int = 2) -> DataFrame:
    """family, pos, symbol, n, freq: gaps count; families of fewer rows than min_rows have no profile."""
    enough = aligned.groupBy("family").agg(F.count("*").alias("rows")).where(F.col("rows") >= min_rows)
    n = cells(aligned).groupBy("family", "pos", "symbol").agg(F.count("*").alias("n"))
    return n.join(enough, "family").select("family", "pos", "symbol", "n", (F.col("n") / F.col("rows")).alias("freq"))


def wide(profile: DataFrame, orient: str = "positions", symbols: list[str] | None = None, width: int | None = None) -> DataFrame:
    """Positions by symbols, or symbols by positions."""
    if orient == "positions":
        return profile.groupBy("family", "pos").pivot("symbol", symbols).agg(F.max("freq"))
    return profile.groupBy("family", "symbol").pivot("pos", list(range(width)) if width else None).agg(F.max("freq"))


def draw(seed: int, family: Column, node: int, pos: Column, k: Column) -> Column:
    """The same number below k as kernels.draw."""
    x = F.lit((seed + 1) % DRAW_MOD).cast("long")
    for v in (F.crc32(family.cast("binary")), F.lit(node), pos.cast("long"), F.lit(0), F.lit(0)):
        x = (x * DRAW_MUL + v) % DRAW_MOD
    return x % k


def ties(profile: DataFrame, gap_policy: str = "include") -> DataFrame:
    """family, pos, tied: the equally most frequent symbols, in order."""
    if gap_policy == "exclude":
        letters = F.sum((F.col("symbol") != GAP).cast("int")).over(Window.partitionBy("family", "pos"))
        profile = profile.withColumn("letters", letters).where((F.col("symbol") != GAP) | (F.col("letters") == 0))
    top = profile.withColumn("rank", F.rank().over(Window.partitionBy("family", "pos").orderBy(F.desc("n")))).where("rank = 1")
    return top.groupBy("family", "pos").agg(F.array_sort(F.collect_set("symbol")).alias("tied"))


def consensus_symbols(profile: DataFrame, tie: str = "first", gap_policy: str = "include", partner: DataFrame | None = None, seed: int = 0, node: int = 0) -> DataFrame:
    """family, pos, symbol. tie="partner": the partner's symbol at that place if it is among the tied ones, else a seeded draw.

    partner: family, pos, symbol; a place that it lacks (a shorter partner) is drawn too.
    """
    t = ties(profile, gap_policy)
    if tie == "first":
        return t.select("family", "pos", F.col("tied")[0].alias("symbol"))
    if tie == "last":
        return t.select("family", "pos", F.element_at("tied", -1).alias("symbol"))
    drawn = F.element_at("tied", (draw(seed, F.col("family"), node, F.col("pos"), F.size("tied")) + 1).cast("int"))
    if partner is None:
        return t.select("family", "pos", drawn.alias("symbol"))
    p = partner.select("family", "pos", F.col("symbol").alias("theirs"))
    return t.join(p, ["family", "pos"], "left").select("family", "pos", F.when(F.array_contains("tied", F.col("theirs")), F.col("theirs")).otherwise(drawn).alias("symbol"))


def as_string(symbols: DataFrame) -> DataFrame:
    """family, consensus."""
    joined = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("pos", "symbol"))), lambda x: x["symbol"]), "")
    return symbols.groupBy("family").agg(joined.alias("consensus"))


def consensus(profile: DataFrame, **kw) -> DataFrame:
    return as_string(consensus_symbols(profile, **kw))


def entropy(profile: DataFrame) -> DataFrame:
    """family, pos, entropy in bits."""
    return profile.groupBy("family", "pos").agg(F.sum(-F.col("freq") * F.log2("freq")).alias("entropy"))


def conservation(profile: DataFrame) -> DataFrame:
    """family, pos, identity: share of the most frequent letter among all rows; 0 for a column of gaps."""
    return profile.groupBy("family", "pos").agg(F.coalesce(F.max(F.when(F.col("symbol") != GAP, F.col("freq"))), F.lit(0.0)).alias("identity"))


def conserved_blocks(profile: DataFrame, identity: float = 1.0, least: int = 2) -> DataFrame:
    """family, start, width: maximal runs of columns of that identity or more."""
    good = conservation(profile).where(F.col("identity") >= identity - 1e-12)
    run = good.withColumn("run", F.col("pos") - F.row_number().over(Window.partitionBy("family").orderBy("pos")))
    return run.groupBy("family", "run").agg(F.min("pos").alias("start"), F.count("*").alias("width")).where(F.col("width") >= least).select("family", "start", "width")


def motif_scan(profile: DataFrame, width: int = 4) -> DataFrame:
    """family, pos, motif, mean identity of each consensus window, best first by rank."""
    both = consensus_symbols(profile).join(conservation(profile), ["family", "pos"])
    w = Window.partitionBy("family").orderBy("pos").rowsBetween(0, width - 1)
    scan = both.select("family", "pos", F.array_join(F.collect_list("symbol").over(w), "").alias("motif"), F.avg("identity").over(w).alias("identity"))
    scan = scan.where(F.length("motif") == width).withColumn("identity", F.round("identity", 9))
    return scan.withColumn("rank", F.row_number().over(Window.partitionBy("family").orderBy(F.desc("identity"), "pos")))


def motif_occurrences(aligned: DataFrame, pattern: str) -> DataFrame:
    """family, seq_id, place of the pattern in the sequence, column of its first symbol."""
    at = coordinate_map(aligned).where("letter IS NOT NULL")
    place = F.explode(F.transform(F.sequence(F.lit(1), F.greatest(F.length("seq") - len(pattern) + 1, F.lit(1))), lambda i: F.when(F.substring("seq", i, F.lit(len(pattern))) == pattern, i - 1)))
    hits = aligned.select("family", "seq_id", F.regexp_replace("aligned", GAP, "").alias("seq")).select("family", "seq_id", place.alias("letter")).where("letter IS NOT NULL")
    return hits.join(at, ["family", "seq_id", "letter"]).select("family", "seq_id", "letter", "pos")


def coordinate_map(aligned: DataFrame) -> DataFrame:
    """family, seq_id, pos, symbol, letter: number of the sequence's letter at each column, null at gaps."""
    w = Window.partitionBy("family", "seq_id").orderBy("pos").rowsBetween(Window.unboundedPreceding, 0)
    upto = F.sum((F.col("symbol") != GAP).cast("int")).over(w)
    return cells(aligned).withColumn("letter", F.when(F.col("symbol") != GAP, upto - 1).cast("int"))
