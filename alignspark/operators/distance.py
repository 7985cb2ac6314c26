"""Pairwise distances of families of sequences, and views of a distance table."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.columns import kmers
from ..functions.scoring import Scoring
from ..schemas import DISTANCES
from . import kernels as K
from .pairwise import edit_distance, global_score, pairs


def pairwise_distances(seqs: DataFrame, metric: str = "mismatch_gap", scoring: Scoring | None = None, plan: str = "auto", k: int = 3) -> DataFrame:
    """family, i, j, distance for i < j. Metrics: mismatch_gap, p_distance, edit, score_normalised, score_gap, kmer, jc_corrected.

    edit and kmer run in the JVM; the others send pairs through Arrow. plan="local" computes a family's matrix in one task.
    """
    scoring = scoring or Scoring.experiment()
    if plan == "local":
        return _local(seqs, metric, scoring)
    p = pairs(seqs, plan)
    if metric == "edit":
        return p.select("family", "i", "j", edit_distance("a", "b").cast("double").alias("distance"))
    if metric == "kmer":
        return kmer_distances(seqs, k)
    if metric in ("score_gap", "score_normalised"):
        s = p.withColumn("s", global_score("a", "b", scoring))
        if metric == "score_gap":
            return s.select("family", "i", "j", (F.max("s").over(Window.partitionBy("family")) - F.col("s")).cast("double").alias("distance"))
        # a sequence against itself matches all along
        own = F.least(F.length("a"), F.length("b")) * F.lit(scoring.match)
        return s.select("family", "i", "j", F.when(own > 0, 1 - F.col("s") / own).otherwise((F.col("a") != F.col("b")).cast("double")).alias("distance"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            d = K.distances(list(zip(batch.column(3).to_pylist(), batch.column(4).to_pylist())), metric, scoring)
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], pa.array(d, pa.float64())], names=["family", "i", "j", "distance"])

    return p.mapInArrow(run, DISTANCES)


def kmer_distances(seqs: DataFrame, k: int = 3) -> DataFrame:
    """1 - shared k-mers (with repeats) over those of the shorter one: counts join on family and k-mer, no alignment."""
    counts = seqs.select("family", "seq_id", F.explode(kmers(F.col("seq"), k)).alias("g")).groupBy("family", "seq_id", "g").agg(F.count("*").alias("n"))
    a, b = (counts.select("family", "g", F.col("seq_id").alias(c), F.col("n").alias(n)) for c, n in (("i", "x"), ("j", "y")))
    shared = a.join(b, ["family", "g"]).where("i < j").groupBy("family", "i", "j").agg(F.sum(F.least("x", "y")).alias("s"))
    every = pairs(seqs)
    short = F.least(F.length("a"), F.length("b")) - (k - 1)
    return every.join(shared, ["family", "i", "j"], "left").select("family", "i", "j", F.when(short > 0, 1 - F.coalesce("s", F.lit(0)) / short).otherwise((F.col("a") != F.col("b")).cast("double")).alias("distance"))


def _local(seqs: DataFrame, metric: str, scoring: Scoring) -> DataFrame:
    def run(table: pa.Table) -> pa.Table:
        rows = sorted(zip(table.column("seq_id").to_pylist(), table.column("seq").to_pylist()))
        d = K.distance_matrix([s for _, s in rows], metric, scoring)
        at = [(i, j) for i in range(len(rows)) for j in range(i + 1, len(rows))]
        return pa.table({"family": pa.array([table.column("family")[0].as_py()] * len(at), pa.string()), "i": pa.array([rows[i][0] for i, _ in at], pa.int64()), "j": pa.array([rows[j][0] for _, j in at], pa.int64()), "distance": pa.array([float(d[i, j]) for i, j in at], pa.float64())})

    return seqs.groupBy("family").applyInArrow(run, DISTANCES)


def both_ways(d: DataFrame) -> DataFrame:
    """Each pair in both orders."""
    return d.select("family", "i", "j", "distance").unionByName(d.select("family", F.col("j").alias("i"), F.col("i").alias("j"), "distance"))


def to_square(d: DataFrame, ids: list[int]) -> DataFrame:
    """family, i and a column for each id of ids."""
    return both_ways(d).groupBy("family", "i").pivot("j", ids).agg(F.max("distance"))


def triangle_violations(d: DataFrame) -> DataFrame:
    """family, violations: ordered triples whose direct distance is longer than the way round."""
    b = both_ways(d)
    x = b.select("family", "i", F.col("j").alias("k"), F.col("distance").alias("ik"))
    y = b.select("family", F.col("i").alias("k"), "j", F.col("distance").alias("kj"))
    t = b.join(x, ["family", "i"]).join(y, ["family", "k", "j"]).where("k <> i AND k <> j")
    return t.groupBy("family").agg(F.sum((F.col("distance") > F.col("ik") + F.col("kj") + 1e-9).cast("bigint")).alias("violations"))


def _triples(d: DataFrame) -> DataFrame:
    ij = d.select("family", "i", "j", F.col("distance").alias("ij"))
    jk = d.select("family", F.col("i").alias("j"), F.col("j").alias("k"), F.col("distance").alias("jk"))
    ik = d.select("family", "i", F.col("j").alias("k"), F.col("distance").alias("ik"))
    return ij.join(jk, ["family", "j"]).join(ik, ["family", "i", "k"])


def three_point(d: DataFrame) -> DataFrame:
    """family, triples, ultrametric: triples whose two largest distances are equal."""
    s = F.array_sort(F.array("ij", "jk", "ik"))
    return _triples(d).groupBy("family").agg(F.count("*").alias("triples"), F.sum((F.abs(s[2] - s[1]) < 1e-9).cast("bigint")).alias("ultrametric"))


def four_point(d: DataFrame) -> DataFrame:
    """family, quartets, additive: quartets whose two largest sums of opposite pairs are equal."""
    t = _triples(d)
    e = lambda a, b: d.select("family", F.col("i").alias(a), F.col("j").alias(b), F.col("distance").alias(a + b))
    q = t.join(e("i", "l"), ["family", "i"]).join(e("j", "l"), ["family", "j", "l"]).join(e("k", "l"), ["family", "k", "l"])
    s = F.array_sort(F.array(F.col("ij") + F.col("kl"), F.col("ik") + F.col("jl"), F.col("il") + F.col("jk")))
    return q.groupBy("family").agg(F.count("*").alias("quartets"), F.sum((F.abs(s[2] - s[1]) < 1e-9).cast("bigint")).alias("additive"))


def nearest(d: DataFrame, k: int) -> DataFrame:
    w = Window.partitionBy("family", "i").orderBy("distance", "j")
    return both_ways(d).withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def check_metric(d: DataFrame) -> DataFrame:
    """family, pairs, negative, violations: symmetric and zero on the diagonal by construction."""
    head = d.groupBy("family").agg(F.count("*").alias("pairs"), F.sum((F.col("distance") < 0).cast("bigint")).alias("negative"))
    return head.join(triangle_violations(d), "family", "left").fillna(0, ["violations"])


def materialise(d: DataFrame, path: str) -> DataFrame:
    """Written once, read by every tree."""
    d.write.mode("overwrite").parquet(path)
    return d.sparkSession.read.schema(d.schema).parquet(path)
