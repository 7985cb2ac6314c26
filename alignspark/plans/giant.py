"""Giant families: guide trees as rounds of relations, and alignment by way of representatives.

A relational tree takes a round of jobs for each join, so it is for matrices that no task can hold, not for speed; above
some ten thousand live clusters use align_by_representatives, whose tree has only the representatives as leaves.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.scoring import Scoring
from ..operators import kernels as K
from ..schemas import ALIGNED
from .shared import cut

_CHOICE = ("c", "p", "q", "pq", "rp", "rq")


def _both(live: DataFrame) -> DataFrame:
    return live.select("family", "i", "j", "d").unionByName(live.select("family", F.col("j").alias("i"), F.col("i").alias("j"), "d"))


def nj_round(live: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(family, p, q, pq, rp, rq of the pair to join; its distances to the others) for families of 3 clusters or more."""
    r = _both(live).groupBy("family", "i").agg((F.sum("d") / F.greatest(F.count("*") - 1, F.lit(1))).alias("r"))
    c = live.join(r.select("family", "i", F.col("r").alias("ri")), ["family", "i"]).join(r.select("family", F.col("i").alias("j"), F.col("r").alias("rj")), ["family", "j"])
    pick = c.groupBy("family").agg(F.min(F.struct(F.round(F.col("d") - F.col("ri") - F.col("rj"), 9).alias("c"), F.col("i").alias("p"), F.col("j").alias("q"), F.col("d").alias("pq"), F.col("ri").alias("rp"), F.col("rj").alias("rq"))).alias("m"))
    pick = pick.select("family", *[F.col(f"m.{x}").alias(x) for x in _CHOICE])
    near = _both(live).join(pick, "family").where("i IN (p, q) AND j NOT IN (p, q)")
    return pick, near.groupBy("family", "j").agg(((F.sum("d") - F.max("pq")) / 2).alias("d"))


def agglomerative_round(live: DataFrame, sizes: DataFrame, linkage: str) -> tuple[DataFrame, DataFrame]:
    """(family, p, q, pq of the closest pair; the fused cluster's distances to the others)."""
    pick = live.groupBy("family").agg(F.min(F.struct(F.round("d", 9).alias("c"), F.col("i").alias("p"), F.col("j").alias("q"), F.col("d").alias("pq"))).alias("m"))
    pick = pick.select("family", *[F.col(f"m.{x}").alias(x) for x in _CHOICE[:4]], F.lit(0.0).alias("rp"), F.lit(0.0).alias("rq"))
    near = _both(live).join(pick, "family").where("i IN (p, q) AND j NOT IN (p, q)").join(sizes.withColumnRenamed("node", "i"), ["family", "i"])
    new = {"average": F.sum(F.col("d") * F.col("size")) / F.sum("size"), "weighted": F.avg("d"), "single": F.min("d"), "complete": F.max("d")}[linkage]
    return pick, near.groupBy("family", "j").agg(new.alias("d"))


def relational_tree(dist: DataFrame, method: str) -> DataFrame:
    """Merges of every family by rounds over all families at once; Neighbor-Joining is rooted on its last edge."""
    names = dist.select("family", F.col("i").alias("id")).union(dist.select("family", F.col("j").alias("id"))).distinct()
    names = cut(names.withColumn("node", (F.row_number().over(Window.partitionBy("family").orderBy("id")) - 1).cast("int")), "names")
    ids = names.groupBy("family").agg(F.array_sort(F.collect_list("id")).alias("ids"))
    at = lambda c: names.select("family", F.col("id").alias(c), F.col("node").alias(f"n{c}"))
    live = cut(dist.join(at("i"), ["family", "i"]).join(at("j"), ["family", "j"]).select("family", F.col("ni").alias("i"), F.col("nj").alias("j"), F.col("distance").alias("d")), "live")
    sizes = names.select("family", "node", F.lit(1).alias("size"), F.lit(0.0).alias("high"))
    n = ids.select("family", F.size("ids").alias("n"))
    rounds, joins = n.agg(F.max("n")).first()[0] or 1, None
    for step in range(rounds - 1):
        if method == "neighbor_joining":
            pick, new = nj_round(live)
        else:
            pick, new = agglomerative_round(live, sizes, method)
        pick = pick.join(n, "family").withColumn("node", (F.col("n") + step).cast("int"))
        hp, hq = (sizes.select("family", F.col("node").alias(c), F.col("high").alias(f"h{c}"), F.col("size").alias(f"s{c}")) for c in "pq")
        pick = cut(pick.join(hp, ["family", "p"]).join(hq, ["family", "q"]), "pick")
        if method == "neighbor_joining":
            stem = F.when(F.col("n") - step == 2, F.col("pq") / 2).otherwise((F.col("pq") + F.col("rp") - F.col("rq")) / 2)
            done = pick.select("family", F.lit(step).alias("step"), F.col("p").alias("left"), F.col("q").alias("right"), "node", stem.alias("left_len"), (F.col("pq") - stem).alias("right_len"), F.lit(0.0).alias("height"))
        else:
            h = F.col("pq") / 2
            done = pick.select("family", F.lit(step).alias("step"), F.col("p").alias("left"), F.col("q").alias("right"), "node", (h - F.col("hp")).alias("left_len"), (h - F.col("hq")).alias("right_len"), h.alias("height"))
        joins = done if joins is None else joins.unionByName(done)
        few = pick.select("family", "p", "q", "node", "pq", (F.col("sp") + F.col("sq")).alias("size"))
        rest = live.join(few.select("family", "p", "q"), "family").where("i NOT IN (p, q) AND j NOT IN (p, q)").select("family", "i", "j", "d")
        live = cut(rest.unionByName(new.join(few.select("family", "node"), "family").select("family", F.col("j").alias("i"), F.col("node").alias("j"), "d")), "live")
        sizes = cut(sizes.unionByName(few.select("family", "node", "size", (F.col("pq") / 2).alias("high"))), "sizes")
    if joins is None:
        return dist.sparkSession.createDataFrame([], "family string, step int, left int, right int, node int, left_len double, right_len double, height double, ids array<bigint>")
    return joins.join(ids, "family")


def align_by_representatives(seqs: DataFrame, share: float = 0.5, metric: str = "edit", tree: str = "neighbor_joining", scoring: Scoring | None = None, limit: int = 2000, **options) -> DataFrame:
    """family, seq_id, aligned of families too large for one task.

    About n ** share sequences of a family, by a hash of the id, stand for it; each other sequence joins the nearest of
    them, the groups are aligned each in its task, and the groups' profiles (not their rows) are merged in the order of a
    tree over the representatives. Rows then take up the new gaps where they are. A group of more than `limit` sequences
    is a giant family itself.
    """
    from ..operators import progressive
    from ..operators.distance import pairwise_distances

    s = scoring or Scoring.experiment()
    n = seqs.groupBy("family").agg(F.count("*").alias("n"))
    rank = F.row_number().over(Window.partitionBy("family").orderBy(F.xxhash64("seq_id"), "seq_id"))
    few = seqs.join(n, "family").withColumn("rank", rank).where(F.col("rank") <= F.ceil(F.pow("n", F.lit(share)))).select("family", F.col("seq_id").alias("rep"), F.col("seq").alias("rep_seq"))
    few = cut(few, "reps")
    near = seqs.select("family", "seq_id", "seq").join(few, "family").withColumn("d", F.levenshtein("seq", "rep_seq"))
    group = near.groupBy("family", "seq_id").agg(F.min(F.struct("d", "rep")).alias("m"), F.first("seq").alias("seq")).select("family", "seq_id", "seq", F.col("m.rep").alias("rep"))
    group = cut(group, "groups")
    inner = progressive.align(group.select(F.concat_ws("|", "rep", "family").alias("family"), "seq_id", "seq"), tree, s, metric, limit=limit, **options)
    inner = cut(inner.select(F.substring_index("family", "|", 1).cast("bigint").alias("rep"), F.expr("substring(family, instr(family, '|') + 1)").alias("family"), "seq_id", "aligned"), "inner")
    counts = inner.select("family", "rep", F.posexplode(F.split("aligned", "")).alias("pos", "symbol")).where("symbol <> ''").groupBy("family", "rep", "pos", "symbol").agg(F.count("*").alias("c"))
    dist = pairwise_distances(few.select("family", F.col("rep").alias("seq_id"), F.col("rep_seq").alias("seq")), metric, s)
    o = K.Options(scoring=s, **options)

    def merge(profiles: pa.Table, d: pa.Table) -> pa.Table:
        from ..operators.guidetree import square

        family = profiles.column("family")[0].as_py() if profiles.num_rows else ""
        symbols = sorted({*profiles.column("symbol").to_pylist(), K.GAP})
        sides, reps = {}, sorted(set(profiles.column("rep").to_pylist()))
        import numpy as np

        for rep in reps:
            mine = [(p, symbols.index(x), c) for r, p, x, c in zip(*(profiles.column(k).to_pylist() for k in ("rep", "pos", "symbol", "c"))) if r == rep]
            sides[rep] = np.zeros((max(p for p, _, _ in mine) + 1, len(symbols)), np.int64)
            for p, x, c in mine:
                sides[rep][p, x] = c
        place = {r: np.arange(len(sides[r])) for r in reps}
        if len(reps) > 1:
            ids, m = square(d)
            keep = [ids.index(r) for r in reps]
            guide = progressive.build_tree(m[np.ix_(keep, keep)], tree)
            held, members = {k: sides[r] for k, r in enumerate(reps)}, {k: [r] for k, r in enumerate(reps)}
            for a, b, k, *_ in guide.joins:
                at_a, at_b, held[k] = K.merge_columns(held.pop(a), held.pop(b), symbols, o, family, k)
                for side, at in ((a, at_a), (b, at_b)):
                    for r in members[side]:
                        place[r] = at[place[r]]
                members[k] = members[a] + members[b]
            width = len(held[guide.joins[-1][2]])
        else:
            width = len(place[reps[0]]) if reps else 0
        return pa.table({"family": pa.array([family] * len(reps), pa.string()), "rep": pa.array(reps, pa.int64()), "place": pa.array([place[r].tolist() for r in reps], pa.list_(pa.int32())), "width": pa.array([width] * len(reps), pa.int32())})

    places = counts.groupBy("family").cogroup(dist.groupBy("family")).applyInArrow(merge, "family string, rep bigint, place array<int>, width int")
    whole = inner.join(places, ["family", "rep"])
    at = F.map_from_arrays("place", F.split("aligned", ""))
    row = F.array_join(F.transform(F.sequence(F.lit(0), F.col("width") - 1), lambda k: F.coalesce(F.element_at(at, k), F.lit(K.GAP))), "")
    return whole.where("width > 0").select("family", "seq_id", row.alias("aligned")).select(*[x.split()[0] for x in ALIGNED.split(", ")])
