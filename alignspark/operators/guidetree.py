"""Guide trees: one task a family for all but giant families, and the same rounds as relations (see plans.giant)."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..schemas import MERGES
from . import kernels as K
from .distance import both_ways

_JOIN = pa.struct([("step", pa.int32()), ("left", pa.int32()), ("right", pa.int32()), ("node", pa.int32()), ("left_len", pa.float64()), ("right_len", pa.float64()), ("height", pa.float64())])


def square(table: pa.Table) -> tuple[list[int], np.ndarray]:
    """(ids in order, dense matrix) of one family's distance rows."""
    i, j, v = (table.column(c).to_pylist() for c in ("i", "j", "distance"))
    ids = sorted({*i, *j})
    at = {x: k for k, x in enumerate(ids)}
    d = np.zeros((len(ids), len(ids)))
    for a, b, x in zip(i, j, v):
        d[at[a], at[b]] = d[at[b], at[a]] = x
    return ids, d


def _trees(dist: DataFrame, build) -> DataFrame:
    """Merges of each family's tree; leaves are numbered by the order of ids, which each row carries."""

    def run(table: pa.Table) -> pa.Table:
        ids, d = square(table)
        joins = build(d).joins
        cols = list(zip(*joins)) if joins else [()] * 6
        names = ("left", "right", "node", "left_len", "right_len", "height")
        types = (pa.int32(),) * 3 + (pa.float64(),) * 3
        made = {"family": pa.array([table.column("family")[0].as_py()] * len(joins), pa.string()), "step": pa.array(range(len(joins)), pa.int32())}
        made |= {n: pa.array(list(c), t) for n, c, t in zip(names, cols, types)}
        return pa.table(made | {"ids": pa.array([ids] * len(joins), pa.list_(pa.int64()))})

    return dist.groupBy("family").applyInArrow(run, MERGES)


def neighbor_joining(dist: DataFrame, impl: str = "local", root: str = "midpoint", negative: str = "keep", search: str = "scan") -> DataFrame:
    if impl == "relational":
        from ..plans.giant import relational_tree

        return relational_tree(dist, "neighbor_joining")
    return _trees(dist, lambda d: K.neighbor_joining(d, root, negative, search))


def agglomerative(dist: DataFrame, linkage: str = "average", impl: str = "local", search: str = "scan") -> DataFrame:
    if linkage not in K.LINKAGES:
        raise ValueError(f"unknown linkage {linkage}")
    if impl == "relational":
        from ..plans.giant import relational_tree

        return relational_tree(dist, linkage)
    return _trees(dist, lambda d: K.agglomerative(d, linkage, search))


def caterpillar(dist: DataFrame) -> DataFrame:
    return _trees(dist, lambda d: K.caterpillar(len(d)))


def random_tree(dist: DataFrame, seed: int = 0) -> DataFrame:
    return _trees(dist, lambda d: K.random_tree(len(d), seed))


def star(dist: DataFrame) -> DataFrame:
    return _trees(dist, K.star)


# one round of Neighbor-Joining, step by step, over a distance table


def nj_divergence(dist: DataFrame) -> DataFrame:
    """family, i, r: summed distances over the number of clusters less 2; families of two have none."""
    return both_ways(dist).groupBy("family", "i").agg(F.sum("distance").alias("s"), F.count("*").alias("n")).where("n > 1").select("family", "i", (F.col("s") / (F.col("n") - 1)).alias("r"))


def nj_criterion(dist: DataFrame) -> DataFrame:
    """family, i, j, criterion: distance less both divergences."""
    r = nj_divergence(dist)
    return dist.join(r.select("family", "i", F.col("r").alias("ri")), ["family", "i"]).join(r.select("family", F.col("i").alias("j"), F.col("r").alias("rj")), ["family", "j"]).select("family", "i", "j", "distance", "ri", "rj", (F.col("distance") - F.col("ri") - F.col("rj")).alias("criterion"))


def nj_first_join(dist: DataFrame) -> DataFrame:
    """family, i, j, criterion, distance, ri, rj of the first pair: least criterion (to 9 places), then ids."""
    c = nj_criterion(dist)
    least = F.min(F.struct(F.round("criterion", 9).alias("c"), F.col("i").alias("a"), F.col("j").alias("b"), "distance", "ri", "rj"))
    return c.groupBy("family").agg(least.alias("m")).select("family", F.col("m.a").alias("i"), F.col("m.b").alias("j"), F.col("m.c").alias("criterion"), "m.distance", "m.ri", "m.rj")


def nj_branches(dist: DataFrame) -> DataFrame:
    """family, i, j, stem_i, stem_j of the first join."""
    f = nj_first_join(dist)
    x = (F.col("distance") + F.col("ri") - F.col("rj")) / 2
    return f.select("family", "i", "j", x.alias("stem_i"), (F.col("distance") - x).alias("stem_j"))


def nj_reduce(dist: DataFrame) -> DataFrame:
    """family, other, distance: distances of the first join's new cluster to all others."""
    f = nj_first_join(dist).select("family", F.col("i").alias("p"), F.col("j").alias("q"), F.col("distance").alias("pq"))
    b = both_ways(dist).join(f, "family").where("i IN (p, q) AND j NOT IN (p, q)")
    return b.groupBy("family", F.col("j").alias("other")).agg(((F.sum("distance") - F.max("pq")) / 2).alias("distance"))


# views of merge tables


def tree_of(rows: list[dict]) -> tuple[K.Tree, list[int]]:
    rows = sorted(rows, key=lambda r: r["step"])
    ids = rows[0]["ids"]
    return K.Tree(len(ids), [(r["left"], r["right"], r["node"], r["left_len"], r["right_len"], r["height"]) for r in rows]), ids


def _per_tree(merges: DataFrame, schema: str, make) -> DataFrame:
    """make(tree, ids) gives rows without family."""
    from pyspark.sql.types import StructType

    arrow = StructType.fromDDL(schema)

    def run(table: pa.Table) -> pa.Table:
        from pyspark.sql.pandas.types import to_arrow_schema

        family = table.column("family")[0].as_py()
        rows = [(family, *r) for r in make(*tree_of(table.to_pylist()))]
        s = to_arrow_schema(arrow)
        return pa.table({f.name: pa.array([r[i] for r in rows], f.type) for i, f in enumerate(s)})

    return merges.groupBy("family").applyInArrow(run, schema)


def newick(merges: DataFrame) -> DataFrame:
    return _per_tree(merges, "family string, newick string", lambda t, ids: [(t.newick(ids),)])


def splits(merges: DataFrame) -> DataFrame:
    """family, split: ids on one side, as text, of each inner edge."""
    return _per_tree(merges, "family string, split string", lambda t, ids: [(",".join(str(ids[i]) for i in sorted(s)),) for s in sorted(t.splits(), key=sorted)])


def levels(merges: DataFrame) -> DataFrame:
    return _per_tree(merges, "family string, node int, level int", lambda t, ids: sorted(t.levels().items()))


def cophenetic(merges: DataFrame) -> DataFrame:
    return _per_tree(merges, "family string, i bigint, j bigint, distance double", lambda t, ids: [(ids[i], ids[j], float(d)) for d_ in [t.cophenetic()] for i in range(t.n) for j in range(i + 1, t.n) for d in [d_[i, j]]])


def rerooted(merges: DataFrame) -> DataFrame:
    """The same trees with their roots at the midpoint."""
    return _per_tree(merges, MERGES, lambda t, ids: [(k, *j[:3], float(j[3]), float(j[4]), float(j[5]), ids) for k, j in enumerate(K.midpoint(t).joins)])


def leaf_order(merges: DataFrame) -> DataFrame:
    return _per_tree(merges, "family string, place int, seq_id bigint", lambda t, ids: [(k, ids[i]) for k, i in enumerate(t.leaf_order())])


def compact(merges: DataFrame) -> DataFrame:
    """One row a family, its merges in an array."""
    return merges.groupBy("family").agg(F.array_sort(F.collect_list(F.struct("step", "left", "right", "node", "left_len", "right_len", "height"))).alias("merges"), F.first("ids").alias("ids"))


def robinson_foulds(one: DataFrame, other: DataFrame) -> DataFrame:
    """family, only_one, only_other, rf, normalised: inner edges that one tree has and the other lacks."""
    a, b = splits(one).withColumn("a", F.lit(1)), splits(other).withColumn("b", F.lit(1))
    n = one.select("family", F.size("ids").alias("n")).distinct()
    x = a.join(b, ["family", "split"], "full").groupBy("family").agg(F.sum(F.when(F.col("b").isNull(), 1).otherwise(0)).alias("only_one"), F.sum(F.when(F.col("a").isNull(), 1).otherwise(0)).alias("only_other"))
    x = n.join(x, "family", "left").fillna(0)
    rf = F.col("only_one") + F.col("only_other")
    return x.select("family", "only_one", "only_other", rf.alias("rf"), F.when(F.col("n") > 3, rf / (2 * (F.col("n") - 3))).otherwise(0.0).alias("normalised"))


def same_topology(one: DataFrame, other: DataFrame) -> DataFrame:
    return robinson_foulds(one, other).select("family", (F.col("rf") == 0).alias("same"))
