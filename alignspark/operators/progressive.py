"""Progressive alignment of families: encode, distances, tree, merges in tree order, cost.

A family of ordinary size is one task from distances to rows; sequences reach it by one shuffle on family. Options are
those of kernels.Options. Families of one return themselves; two are aligned directly. Giant families are counted out first
and go to plans.giant; compare() is for families that fit a task.
"""

from __future__ import annotations

import time
from dataclasses import replace

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.scoring import Scoring
from ..plans.shared import cut
from ..schemas import ALIGNED, RESULTS
from . import kernels as K
from .guidetree import tree_of

#: Sequences of a family beyond which one task would hold too large a matrix (8 n^2 bytes) and the giant plan takes over.
LOCAL_LIMIT = 2000


def build_tree(d, method: str, linkage: str = "average", root: str = "midpoint", seed: int = 0) -> K.Tree:
    if method == "neighbor_joining":
        return K.neighbor_joining(d, root)
    if method == "agglomerative":
        return K.agglomerative(d, linkage)
    if method == "input":
        return K.caterpillar(len(d))
    if method == "random":
        return K.random_tree(len(d), seed)
    if method == "star":
        return K.star(d)
    raise ValueError(f"unknown tree method {method}")


def _rows(table: pa.Table) -> tuple[str, list[int], list[str]]:
    rows = sorted(zip(table.column("seq_id").to_pylist(), table.column("seq").to_pylist()))
    return table.column("family")[0].as_py(), [i for i, _ in rows], [s or "" for _, s in rows]


def _giants(slim: DataFrame, limit: int) -> DataFrame | None:
    """Families of more than `limit` sequences, if there are any; found by a count before any matrix is made."""
    big = slim.groupBy("family").agg(F.count("*").alias("n")).where(F.col("n") > limit).select("family")
    big = cut(big, "giants")
    return big if big.limit(1).count() else None


def align(seqs: DataFrame, tree: str | DataFrame = "neighbor_joining", scoring: Scoring | None = None, metric: str = "mismatch_gap", linkage: str = "average", root: str = "midpoint", collapse_equal: bool = False, limit: int = LOCAL_LIMIT, **options) -> DataFrame:
    """family, seq_id, aligned. tree: a method's name, or merges whose ids are the sequences'.

    collapse_equal: equal sequences of a family are aligned once and share the row (changes the tree a little).
    limit: families of more sequences go to plans.giant.align_by_representatives, which calls this for its groups; there
    equal sequences share a row, so that no group can be all of one sequence. Merges given as a table are followed as
    they are, each family in one task.
    """
    o = K.Options(scoring=scoring or Scoring.experiment(), **options)
    slim, method = seqs.select("family", "seq_id", "seq"), tree if isinstance(tree, str) else "neighbor_joining"
    if isinstance(tree, str) and (big := _giants(slim, limit)) is not None:
        from ..plans.giant import align_by_representatives

        rest = align(slim.join(big, "family", "left_anti"), tree, o.scoring, metric, linkage, root, collapse_equal, limit=1 << 62, **options)
        many = slim.join(big, "family", "left_semi")
        texts = cut(many.groupBy("family", "seq").agg(F.min("seq_id").alias("first")), "texts")
        few = texts.select("family", F.col("first").alias("seq_id"), "seq")
        over = _giants(few, limit)
        if over is None:
            rows = align(few, tree, o.scoring, metric, linkage, root, limit=1 << 62, **options)
        else:
            rows = align(few.join(over, "family", "left_anti"), tree, o.scoring, metric, linkage, root, limit=1 << 62, **options)
            rows = rows.unionByName(align_by_representatives(few.join(over, "family", "left_semi"), metric=metric, tree=tree, scoring=o.scoring, limit=limit, **options))
        rows = rows.select("family", F.col("seq_id").alias("first"), "aligned")
        back = many.join(texts, ["family", "seq"]).join(rows, ["family", "first"]).select("family", "seq_id", "aligned")
        return rest.unionByName(back)

    def aligned(family: str, ids: list[int], strings: list[str], merges: list[dict] | None) -> pa.Table:
        some = sorted(set(strings), key=strings.index) if collapse_equal else strings
        if len(some) == 1:
            rows = list(some)
        else:
            if merges:
                guide, named = tree_of(merges)
                if named != ids or collapse_equal:
                    raise ValueError(f"family {family}: the tree's leaves aren't its sequences")
            else:
                guide = build_tree(K.distance_matrix(some, metric, o.scoring, o.traceback), method, linkage, root, o.seed)
            rows, _ = K.progressive(some, guide, o, family)
        by = dict(zip(some, rows)) if collapse_equal else None
        return pa.table({"family": pa.array([family] * len(ids), pa.string()), "seq_id": pa.array(ids, pa.int64()), "aligned": pa.array([by[s] for s in strings] if by else rows, pa.string())})

    if isinstance(tree, str):
        return slim.groupBy("family").applyInArrow(lambda t: aligned(*_rows(t), None), ALIGNED)

    def with_tree(t: pa.Table, m: pa.Table) -> pa.Table:
        if not t.num_rows:
            return pa.table({"family": pa.array([], pa.string()), "seq_id": pa.array([], pa.int64()), "aligned": pa.array([], pa.string())})
        return aligned(*_rows(t), m.to_pylist() or None)

    return slim.groupBy("family").cogroup(tree.groupBy("family")).applyInArrow(with_tree, ALIGNED)


def setup(number: int) -> dict:
    """Arguments of align() for the two setups compared: 1 the agglomerative tree, 2 Neighbor-Joining."""
    return {"scoring": Scoring.experiment(), "tree": {1: "agglomerative", 2: "neighbor_joining"}[number]}


def compare(seqs: DataFrame, seeds: tuple[int, ...] = (0, 1, 2), metric: str = "mismatch_gap", linkage: str = "average", scoring: Scoring | None = None, **options) -> DataFrame:
    """A row for each family, method, root and seed under equal settings; a family's distances are computed once for all.

    methods: agglomerative, and Neighbor-Joining rooted on its last edge and at its midpoint. same_topology: whether the
    unrooted tree has the agglomerative tree's splits. secs: tree, merges and cost, without the shared distances.
    """
    base = K.Options(scoring=scoring or Scoring.experiment(), **options)
    s = base.scoring

    def run(table: pa.Table) -> pa.Table:
        family, _, strings = _rows(table)
        out = []
        if len(strings) > 1:
            d = K.distance_matrix(strings, metric, s, base.traceback)
            plain = K.agglomerative(d, linkage).splits()
            for method, root in (("agglomerative", "top"), ("neighbor_joining", "last"), ("neighbor_joining", "midpoint")):
                for seed in seeds:
                    began = time.perf_counter()
                    guide = build_tree(d, method, linkage, root)
                    rows, cells = K.progressive(strings, guide, replace(base, seed=seed), family)
                    same, other, gaps = K.sum_of_pairs(rows, s)
                    score = s.match * same + s.mismatch * other + s.gap * gaps
                    cost = (s.match - s.mismatch) * other + (s.match / 2 - s.gap) * gaps
                    out.append((family, method, root, seed, int(score), float(cost), len(rows[0]), cells, guide.splits() == plain, time.perf_counter() - began))
        types = (pa.string(), pa.string(), pa.string(), pa.int32(), pa.int64(), pa.float64(), pa.int32(), pa.int64(), pa.bool_(), pa.float64())
        names = [x.split()[0] for x in RESULTS.split(", ")]
        return pa.table({n: pa.array([r[i] for r in out], t) for i, (n, t) in enumerate(zip(names, types))})

    return seqs.select("family", "seq_id", "seq").groupBy("family").applyInArrow(run, RESULTS)


def compare_summary(results: DataFrame) -> DataFrame:
    """method, root, runs, mean and spread of score and cost over all families and seeds; never the best of several."""
    return results.groupBy("method", "root").agg(F.count("*").alias("runs"), F.avg("score").alias("mean_score"), F.stddev("score").alias("sd_score"), F.avg("cost").alias("mean_cost"), F.min("cost").alias("min_cost"), F.max("cost").alias("max_cost"), F.avg("secs").alias("mean_secs"))


def add_sequence(aligned: DataFrame, new: DataFrame, scoring: Scoring | None = None, **options) -> DataFrame:
    """aligned with one more sequence a family (the least seq_id of new): a single sequence-profile merge."""
    o = K.Options(scoring=scoring or Scoring.experiment(), **options)

    def run(old: pa.Table, more: pa.Table) -> pa.Table:
        rows = sorted(zip(old.column("seq_id").to_pylist(), old.column("aligned").to_pylist()))
        family = (old if old.num_rows else more).column("family")[0].as_py()
        add = sorted(zip(more.column("seq_id").to_pylist(), more.column("seq").to_pylist()))[:1]
        ids, strings = [i for i, _ in rows] + [i for i, _ in add], [s for _, s in rows]
        for _, s in add:
            strings = K.add_sequence(strings, s, o, family) if strings else [s]
        return pa.table({"family": pa.array([family] * len(ids), pa.string()), "seq_id": pa.array(ids, pa.int64()), "aligned": pa.array(strings, pa.string())})

    return aligned.select("family", "seq_id", "aligned").groupBy("family").cogroup(new.select("family", "seq_id", "seq").groupBy("family")).applyInArrow(run, ALIGNED)


def exact_three(seqs: DataFrame, scoring: Scoring | None = None, limit: int = 60) -> DataFrame:
    """family, score: the exact optimum of families of three short sequences; other families are left out."""
    s = scoring or Scoring.experiment()

    def run(table: pa.Table) -> pa.Table:
        family, _, strings = _rows(table)
        ok = len(strings) == 3 and max(map(len, strings)) <= limit
        return pa.table({"family": pa.array([family] * ok, pa.string()), "score": pa.array([int(K.exact_three(*strings, s, limit))] * ok if ok else [], pa.int64())})

    return seqs.select("family", "seq_id", "seq").groupBy("family").applyInArrow(run, "family string, score bigint")
