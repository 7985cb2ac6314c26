"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

Stages are timed apart (distances, tree, merges with cost), both tree methods under equal settings, with the median of
three runs and their range. Distances are written once and read by both trees.
"""

from __future__ import annotations

import json
import os
import sys
import time
from statistics import median

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))


def main() -> None:
    from pyspark.sql import SparkSession
    from pyspark.sql import functions as F

    cpus, sf = os.environ.get("BENCH_CPUS", "8"), os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("bench")
        .config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "12g").config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from alignspark.functions.scoring import Scoring
    from alignspark.operators import distance, guidetree, measures, progressive
    from alignspark.plans.shared import cut
    from alignspark.sources import tables
    from alignspark.sources.sinks import to_noop

    s, seconds, ranges, facts = Scoring.experiment(), {}, {}, {}

    def timed(name: str, make, repeats: int = 3) -> None:
        took = []
        for _ in range(repeats):
            t = time.perf_counter()
            to_noop(make())
            took.append(time.perf_counter() - t)
        seconds[name], ranges[name] = round(median(took), 3), [round(min(took), 3), round(max(took), 3)]

    sources = {"short_orders": tables.orders, "medium_events": tables.events, "large_lineitem": tables.lineitem}
    for name, build in sources.items():
        timed(f"{name}_sequences", lambda: build(spark, sf), 1)
        seqs = cut(build(spark, sf), "bench")
        timed(f"{name}_distances", lambda: distance.pairwise_distances(seqs, "mismatch_gap", s), 1 if name == "large_lineitem" else 3)
        d = cut(distance.pairwise_distances(seqs, "mismatch_gap", s), "bench")
        trees = {"nj": lambda: guidetree.neighbor_joining(d), "agg": lambda: guidetree.agglomerative(d)}
        for method, tree in trees.items():
            timed(f"{name}_tree_{method}", tree)
            guide = cut(tree(), "bench")
            timed(f"{name}_merge_cost_{method}", lambda: measures.total_cost(progressive.align(seqs, guide, s), s))
            rows = cut(progressive.align(seqs, guide, s), "bench")
            total = measures.sum_of_pairs(rows, s).join(measures.total_cost(rows, s), "family").agg(F.sum("score").alias("s"), F.sum("cost").alias("c")).first()
            facts[f"{name}_{method}"] = {"score": total["s"], "cost": total["c"]}
        w = measures.work(seqs).agg(F.sum("cells").alias("c"), F.count("*").alias("n")).first()
        facts[name] = {"families": w["n"], "cells": w["c"], "cells_a_second": round(w["c"] / seconds[f"{name}_distances"]), "families_a_second": round(w["n"] / (seconds[f"{name}_distances"] + seconds[f"{name}_tree_nj"] + seconds[f"{name}_merge_cost_nj"]), 1)}
    timed("edit_distances_lineitem", lambda: distance.pairwise_distances(tables.lineitem(spark, sf), "edit"), 1)
    timed("compare_setups_events", lambda: progressive.compare(tables.events(spark, sf), seeds=(0,)), 1)
    print(json.dumps({"metric": "total seconds of the headline queries", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "ranges": ranges, "facts": facts, "sf": os.path.basename(sf.rstrip("/"))}))


if __name__ == "__main__":
    main()
