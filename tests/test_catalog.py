"""Every query of the catalogue on the smallest tables: against DuckDB where there is SQL, else for rows and schema."""

import math
from collections import Counter

import pytest

from alignspark import catalog
from alignspark.functions.scoring import Scoring
from alignspark.operators import distance, guidetree, measures, profile, progressive
from alignspark.plans import giant
from alignspark.sources import sinks, tables

SLOW = {"compare_near_copies"}


@pytest.fixture(scope="session")
def duck(sf):
    import duckdb

    con = duckdb.connect()
    for t in catalog.TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


def plain(v):
    return None if isinstance(v, float) and math.isnan(v) else round(v, 5) + 0.0 if isinstance(v, float) else v


@pytest.mark.parametrize("name", sorted(catalog.ORACLES))
def test_oracle(spark, sf, duck, name):
    got = catalog.QUERIES[name](spark, sf)
    cur = duck.execute(catalog.ORACLES[name])
    cols, want = [c[0] for c in cur.description], cur.fetchall()
    assert sorted(cols) == sorted(got.columns)
    rows = Counter(tuple(plain(r[c]) for c in cols) for r in got.collect())
    assert rows == Counter(tuple(map(plain, r)) for r in want)


@pytest.mark.parametrize("name", sorted(set(catalog.QUERIES) - set(catalog.ORACLES) - SLOW))
def test_rows(spark, sf, name):
    rows = catalog.QUERIES[name](spark, sf).collect()
    assert rows or name in ("compare_near_copies",)


def test_plans_agree(spark, sf):
    t = tables.events(spark, sf)
    for metric in ("mismatch_gap", "edit", "score_gap", "score_normalised", "kmer"):
        one = {(r["i"], r["j"]): r["distance"] for r in distance.pairwise_distances(t, metric).collect()}
        for plan in ("shuffle", "blocked", "local"):
            other = {(r["i"], r["j"]): r["distance"] for r in distance.pairwise_distances(t, metric, plan=plan).collect()}
            assert one.keys() == other.keys() and all(math.isclose(one[k], other[k], abs_tol=1e-9) for k in one)
    d = distance.pairwise_distances(t, "edit")
    for kind in ("average", "single"):
        local = sorted(tuple(r)[:5] for r in guidetree.agglomerative(d, kind).collect())
        assert local == sorted(tuple(r)[:5] for r in guidetree.agglomerative(d, kind, impl="relational").collect())


def test_alignment_is_the_same_in_any_partitioning(spark, sf):
    t = tables.events(spark, sf)
    want = sorted(map(tuple, progressive.align(t, seed=5).collect()))
    assert sorted(map(tuple, progressive.align(t.repartition(13), seed=5).collect())) == want
    rows = progressive.align(t)
    s = Scoring.experiment()
    assert sorted(map(tuple, measures.sum_of_pairs(rows, s).collect())) == sorted(map(tuple, measures.sum_of_pairs_bruteforce(rows, s).collect()))
    freq = profile.build(rows).groupBy("family", "pos").sum("freq").collect()
    assert all(abs(r["sum(freq)"] - 1) < 1e-9 for r in freq)


def test_giant_family(spark):
    import random

    rnd = random.Random(2)
    root = "".join(rnd.choice("ACGT") for _ in range(60))
    seqs = [(0, "f", "".join(c if rnd.random() > 0.1 else rnd.choice("ACGT") for c in root)) for _ in range(30)]
    t = spark.createDataFrame([(f, i, s) for i, (_, f, s) in enumerate(seqs)], "family string, seq_id bigint, seq string")
    rows = giant.align_by_representatives(t).collect()
    assert {r["seq_id"]: r["aligned"].replace("_", "") for r in rows} == {i: s for i, (_, _, s) in enumerate(seqs)}
    assert len({len(r["aligned"]) for r in rows}) == 1


def test_large_families_are_dispatched(spark):
    import random

    rnd = random.Random(3)
    texts = ["".join(rnd.choice("ACGT") for _ in range(rnd.randint(3, 12))) for _ in range(40)]
    rows = [("big", k, texts[k % 40]) for k in range(150)] + [("copies", k, "ACGTA") for k in range(60)] + [("small", k, texts[k]) for k in range(5)]
    seqs = spark.createDataFrame(rows, "family string, seq_id bigint, seq string")
    made = progressive.align(seqs, limit=12).collect()
    assert sorted((r["family"], r["seq_id"], r["aligned"].replace("_", "")) for r in made) == sorted(rows)
    assert all(len({len(r["aligned"]) for r in made if r["family"] == f}) == 1 for f in ("big", "copies", "small"))
    few = {(r["family"], r["seq_id"]): r["aligned"] for r in progressive.align(seqs.where("family = 'small'")).collect()}
    assert few == {(r["family"], r["seq_id"]): r["aligned"] for r in made if r["family"] == "small"}


def test_sweeps_and_costs_move_as_they_should(spark, sf):
    rows = {r["size"]: r for r in catalog.QUERIES["sweep_family_size"](spark, sf).collect()}
    assert rows[5]["pairs"] < rows[20]["pairs"] and rows[5]["sequences"] == rows[80]["sequences"]
    cost = {(r["set"], r["method"], r["root"]): r for r in catalog.QUERIES["cost_by_size"](spark, sf).collect()}
    assert {k[0] for k in cost} == {"short", "medium", "long", "clock", "uneven"} and len(cost) == 15


def test_draws_are_the_same_in_spark(spark):
    from pyspark.sql import functions as F

    from alignspark.operators import kernels

    df = spark.range(50).select(F.lit("fam").alias("family"), F.col("id").alias("pos"))
    got = [r[0] for r in df.select(profile.draw(9, F.col("family"), 4, F.col("pos"), F.lit(3))).collect()]
    assert sorted(got) == sorted(kernels.draw(9, "fam", 4, p, 3) for p in range(50))


def test_sinks(spark, sf, tmp_path):
    t = tables.printed(spark)
    sinks.to_fasta(t, str(tmp_path / "fasta"))
    assert sorted(map(tuple, tables.fasta(spark, str(tmp_path / "fasta")).select("seq_id", "seq").collect())) == list(enumerate(tables.PRINTED))
    lines = sinks.blocks(tables.printed(spark, tables.PRINTED_ROWS, name="aligned"), 6).collect()
    assert len(lines) == 21 and all(r["line"][11:] for r in lines)


def test_pushdown_and_one_shuffle(spark, sf):
    plan = tables.events(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1 and "props" not in plan


def test_entry(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_documents_are_folded_whole(spark, tmp_path):
    from alignspark import workloads

    text = " ".join(f"word{'abcdefghij'[i % 10]}{'klmnopqrst'[i // 10 % 10]} x{'uvwxyzabcd'[i // 100]}" for i in range(400))
    texts = [text, text[:-9] + "qqq rr ee", text]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r["seq_id"]: r["len"] for r in catalog.QUERIES["seq_documents_folded"](spark, str(tmp_path)).collect()}
    assert got == {i: sum(c.isalpha() for c in t) for i, t in enumerate(texts)} and min(got.values()) > 1500
    rows = progressive.compare(workloads.near_copy_sequences(spark, str(tmp_path)), seeds=(0,)).collect()
    assert len(rows) == 3 and all(r["cost"] > 0 and r["width"] > 1500 for r in rows)


@pytest.mark.parametrize("name", ["align_edge_cases", "align_printed", "dp_align_pairs"])
def test_rows_come_from_the_table(spark, sf, name):
    rows = catalog.QUERIES[name](spark, sf)
    seqs = tables.conversations(spark, sf)
    families = {r["family"].rsplit("/", 1)[-1] for r in rows.select("family").collect()}
    assert families <= {r["family"] for r in seqs.collect()} and len(families) > 1
    if name == "align_edge_cases":
        by = {}
        for r in rows.collect():
            by.setdefault(r["family"], []).append(r["aligned"])
        assert all(len(set(map(len, x))) == 1 for x in by.values())
        assert {f.split("/")[0] for f in by} == {"one", "two", "empty", "all_empty", "odd", "long", "same"}
        assert all(set(x) == {""} for f, x in by.items() if f.startswith("all_empty"))


def test_copies_are_counted_not_paired(spark):
    from pyspark.sql import functions as F

    from alignspark.operators import pairwise

    seqs = spark.createDataFrame([("f", k, ["AC", "AC", "ACG", "T", "T", "T"][k]) for k in range(6)], "family string, seq_id bigint, seq string")
    got = pairwise.distinct_pairs(seqs, 1)
    assert {(r["a"], r["b"]): r["n"] for r in got.collect()} == {("AC", "ACG"): 2, ("AC", "T"): 6, ("ACG", "T"): 3}
    each = pairwise.pairs(seqs).agg(F.sum(pairwise.edit_distance("a", "b"))).first()[0]
    assert got.agg(F.sum(pairwise.edit_distance("a", "b") * F.col("n"))).first()[0] == each


def test_column_pairs_of_large_families(spark, tmp_path):
    from pyspark.sql import functions as F

    n = 9000
    rows = spark.range(n).select(F.col("id").alias("vec_id"), F.lit(1).alias("label"), F.array_repeat(F.when(F.col("id") == 0, -0.5).otherwise(0.5), 64).alias("embedding"))
    rows.write.parquet(f"{tmp_path}/embeddings.parquet")
    got = [tuple(r) for r in catalog.QUERIES["column_pairs_printed"](spark, str(tmp_path)).collect()]
    assert got == [("1", 64 * (n - 1) * (n - 2) // 2, 64 * (n - 1), 0)] and got[0][1] > 1 << 31


def test_edits_of_blocks_are_those_of_pairs(spark):
    import random

    from pyspark.sql import functions as F

    from alignspark.operators import pairwise

    rnd = random.Random(9)
    texts = ["".join(rnd.choice("ACGTé") for _ in range(rnd.choice([0, 1, 3, 6, 6, 9, 80]))) for _ in range(200)]
    seqs = spark.createDataFrame([("fg"[k % 2], k, rnd.choice(texts)) for k in range(500)], "family string, seq_id bigint, seq string")
    want = {r["family"]: r["edits"] for r in pairwise.pairs(seqs).groupBy("family").agg(F.sum(pairwise.edit_distance("a", "b")).alias("edits")).collect()}
    for block, together in ((1, 30), (400, 20)):
        both = pairwise.distinct_pairs(seqs, block, together).withColumn("edits", pairwise.edit_distance("a", "b", counts=("na", "nb")))
        got = {r["family"]: r["edits"] for r in both.groupBy("family").agg(F.sum(F.expr("shiftright(edits, twice)")).alias("edits")).collect()}
        assert got == want and (together == 20) == (both.count() == 2)
