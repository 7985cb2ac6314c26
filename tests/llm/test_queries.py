"""Operators on Spark against brute force, on the small table and on edge cases."""

import hashlib
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F
from test_local import naive_removal, random_docs

from alignspark.llm import decontaminate, html_template, langid, mixing, quality, queries, simhash, suffix_dedup, token_coder, token_output, url_filter
from alignspark.llm.oracles import oracle_sql

CLASHES = "h key bucket size rank node row place gone_node spans items id of words copies rows turn word n at fp label family component_id __spans __items __gone __size __id __n __copies __rows".split()
DOCS = "doc_id long, text string, lang string, source string, n_chars long, " + ", ".join(f"{c} int" for c in CLASHES)


def edge_docs(spark):
    rows = [
        (1, None, "en", "a", None), (2, "", None, None, 0), (3, "one two three", "en", "a", 13), (3, "one two three", "en", "a", 13),
        (4, "word " * 4000, "en", "b", 20000), (None, "no id here at all", None, None, None), (5, "é" * 60, "fr", "c", 60), (6, "é" * 60 + "x", "fr", "c", 61),
        (7, " \t\n", "fr", None, 3), (8, "12345 !!", "de", "b", 8),
    ]
    return spark.createDataFrame([(*r, *range(len(CLASHES))) for r in rows], DOCS)


def no_docs(spark):
    return spark.createDataFrame([], DOCS)


def test_repeats_removed(spark):
    import random

    rnd = random.Random(9)
    for _ in range(2):
        docs = random_docs(rnd)
        want = naive_removal([(d, t.encode()) for d, t in docs], 50)
        got = suffix_dedup.remove_repeats(spark.createDataFrame(docs, "doc_id long, text string"), buckets=5).collect()
        assert {r["doc_id"]: (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in got} == want
    got = suffix_dedup.remove_repeats(edge_docs(spark), buckets=3).collect()
    assert len(got) == 10
    by = {r["doc_id"]: r for r in got}
    assert by[1]["n_bytes"] == 0 and by[1]["kept_sha256"] == hashlib.sha256(b"").hexdigest()
    assert (by[6]["n_removed"], by[6]["n_spans"], by[5]["n_removed"], by[4]["n_removed"]) == (120, 1, 0, 0)
    assert suffix_dedup.remove_repeats(no_docs(spark)).count() == 0


@pytest.mark.parametrize(("gather", "often"), [(300, 1), (300, 1000), (1 << 20, 2)])
def test_repeats_over_stretches_and_frequent_keys(spark, monkeypatch, gather, often):
    import random

    monkeypatch.setattr(suffix_dedup, "HOT_DOCS", often)
    rnd, passage = random.Random(11), "the one passage that every document of this table holds, word for word. "
    docs = [*random_docs(rnd), *((2000 + i, f"{i} own words {i * 7} " + passage + f"and its end {i}") for i in range(60)), *((3000 + i, passage * 3) for i in range(20))]
    want = naive_removal([(d, t.encode()) for d, t in docs], 50)
    got = suffix_dedup.remove_repeats(spark.createDataFrame(docs, "doc_id long, text string"), buckets=3, gather=gather).collect()
    assert {r["doc_id"]: (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in got} == want


def test_tree_decides_on_equal_texts_too():
    text = bytes(range(60)) * 2
    data, size = np.frombuffer(text[:70] * 3, np.uint8), np.array([70, 70, 70])
    assert suffix_dedup.repeated_spans(data, size, np.array([5, 9, 5])).tolist() == [[1, 0, 70]]


def test_packed_rows_follow_the_input_not_the_partitions(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", F.lit(0).cast("long").alias("row"), "text")
    none, counts, before = np.zeros(0, np.uint64), [], spark.conf.get("spark.sql.shuffle.partitions")
    for parts in (8, 64):
        spark.conf.set("spark.sql.shuffle.partitions", str(parts))
        runs = docs.coalesce(1).mapInArrow(lambda b: suffix_dedup._find_runs(b, 3, 3, none, 50, 1 << 20), suffix_dedup.PACKED)
        counts.append(runs.groupBy("at").applyInArrow(lambda t: suffix_dedup._compare_runs(t, 3, 50), suffix_dedup.PACKED).count())
    spark.conf.set("spark.sql.shuffle.partitions", before)
    assert counts[0] == counts[1] <= 3 * (1 + 3 + 3)


def test_rows_of_one_id_are_cut_for_themselves(spark):
    a, b = "".join(chr(97 + i % 23) for i in range(90)), "".join(chr(97 + i * 7 % 19) for i in range(80))
    got = suffix_dedup.remove_repeats(spark.createDataFrame([(1, a), (2, "zz" + a), (2, b + a), (2, b + a)], "doc_id long, text string"), buckets=3).collect()
    assert sorted((r["doc_id"], r["n_bytes"], r["n_removed"]) for r in got) == [(1, 90, 0), (2, 92, 90), (2, 170, 90), (2, 170, 90)]


def test_tokens(spark, sf):
    from tokenizers import Tokenizer

    t, at = Tokenizer.from_file(queries.tokenizer_path()), 0
    want = []
    for r in sorted(spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect(), key=lambda r: r["doc_id"]):
        ids = np.array([*t.encode(r["text"] or "", add_special_tokens=False).ids, 2], "<u4")
        want.append((r["doc_id"], at, len(ids), zlib.crc32(ids.tobytes())))
        at += len(ids)
    assert sorted(tuple(r) for r in queries.op2_token_output(spark, sf).collect()) == want
    edges = token_output.round_trip(edge_docs(spark), queries.tokenizer_path()).collect()
    assert len(edges) == 10 and min(r["start"] for r in edges) == 0
    assert {r["n_tokens"] for r in edges if r["doc_id"] in (1, 2, 7)} == {1}
    assert sum(r["n_tokens"] for r in edges) == max(r["start"] + r["n_tokens"] for r in edges)
    assert token_output.round_trip(no_docs(spark), queries.tokenizer_path()).count() == 0


def test_chunked_tokenizer_equals_whole_text(spark):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(queries.tokenizer_path())
    texts = ["It's 12 o'clock\n\nÉtÉ  ÀB", "a\u0301 b \u0301c", "\tx\u00a0y\u2003z\r\n", "<|endoftext|> a<|endoftext|>b", "don't 'S ''s", "ΑΣ Σ", "İ I", "", " "]
    texts += ["M\u00dcLLER stra\u00dfe42, \u00c9t\u00e9&&& x\x1cy \x1f", "a\u00d7b \u00f7 \u00aa\u00b5 co-op {e}~", "<|startoftext|>", "\u0130stanbul \ufb01n", "\u1e9bx o\u0308", "tab\x0bv\x85n"]
    texts += [r["text"] or "" for r in spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("text").collect()]
    for end in (None, 2):
        c = token_output.CachedTokenizer(queries.tokenizer_path(), end)
        want = [t.encode(x, add_special_tokens=False).ids + ([] if end is None else [end]) for x in texts]
        for _ in range(2):
            ids, sizes = c.encode(texts)
            assert sizes.tolist() == list(map(len, want)) and ids.tolist() == [i for x in want for i in x]


def test_ids_beyond_sixteen_bits():
    ids = np.random.default_rng(2).integers(0, 1 << 32, 3000)
    ids[::3] = 1 << 20
    assert (token_coder.unpack(token_coder.pack(ids)) == ids).all()


def test_coder_in_spark_writes_the_same_bytes(spark):
    """token_jvm against token_coder, both ways; a flipped bit is noticed; decoding plans no Python."""
    from alignspark.llm import token_jvm

    rng, runs = np.random.default_rng(3), [np.zeros(0, int), np.array([2]), np.repeat(7, 3000), np.array([0, 0, 1, 0xFFFFFFFF])]
    runs += [rng.integers(0, 50, 3000), rng.zipf(1.3, 140_000) % 49_000, rng.integers(0, 1 << 16, 5000), rng.integers(0, 1 << 32, 3000), rng.zipf(1.2, 9000) % 100_000]
    token_jvm.register(spark)
    rows = [(i, bytearray(r.astype("<u4").tobytes()), bytearray(token_coder.pack(r)), bytearray(np.array([len(r)], "<i8").tobytes()), bytearray(np.array([i], "<i8").tobytes()), bytearray([128 * (i % 2)])) for i, r in enumerate(runs)]
    df = spark.createDataFrame(rows, "i int, ids binary, data binary, lengths binary, doc_ids binary, no_id binary").repartition(3)
    docs = F.call_function(token_jvm.DOCS, "data", "lengths", "doc_ids", "no_id")
    packed = df.select("i", (F.call_function(token_jvm.PACK, "ids") == F.col("data")).alias("same")).collect()
    assert len(packed) == len(runs) and all(r["same"] for r in packed)
    want = {(i, None if i % 2 else i, 0, len(r), zlib.crc32(r.astype("<u4").tobytes())) for i, r in enumerate(runs)}
    assert {tuple(r) for r in df.select("i", F.inline(docs)).collect()} == want
    broken = bytearray(rows[5][2])
    broken[len(broken) // 2] ^= 16
    with pytest.raises(Exception, match="corrupt block"):
        spark.createDataFrame([(5, broken, *rows[5][3:])], "i int, data binary, lengths binary, doc_ids binary, no_id binary").select(F.inline(docs)).collect()
    assert "MapInArrow" not in queries.op2_token_output(spark, "/root/testdata/sf0.001")._jdf.queryExecution().toString()


def duck(sql, tables):
    import duckdb

    con = duckdb.connect()
    for name, path in tables.items():
        con.execute(f"CREATE VIEW {name} AS SELECT * FROM '{path}'")
    cur = con.execute(sql)
    return [x[0] for x in cur.description], cur.fetchall()


@pytest.mark.parametrize("name", sorted(oracle_sql()))
def test_sql(spark, sf, name):
    cols, rows = duck(oracle_sql()[name], {t: f"{sf}/{t}.parquet" for t in ("documents", "benchmark", "pages")})
    got = queries.queries()[name](spark, sf).select(*cols).collect()
    clean = lambda rows: Counter(tuple(round(x, 6) if isinstance(x, float) else x for x in r) for r in rows)
    assert clean(got) == clean(rows)


def test_decontamination_edges(spark):
    bench = spark.createDataFrame([("1", "one two three"), ("2", None), ("3", ""), (None, "no id here")], "item_id string, text string")
    for block in (1 << 20, 1):
        got = {(r["doc_id"], r["n_hit"], r["n_items"]) for r in decontaminate.find(edge_docs(spark), bench, block_chars=block).collect()}
        assert {(3, 3, 1), (None, 3, 0), (1, 0, 0), (4, 0, 0)} <= got
    for block in (1 << 20, 1):
        kept = decontaminate.drop_contaminated(edge_docs(spark), bench, block_chars=block)
        assert kept.columns == edge_docs(spark).columns and kept.count() == 7
        assert all(tuple(r)[5:] == tuple(range(len(CLASHES))) for r in kept.collect())
        assert decontaminate.drop_contaminated(no_docs(spark), bench, block_chars=block).count() == 0
    assert decontaminate.find(no_docs(spark), bench).count() == 0
    assert decontaminate.find(edge_docs(spark), bench.where("false")).where("contaminated").count() == 0


def test_large_benchmark_is_joined(spark, sf):
    docs, bench = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "benchmark"))
    want = sorted(map(tuple, decontaminate.find(docs, bench).collect()))
    joined = decontaminate.find(docs, bench, block_chars=1)
    assert sorted(map(tuple, joined.collect())) == want and any(r[-1] for r in want)
    plan = joined._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("documents") <= 3 and "CartesianProduct" not in plan


def brute_components(rows):
    fp = {d: simhash.fingerprint(t) for d, t in rows}
    comp = {d: d for d in fp}
    changed = True
    while changed:
        changed = False
        for a in fp:
            for b in fp:
                if bin(fp[a] ^ fp[b]).count("1") <= 2 and comp[b] < comp[a]:
                    comp[a], changed = comp[b], True
    return {(d, f"{fp[d]:016x}", comp[d]) for d in fp}


def test_simhash(spark, sf):
    rows = [tuple(r) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()]
    assert {tuple(r) for r in queries.op4_simhash(spark, sf).collect()} == brute_components(rows)
    got = {(r["doc_id"], r["component_id"]) for r in simhash.components(edge_docs(spark)).collect()}
    assert {(1, 1), (2, 1), (7, 1), (3, 3)} <= got
    kept = simhash.keep_first(edge_docs(spark))
    assert kept.columns == edge_docs(spark).columns
    assert simhash.components(no_docs(spark)).count() == 0
    chain = spark.createDataFrame([((1 << i) - 1,) for i in range(0, 64, 2)] + [(-1,)], "fp long")
    labels = simhash.label(simhash.links(chain)).collect()
    assert len(labels) == 33 and len({r["label"] for r in labels}) == 1


def test_one_row_of_each_component_stays(spark):
    a, b = "alpha beta gamma delta", "one two three four five six"
    rows = [(3, a, "x"), (5, a, "x"), (5, b, "x"), (9, b, "x"), (7, "solo text here", "x"), (7, "solo text here", "y"), (None, "no id at all", "x"), (None, "no id at all", "x")]
    kept = simhash.keep_first(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()
    assert Counter((r["doc_id"], r["text"]) for r in kept) == Counter([(3, a), (5, b), (7, "solo text here"), (None, "no id at all")])


def test_pipeline_drops_near_copies(spark):
    import random

    import corpus_pipeline
    from alignspark.llm import near_copies

    rnd = random.Random(4)
    texts = [[f"w{rnd.randrange(5000)}" for _ in range(100)] for _ in range(8)]
    rows = [(10 * k, " ".join(t)) for k, t in enumerate(texts)]
    rows += [(10 * k + 1, " ".join([*t[:50], "changed", *t[51:]])) for k, t in enumerate(texts)]
    rows += [(200, None), (201, ""), (202, " \n")]
    kept = corpus_pipeline.near_duplicates(spark, spark.createDataFrame(rows, "doc_id long, text string"), "").collect()
    assert sorted(r["doc_id"] for r in kept) == [*range(0, 80, 10), 200]
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text").where("length(text) < 600")
    sets = {r["doc_id"]: set(near_copies.shingles(r["text"]).tolist()) for r in docs.collect()}
    family = {d: d for d in sets}
    for _ in sets:
        for a in sets:
            for b in sets:
                if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]) - 1e-9:
                    family[a] = family[b] = min(family[a], family[b])
        if all(family[family[a]] == family[a] for a in sets):
            break
    assert {(r["doc_id"], r["family"]) for r in near_copies.families(docs).collect()} == set(family.items())


def test_urls(spark):
    rows = [(1, None), (2, "no scheme"), (3, "HTTP://A.Example.COM/en/71?x"), (4, "x://adult-x.example.org"), (5, "x://b.net/de/"), (6, "://"), (6, "://"), (7, "a://b://c#d"), (8, "x://h.example.net/de/8\ny")]
    pages = spark.createDataFrame([(*r, "<p>", 1) for r in rows], "page_id long, url string, html string, hit int")
    listed = spark.createDataFrame([(x,) for x in [*queries.LISTED, None]], "canon string")
    for limit in (1 << 20, 0):
        got = sorted((r["page_id"], r["host"], r["path"], r["rule"], r["verdict"]) for r in url_filter.filter_urls(pages, queries.RULES, listed, max_filter_bytes=limit).collect())
        assert got == [
            (1, "", "", None, "allow"), (2, "", "", None, "allow"), (3, "a.example.com", "/en/71", "example.com/en/7", "allow"), (4, "adult-x.example.org", "", None, "block"),
            (5, "b.net", "/de/", "net/de/", "allow"), (6, "", "", None, "allow"), (6, "", "", None, "allow"), (7, "b:", "//c", None, "allow"), (8, "h.example.net", "/de/8\ny", "example.net/de/8", "block"),
        ]
    assert url_filter.filter_urls(pages.where("false"), queries.RULES, listed).count() == 0


def test_language(spark):
    got = queries.op6_language_id(spark, "/root/testdata/sf0.01")
    truth = {r["doc_id"]: r["lang"] for r in spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "lang").collect()}
    held = [r for r in got.collect() if r["held_out"]]
    assert all((zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2) == r["held_out"] for r in held)
    assert np.mean([truth[r["doc_id"]] == r["lang_pred"] for r in held]) > 0.97
    edges = {(r["doc_id"], r["lang_pred"], r["score"]) for r in langid.predict(edge_docs(spark), langid.fit(edge_docs(spark))).collect()}
    assert {(1, "und", 0.0), (2, "und", 0.0), (8, "und", 0.0)} <= edges
    assert langid.predict(no_docs(spark), langid.fit(no_docs(spark))).count() == 0


def test_pages(spark, sf):
    assert all(r["text"] and r["n_chars"] == len(r["text"]) for r in queries.op7_html_extraction(spark, sf).collect())
    page = "<html><body><nav>m</nav><div class=main-part><p>{}</p><p>b</p></div><footer>f</footer></body></html>"
    rows = [(1, None, None), (2, "", ""), (3, "x://h/1", page.format("a" * 400)), (4, "x://h/2", page.format("z" * 300)), (4, "x://h/2", page.format("z" * 300)), (5, "x://one", "just text")]
    got = sorted((r["page_id"], r["text"]) for r in html_template.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect())
    assert got == [(1, ""), (2, ""), (3, "a" * 400 + "\nb"), (4, "z" * 300 + "\nb"), (4, "z" * 300 + "\nb"), (5, "just text")]


def test_text_of_all_pages_is_template(spark):
    shapes = {
        "a": "<html><body><div>Home | About | Legal</div><div>{0}</div></body></html>",
        "b": "<html><body><p>Home | About</p><div><p>{0}</p><p>same</p></div><p>Legal</p></body></html>",
        "c": "<html><body><article><h2>Column</h2><div><p>{0}</p></div><div>Tell a friend</div></article></body></html>",
    }
    words = ["red fox", "blue hare", "old owl", "wet newt"]
    rows = [(10 * i + k, f"x://{h}/{k}", page.format(w)) for i, (h, page) in enumerate(shapes.items()) for k, w in enumerate(words)]
    rows += [(90 + k, "x://copies/1", "<html><body><div>menu</div><div>one text</div></body></html>") for k in range(4)]
    got = {r["page_id"]: r["text"] for r in html_template.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    want = {10 * i + k: text.format(w) for i, text in enumerate(("{0}", "{0}\nsame", "Column\n{0}")) for k, w in enumerate(words)}
    assert got == want | {90 + k: "menu\none text" for k in range(4)}


def test_quality(spark):
    sf = "/root/testdata/sf0.01"
    truth = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    for name, column in (("op8_quality_classifier", "predicted"), ("op9_quality_rules", "kept")):
        rows = [r for r in queries.queries()[name](spark, sf).collect() if r["doc_id"] in truth and zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2]
        assert np.mean([int(r[column]) == truth[r["doc_id"]] for r in rows]) > 0.9
    labels = spark.createDataFrame([(3, 1), (4, 0), (None, 1)], "doc_id long, quality int")
    for docs, n in ((edge_docs(spark), 10), (no_docs(spark), 0)):
        assert quality.rate(docs, quality.fit_rules(docs, labels)).count() == n
        assert quality.classify(docs, quality.fit_classifier(docs, labels)).count() == n
        assert quality.keep_good(docs, quality.fit_rules(docs, labels)).columns == docs.columns


def test_mixing(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = queries.op10_mixing(spark, sf).collect()
    assert sorted(map(tuple, rows)) == sorted(map(tuple, queries.op10_mixing(spark, sf).collect()))
    assert all(r["taken"] <= 2 * r["size"] for r in rows)
    joined = mixing.plan(docs).groupBy("source", "target").sum("taken").collect()
    biggest = max(r["size"] for r in rows)
    assert all(abs(r["target"] - r["sum(taken)"]) <= biggest for r in joined)
    for rows_ in ([(1, "a b", "x")] * 7 + [(2, "a b c", "x")] * 3 + [(None, "d", "y")] * 5, [(k % 3, "w " * (k % 4), "x") for k in range(40)]):
        some = spark.createDataFrame(rows_, "doc_id long, text string, source string")
        planned, mixed = mixing.plan(some).agg({"copies": "sum", "taken": "sum"}).first(), [r["text"].split() for r in mixing.mix(some).collect()]
        assert (len(mixed), sum(map(len, mixed))) == (planned["sum(copies)"], planned["sum(taken)"])
    mixed = mixing.mix(docs)
    assert mixed.count() == sum(r["copies"] for r in rows) and mixed.columns == docs.columns
    assert mixing.plan(edge_docs(spark)).count() == 10 and mixing.plan(no_docs(spark)).count() == 0
    assert mixing.mix(edge_docs(spark)).columns == edge_docs(spark).columns
    unequal = mixing.plan(docs.withColumn("w", docs["n_chars"] / 1000), importance="w", bins=7)
    assert unequal.count() == docs.count()


def test_capped_source_is_not_ranked(spark):
    rows = [(k, "" if k else "three words here", "a") for k in range(40)] + [(100 + k, "word " * 50, "b") for k in range(4)] + [(200, "", "c")]
    got = mixing.plan(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()
    assert {(r["target"], r["copies"]) for r in got if r["source"] == "a"} == {(6.0, 2)}
    assert [r["copies"] for r in got if r["source"] == "c"] == [1]


def test_pipeline_stages_on_edges(spark):
    import corpus_pipeline

    sf = "/root/testdata/sf0.001"
    for docs in (edge_docs(spark), no_docs(spark)):
        for name, stage in corpus_pipeline.STAGES:
            out = stage(spark, docs, sf)
            rows = out.collect()
            if name != "token_ids":
                assert out.columns == docs.columns, name
                assert all(tuple(r)[5:] == tuple(range(len(CLASHES))) for r in rows), name
    near = corpus_pipeline.near_duplicates(spark, edge_docs(spark), sf).collect()
    assert Counter(r["doc_id"] for r in near) == Counter([1, 3, 4, 5, 6, 8, None])
    clean = corpus_pipeline.benchmark_decontamination(spark, edge_docs(spark), sf)
    assert clean.count() == 10


def test_pipeline(spark, sf):
    import corpus_pipeline
    from alignspark.llm import near_copies

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    kept = {r["doc_id"]: r["text"] for r in docs.collect()}
    bench = {}
    for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect():
        for w in decontaminate.windows_of(decontaminate.words_of(r["text"])):
            bench[w] = 1
    stage = docs
    for name, f in corpus_pipeline.STAGES[:-1]:
        before, stage = stage, f(spark, stage, sf)
        assert stage.columns == docs.columns, name
        got = Counter(r["doc_id"] for r in stage.collect())
        if name == "quality_rules":
            verdict = {r["doc_id"]: r["kept"] for r in queries.op9_quality_rules(spark, sf).collect()}
            assert got == Counter(d for d in kept if verdict[d])
        elif name == "near_duplicates":
            # families by brute force: five-word shingles, a similarity of 0.8 or more; the least doc_id of each stays
            sets = {r["doc_id"]: set(near_copies.shingles(r["text"]).tolist()) for r in before.collect()}
            family = {d: d for d in sets}
            linked = [(a, b) for a in sets for b in sets if a < b and len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]) - 1e-9]
            for _ in linked:
                for a, b in linked:
                    family[a] = family[b] = min(family[a], family[b])
            assert got == Counter(set(family.values()))
        elif name == "benchmark_decontamination":
            short = {w for w in bench if len(w) < 10}
            hit = lambda t: any(w in bench for w in decontaminate.windows_of(decontaminate.words_of(t))) or any(w in short for n in {len(x) for x in short} for w in decontaminate.windows_of(decontaminate.words_of(t), n))
            assert got == Counter(r["doc_id"] for r in before.collect() if not hit(r["text"]))
        else:
            copies = {r["doc_id"]: r["copies"] for r in mixing.plan(before).collect()}
            assert got == Counter({d: c for d, c in copies.items() if c})
    rows = corpus_pipeline.run(spark, sf).collect()
    assert Counter(r["doc_id"] for r in rows) == got
    assert sum(r["n_tokens"] for r in rows) == max(r["start"] + r["n_tokens"] for r in rows)
