"""Sequences from ordinary tables: one shuffle by sequence, the order inside a sequence by sorting its own array."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.columns import fold_letters

#: The printed input set and the rows printed for it.
PRINTED = ["ACGTACT", "ACTACG", "ATGGATACTAACTCGG", "ATGGCTAGT", "ATGCTCCGGCAAAGG", "ATGCTGG", "ATCGACAGTGTCA"]
PRINTED_ROWS = ["ACGTAC_T________", "A_CTAC_G________", "ATGGATACTAACTCGG", "ATGG___CTA_GT___", "ATGCTCCGGCAAAGG_", "ATGCT___GG______", "ATCGACAGT__GTCA_"]
PROFILE_ROWS = ["AGT_C", "AGTGC", "ATTG_", "TG_GT"]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def sequences_from(df: DataFrame, family: Column, seq_id: Column, order: list[str], symbol: Column, mapping: dict[str, str] | None = None) -> DataFrame:
    """family, seq_id, seq, len: symbols (translated by mapping; unnamed ones dropped) of each sequence in order."""
    if mapping is not None:
        pairs = [F.lit(x) for kv in mapping.items() for x in kv]
        symbol = F.create_map(*pairs)[symbol]
    rows = df.select(family.cast("string").alias("family"), seq_id.cast("bigint").alias("seq_id"), *order, symbol.alias("__symbol")).where(F.col("__symbol").isNotNull())
    made = rows.groupBy("family", "seq_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct(*order, "__symbol"))), lambda x: x["__symbol"]), "").alias("seq"))
    return made.withColumn("len", F.length("seq"))


def printed(spark: SparkSession, rows: list[str] | None = None, family: str = "printed", name: str = "seq") -> DataFrame:
    df = spark.createDataFrame([(family, i, s) for i, s in enumerate(rows or PRINTED)], f"family string, seq_id bigint, {name} string")
    return df.withColumn("len", F.length("seq")) if name == "seq" else df


def orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """T1: a customer's order priorities; families are blocks of 7 customers."""
    df = table(spark, sf_dir, "orders")
    mapping = {"1-URGENT": "A", "2-HIGH": "C", "3-MEDIUM": "G", "4-NOT SPECIFIED": "T"}
    return sequences_from(df, F.expr("o_custkey div 7"), F.col("o_custkey"), ["o_orderdate", "o_orderkey"], F.col("o_orderpriority"), mapping)


EVENTS4 = {"view": "A", "click": "C", "purchase": "G", "signup": "T"}
EVENTS5 = {"view": "V", "click": "C", "purchase": "P", "signup": "S", "error": "E"}


def events(spark: SparkSession, sf_dir: str, mapping: dict[str, str] | None = None) -> DataFrame:
    """T2 and T3: a user's events; families are blocks of 5 users."""
    return sequences_from(table(spark, sf_dir, "events"), F.expr("user_id div 5"), F.col("user_id"), ["ts", "event_id"], F.col("event_type"), mapping or EVENTS4)


def lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    """T4: return flag and line status of a supplier's items; families are blocks of 5 suppliers."""
    df = table(spark, sf_dir, "lineitem")
    order = ["l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_extendedprice"]
    return sequences_from(df, F.expr("l_suppkey div 5"), F.col("l_suppkey"), order, F.concat("l_returnflag", "l_linestatus"), {"AF": "A", "AO": "C", "RF": "G", "RO": "T"})


def conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """T7: first letters of a conversation's roles; families are blocks of 10 conversations."""
    return sequences_from(table(spark, sf_dir, "conversations"), F.expr("conv_id div 10"), F.col("conv_id"), ["turn"], F.substring("role", 1, 1))


def segments(spark: SparkSession, sf_dir: str) -> DataFrame:
    """T10: first letters of a nation's customer segments; families are blocks of 5 nations."""
    return sequences_from(table(spark, sf_dir, "customer"), F.expr("c_nationkey div 5"), F.col("c_nationkey"), ["c_custkey"], F.substring("c_mktsegment", 1, 1))


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """T5's raw form: folded letters of a document, all in one family; near_copies() splits it."""
    df = table(spark, sf_dir, "documents").select(F.lit("documents").alias("family"), F.col("doc_id").alias("seq_id"), fold_letters(F.col("text")).alias("seq"))
    return df.withColumn("len", F.length("seq"))


def benchmark(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Folded letters of a benchmark item: the root sequences of T6."""
    df = table(spark, sf_dir, "benchmark").select(F.col("item_id").cast("string").alias("family"), F.lit(0).cast("bigint").alias("seq_id"), fold_letters(F.col("text")).alias("seq"))
    return df.withColumn("len", F.length("seq"))


def embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """T8: an embedding's 64 numbers cut at -0.1, 0 and 0.1 into four symbols; families are the labels, all rows of one length."""
    cut = lambda x: F.when(x < -0.1, "A").when(x < 0, "C").when(x < 0.1, "G").otherwise("T")
    df = table(spark, sf_dir, "embeddings").select(F.col("label").cast("string").alias("family"), F.col("vec_id").alias("seq_id"), F.array_join(F.transform("embedding", cut), "").alias("seq"))
    return df.withColumn("len", F.length("seq"))


def embedding_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """family, seq_id, aligned: the same with numbers near 0 as gaps, so that columns hold letters and gaps."""
    cut = lambda x: F.when(x < -0.1, "A").when(x < -0.03, "C").when(x < 0.03, "_").when(x < 0.1, "G").otherwise("T")
    return table(spark, sf_dir, "embeddings").select(F.col("label").cast("string").alias("family"), F.col("vec_id").alias("seq_id"), F.array_join(F.transform("embedding", cut), "").alias("aligned"))


def nested_distances(spark: SparkSession, sf_dir: str) -> DataFrame:
    """family, i, j, distance: suppliers in blocks of 16, as far apart as the least of nested blocks that holds both is wide."""
    df = table(spark, sf_dir, "supplier").select(F.col("s_suppkey").cast("bigint").alias("i")).withColumn("family", F.expr("cast(i div 16 as string)"))
    wide = F.expr("CASE WHEN i div 2 = j div 2 THEN 2.0D WHEN i div 4 = j div 4 THEN 4.0D WHEN i div 8 = j div 8 THEN 8.0D ELSE 16.0D END")
    return df.join(df.withColumnRenamed("i", "j"), "family").where("i < j").select("family", "i", "j", wide.alias("distance"))


def page_tags(spark: SparkSession, sf_dir: str) -> DataFrame:
    """T9: family, seq_id, tokens: the names of a page's start tags in order; families are the hosts."""
    host = F.regexp_extract("url", r"^[a-z]+://([^/?#]*)", 1)
    return table(spark, sf_dir, "pages").select(host.alias("family"), F.col("page_id").alias("seq_id"), F.regexp_extract_all("html", F.lit(r"<([a-z][a-z0-9]*)"), F.lit(1)).alias("tokens"))


def tokens_to_sequences(tokens: DataFrame) -> DataFrame:
    """Token sequences as strings: each distinct token of a family becomes one private character, by token order.

    What is joined back is one row for each family and distinct token."""
    from pyspark.sql import Window

    each = tokens.select("family", "seq_id", F.posexplode("tokens").alias("pos", "token"))
    known = each.select("family", "token").distinct().withColumn("code", F.row_number().over(Window.partitionBy("family").orderBy("token")))
    each = each.join(known, ["family", "token"]).withColumn("symbol", F.decode(F.unhex(F.lpad(F.hex(F.col("code") + 0xE000), 4, "0")), "UTF-16BE"))
    return sequences_from(each, F.col("family"), F.col("seq_id"), ["pos"], F.col("symbol"))


def fasta(spark: SparkSession, path: str, family: str = "fasta") -> DataFrame:
    """Sequences of FASTA text: a record from each ">" to the next; lines of a record are joined."""
    rows = spark.read.text(path, lineSep=">").where(F.trim("value") != "")
    head, body = F.substring_index("value", "\n", 1), F.expr("substring(value, instr(value, '\n') + 1)")
    df = rows.select(F.lit(family).alias("family"), F.regexp_extract(head, r"^(\d+)", 1).cast("bigint").alias("seq_id"), F.regexp_replace(body, r"\s", "").alias("seq"))
    return df.withColumn("len", F.length("seq"))


def read_csv(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("family string, seq_id bigint, seq string, len int").csv(path, header=True)


def read_json(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("family string, seq_id bigint, seq string, len int").json(path)
