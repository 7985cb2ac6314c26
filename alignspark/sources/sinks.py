"""Writers of sequences, alignments, trees and distances."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def to_parquet(df: DataFrame, path: str, buckets: int = 64) -> None:
    """Parquet by bucket of family, so that a family's rows lie together and a family reads one bucket."""
    df.withColumn("bucket", F.pmod(F.xxhash64("family"), F.lit(buckets)).cast("int")).repartition("bucket").write.partitionBy("bucket").parquet(path)


def to_fasta(df: DataFrame, path: str, column: str = "seq") -> None:
    """One record a row: ">id", then the sequence, gaps and all."""
    df.select(F.concat(F.lit(">"), F.col("seq_id").cast("string"), F.lit("\n"), F.col(column)).alias("value")).write.text(path)


def newick_lines(trees: DataFrame) -> DataFrame:
    return trees.select(F.concat_ws("\t", "family", "newick").alias("value"))


def lower_triangle(distances: DataFrame) -> DataFrame:
    """family, i, line: the distances of sequence i to all smaller ids, in their order."""
    rows = distances.groupBy("family", F.col("j").alias("i")).agg(F.array_sort(F.collect_list(F.struct(F.col("i").alias("k"), F.round("distance", 6).alias("d")))).alias("x"))
    return rows.select("family", "i", F.concat_ws(" ", F.col("i").cast("string"), F.array_join(F.transform("x", lambda e: e["d"].cast("string")), " ")).alias("line"))


def blocks(aligned: DataFrame, width: int = 60) -> DataFrame:
    """family, block, seq_id, line: aligned rows cut into blocks of so many columns."""
    n = F.ceil(F.length("aligned") / width).cast("int")
    cut = aligned.select("family", "seq_id", "aligned", F.explode(F.sequence(F.lit(0), F.greatest(n - 1, F.lit(0)))).alias("block"))
    return cut.select("family", "block", "seq_id", F.concat_ws(" ", F.rpad(F.col("seq_id").cast("string"), 10, " "), F.expr(f"substring(aligned, block * {width} + 1, {width})")).alias("line"))


def to_noop(df: DataFrame) -> None:
    """Runs the plan and writes nowhere: for timing."""
    df.write.format("noop").mode("overwrite").save()


def numbered(df: DataFrame) -> DataFrame:
    return df.withColumn("line_no", F.row_number().over(Window.partitionBy("family").orderBy("seq_id")))
