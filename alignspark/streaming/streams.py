"""Streams of events and sequences: windows, sessions, late rows, duplicates, stored profiles kept up to date."""

from __future__ import annotations

import json
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import kernels as K
from ..plans.shared import new_path
from ..sources.tables import EVENTS4

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The event table as a file stream, a file a trigger; event time is a timestamp."""
    stream = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", 1).option("pathGlobFilter", "*.parquet").option("recursiveFileLookup", "true")
    return stream.parquet(f"{sf_dir}/events.parquet*").withColumn("ts", F.col("ts").cast("timestamp"))


def run(stream: DataFrame, mode: str = "append") -> DataFrame:
    """All that is there now through the stream, and its result as a table. complete: the last state; append and update: all rows."""
    spark = stream.sparkSession
    path, state = new_path(spark, "stream"), new_path(spark, "state")

    def put(df: DataFrame, epoch: int) -> None:
        df.write.mode("overwrite").parquet(path if mode == "complete" else f"{path}/epoch={epoch}")

    query = stream.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", state).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(path) if mode == "complete" else spark.read.schema(stream.schema).option("recursiveFileLookup", "true").parquet(path)


def tumbling(stream: DataFrame, width: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", "2 hours").groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.date_format("w.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "event_type", "n")


def sliding(stream: DataFrame, width: str = "2 hours", step: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", "2 hours").groupBy(F.window("ts", width, step).alias("w")).agg(F.count("*").alias("n")).select(F.date_format("w.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


def session_sequences(stream: DataFrame, gap: str = "12 hours") -> DataFrame:
    """A sequence for each session of a user's events: symbols in time order."""
    pairs = [F.lit(x) for kv in EVENTS4.items() for x in kv]
    symbol = F.create_map(*pairs)[F.col("event_type")]
    rows = stream.withWatermark("ts", "2 hours").select("user_id", "ts", "event_id", symbol.alias("symbol")).where("symbol IS NOT NULL")
    made = rows.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.array_sort(F.collect_list(F.struct("ts", "event_id", "symbol"))).alias("x"))
    return made.select("user_id", F.date_format("w.start", "yyyy-MM-dd HH:mm:ss").alias("start"), F.array_join(F.transform("x", lambda e: e["symbol"]), "").alias("seq"))


def deduplicated(stream: DataFrame) -> DataFrame:
    return stream.withWatermark("ts", "2 hours").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id", "event_type")


def in_time(stream: DataFrame, delay: str = "30 minutes") -> DataFrame:
    """Hourly counts in append mode: windows come out once the watermark has passed them, and later rows no longer count."""
    return stream.withWatermark("ts", delay).groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count("*").alias("n")).select(F.date_format("w.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


STATE = "rows int, symbols string, counts string"
UPDATED = "family string, rows int, width int, consensus string"


def profile_updates(sequences: DataFrame, options: K.Options | None = None) -> DataFrame:
    """Running profiles: each new sequence is merged into its family's stored profile, which is all the state there is.

    State is one count for each symbol and position: it grows with the alignment's width, not with the number of sequences.
    """
    o = options or K.Options(tie="first")

    def update(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        rows, symbols, counts = state.get if state.exists else (0, '["_"]', "[]")
        symbols, counts = json.loads(symbols), np.array(json.loads(counts), np.int64)
        for frame in frames:
            for seq in frame.sort_values("seq_id")["seq"]:
                every = sorted({*symbols, *seq})
                wide = np.zeros((len(counts), len(every)), np.int64)
                if len(counts):
                    wide[:, [every.index(c) for c in symbols]] = counts
                new = np.zeros((len(seq), len(every)), np.int64)
                new[np.arange(len(seq)), [every.index(c) for c in seq]] = 1
                symbols = every
                counts = K.merge_columns(wide, new, symbols, o, str(key[0]), rows)[2] if rows else new
                rows += 1
        state.update((rows, json.dumps(symbols), json.dumps(counts.tolist())))
        text = "".join(symbols[k] for k in K.consensus(counts, symbols, o.tie if o.tie != "partner" else "first", o.seed, str(key[0]), rows)) if len(counts) else ""
        yield pd.DataFrame([(key[0], rows, len(counts), text)], columns=["family", "rows", "width", "consensus"])

    return sequences.groupBy("family").applyInPandasWithState(update, UPDATED, STATE, "update", "NoTimeout")


def sequence_stream(spark: SparkSession, seqs: DataFrame) -> DataFrame:
    """A table of sequences, written out and read as a file stream."""
    path = new_path(spark, "sequences")
    seqs.select("family", "seq_id", "seq").write.parquet(path)
    return spark.readStream.schema("family string, seq_id bigint, seq string").parquet(path)


def with_stored(stream: DataFrame, stored: DataFrame) -> DataFrame:
    """Stream-static join: each arriving sequence beside its family's stored consensus."""
    return stream.join(stored.select("family", "consensus"), "family").select("family", "seq_id", F.levenshtein("seq", "consensus").alias("distance"))
