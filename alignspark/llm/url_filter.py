"""URL filter: ordered allow/block rules, then a list of canonical URLs behind a blocked Bloom filter.

Edge cases: a null url, or one without "://", has an empty host and path, fits no rule and is never listed, so it is
allowed. Repeated rows are judged alike and all stay. Extra columns are ignored. An empty table gives an empty result.
Very long urls are read whole. A rule list is a bounded parameter; the URL list may be of any size.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower

#: Bytes of Bloom filter that are broadcast at most; a longer list gets fewer bits a key, and the exact join more to do.
MAX_FILTER_BYTES = 32 << 20
WORDS_PER_BLOCK, BITS_PER_KEY, PROBES = 8, 16, 8


@dataclass(frozen=True)
class Rule:
    """host and all its subdomains, with paths that start with path."""

    verdict: str
    host: str
    path: str

    @property
    def text(self) -> str:
        return self.host + self.path


def split_url(url: Column) -> tuple[Column, Column]:
    """(host in lower case, path) of a url; both empty for a null url or one without "://"."""
    rest = F.when(F.instr(url, "://") > 0, F.regexp_replace(url, r"(?s)^.*?://", "")).otherwise(F.lit(""))
    return ascii_lower(F.regexp_extract(rest, r"^([^/?#]*)", 1)), F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)


def rule_of(host: Column, path: Column, rules: list[Rule]) -> tuple[Column, Column]:
    """(text, verdict) of the longest rule that fits, nulls if none does; of equally long ones the longer host wins."""
    text, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for r in sorted(rules, key=lambda r: (len(r.text), len(r.host), r.text)):
        fits = ((host == r.host) | host.endswith("." + r.host)) & path.startswith(r.path)
        text, verdict = F.when(fits, r.text).otherwise(text), F.when(fits, r.verdict).otherwise(verdict)
    return text, verdict


def lookups(host: Column, path: Column) -> Column:
    """Canonical URLs by which a page may be listed: its own, and the root of its host and of each parent domain."""
    labels = F.split(host, r"\.")
    roots = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.concat(F.array_join(F.slice(labels, i, F.size(labels)), "."), F.lit("/")))
    return F.when(host == "", F.array().cast("array<string>")).otherwise(F.array_union(F.array(F.concat(host, path)), roots))


class BlockedBloom:
    """Bloom filter whose bits of one key lie in one block of 512 bits, so that a probe touches one cache line."""

    def __init__(self, words: np.ndarray) -> None:
        self.words = words

    @staticmethod
    def blocks_for(n: int) -> int:
        return max(1, -(-n * BITS_PER_KEY // (64 * WORDS_PER_BLOCK)))

    @classmethod
    def build(cls, hashes: DataFrame, blocks: int) -> BlockedBloom:
        """From a DataFrame with a long column h: bits are OR-ed by block on the executors."""
        bit = lambda i: F.expr(f"pmod(shiftrightunsigned(xxhash64(h), {7 * i}), 512)")
        word = lambda j: F.reduce(F.array(*[bit(i) for i in range(PROBES)]), F.lit(0).cast("long"), lambda a, b: F.when(F.floor(b / 64) == j, a.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("long"), F.pmod(b, F.lit(64)).cast("int")))).otherwise(a))
        rows = (
            hashes.select(F.pmod("h", F.lit(blocks)).alias("block"), *[word(j).alias(f"w{j}") for j in range(WORDS_PER_BLOCK)])
            .groupBy("block").agg(*[F.bit_or(f"w{j}").alias(f"w{j}") for j in range(WORDS_PER_BLOCK)])
            .toPandas()
        )
        words = np.zeros((blocks, WORDS_PER_BLOCK), np.uint64)
        if len(rows):
            words[rows["block"].to_numpy(np.int64)] = rows[[f"w{j}" for j in range(WORDS_PER_BLOCK)]].to_numpy(np.int64).view(np.uint64)
        return cls(words)

    def may_hold(self, h: np.ndarray, again: np.ndarray) -> np.ndarray:
        """h: keys; again: Spark's xxhash64 of them, from which the bits come."""
        block, found = np.mod(h, len(self.words)), np.ones(len(h), bool)
        for i in range(PROBES):
            bit = (again.view(np.uint64) >> np.uint64(7 * i)) % np.uint64(512)
            found &= (self.words[block, (bit // np.uint64(64)).astype(np.int64)] >> (bit % np.uint64(64))) & np.uint64(1) == 1
        return found


def listed_urls(pages: DataFrame, listed: DataFrame, url: str = "url", max_filter_bytes: int = MAX_FILTER_BYTES) -> DataFrame:
    """Distinct urls of pages that are on the list (column canon: canonical URLs, host root entries cover a whole host)."""
    wanted = listed.select("canon").where(F.col("canon").isNotNull()).distinct()
    seen = pages.select(F.col(url).alias("url")).where(F.col("url").isNotNull()).distinct()
    looked = seen.select("url", F.explode(lookups(*split_url(F.col("url")))).alias("canon")).withColumn("h", F.xxhash64("canon"))
    n = wanted.count()
    blocks = max(1, min(BlockedBloom.blocks_for(n), max_filter_bytes // 64))
    bloom = BlockedBloom.build(wanted.select(F.xxhash64("canon").alias("h")), blocks)
    held = pages.sparkSession.sparkContext.broadcast(bloom.words)

    @F.pandas_udf("boolean")
    def may_hold(h: pd.Series, again: pd.Series) -> pd.Series:
        return pd.Series(BlockedBloom(held.value).may_hold(h.to_numpy(np.int64), again.to_numpy(np.int64)))

    looked = looked.where(may_hold("h", F.xxhash64("h")))
    return looked.join(wanted.hint("shuffle_hash"), "canon", "left_semi").select("url").distinct()


def filter_urls(pages: DataFrame, rules: list[Rule], listed: DataFrame, **kw) -> DataFrame:
    """page_id, url, host, path, rule, verdict of every page: the longest rule decides, else the list blocks, else allow."""
    slim = pages.select("page_id", "url")
    host, path = split_url(F.col("url"))
    rule, said = rule_of(F.col("host"), F.col("path"), rules)
    hits = listed_urls(slim, listed, **kw).withColumnRenamed("url", "hit")
    return (
        slim.withColumns({"host": host, "path": path}).withColumns({"rule": rule, "said": said})
        .join(hits, F.col("url") == F.col("hit"), "left")
        .select("page_id", "url", "host", "path", "rule", F.coalesce("said", F.when(F.col("hit").isNotNull(), "block").otherwise("allow")).alias("verdict"))
    )
