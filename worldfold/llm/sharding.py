"""Sharding by sampled splitters: shards of nearly equal bytes, each a run of key ranges."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from worldfold.llm.common import buckets_for, cut, documents, running

#: Keys drawn for the splitters, and ranges made of them; both bounded.
SAMPLE, RANGES, MOST_RANGES = 1 << 16, 2048, 1 << 16
LOW = (1 << 24) - 1


def splitters(rows: DataFrame, total: int, ranges: int, sample: int = SAMPLE) -> np.ndarray:
    """At most ``ranges`` - 1 splitters: quantiles of a sample of keys drawn in proportion to their sizes.

    Each row draws, by hash, an exponential number of rate its size; those under sample/total are the sample, which is
    expected to be no more than ``sample`` keys however many tasks there are. Between splitters of different texts the
    cut is moved to the first key of the text, so its copies stay together; only a text that fills more than a range is
    cut within.
    """
    draw = -F.log((F.pmod(F.xxhash64("key", "crc", F.lit(7)), F.lit(1 << 52)) + 0.5) / float(1 << 52)) / F.col("size")
    keys = np.array(sorted(r[0] for r in rows.where(draw < sample / max(1, total)).select("k").collect()), np.int64)
    if not len(keys):
        return keys
    cuts = keys[[len(keys) * i // ranges for i in range(1, ranges)]] if len(keys) > ranges else keys
    text = cuts & ~LOW
    again = np.concatenate(([False], text[1:] == text[:-1]))
    return np.unique(np.where(again, cuts, text))


def with_range(rows: DataFrame, cuts: np.ndarray) -> DataFrame:
    held = rows.sparkSession.sparkContext.broadcast(cuts)  # at most MOST_RANGES numbers

    @F.pandas_udf("int")
    def find(k: pd.Series) -> pd.Series:
        return pd.Series(np.searchsorted(held.value, k.to_numpy(), side="right").astype(np.int32))

    return rows.withColumn("range", find("k"))


def shard(docs: DataFrame, key: str = "doc_id", text: str = "text", shards: int = 8, ranges: int | None = None) -> DataFrame:
    """A row a document: key, size, text_crc32, law ('bytes'), shard, slot, grown_shard (null: this law moves rows).

    Rows are ordered by a hash of the text and then of the key, so equal texts are neighbours. Splitters sampled by size
    divide that order into many ranges; ranges that turn out more than twice the mean are divided again by a sample of
    their own. Exact bytes of the ranges (a bounded table) then say which range ends nearest to each shard's share.
    Slots number a shard's rows from 0, range by range.

    Null text: size 1, checksum of no bytes. Repeated rows are rows of their own. An empty table gives no rows. Other
    columns are ignored.
    """
    spark = docs.sparkSession
    t = F.coalesce(F.col(text), F.lit(""))
    k = F.xxhash64(t).bitwiseAND(F.lit(~LOW)).bitwiseOR(F.xxhash64(F.col(key), F.lit(3)).bitwiseAND(F.lit(LOW)))
    rows = cut(docs.select(F.col(key).alias("key"), (F.octet_length(t) + 1).cast("long").alias("size"), F.crc32(t.cast("binary")).alias("crc"), k.alias("k")))
    n, total = rows.agg(F.count("*"), F.coalesce(F.sum("size"), F.lit(0))).first()
    ranges = ranges or min(MOST_RANGES // 2, max(RANGES, buckets_for(n, 500_000)))
    cuts = splitters(rows, total, ranges)
    dealt = with_range(rows, cuts)
    sums = {r[0]: r[1] for r in dealt.groupBy("range").agg(F.sum("size")).collect()}  # at most `ranges` rows
    mean = sum(sums.values()) / max(1, len(sums))
    if over := [r for r, s in sums.items() if s > 2 * mean]:
        more = splitters(dealt.where(F.col("range").isin(over)), sum(sums[r] for r in over), min(MOST_RANGES - ranges, 4 * sum(int(sums[r] / mean) for r in over)))
        dealt = with_range(rows, np.union1d(cuts, more))
        sums = {r[0]: r[1] for r in dealt.groupBy("range").agg(F.sum("size")).collect()}
    order = sorted(sums)
    run, first = np.cumsum([sums[r] for r in order]), [0]
    for i in range(1, shards):  # the range boundary nearest to the share, never before the last
        want = total * i / shards
        j = int(np.searchsorted(run, want))
        j += j < len(run) and (j == 0 or run[j] - want < want - run[j - 1])
        first.append(max(first[-1], j))
    of = {r: sum(int(i >= f) for f in first) - 1 for i, r in enumerate(order)}
    table = spark.createDataFrame([(r, s) for r, s in of.items()], "range int, shard int")
    dealt = cut(dealt.join(F.broadcast(table), "range"))
    out = running(dealt, ["shard"], "range", [F.col("k"), F.col("key"), F.col("crc"), F.col("size")], F.lit(1), "slot")
    return out.select(F.col("key").alias(key), "size", F.col("crc").alias("text_crc32"), F.lit("bytes").alias("law"), "shard", F.col("slot").cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))


def op6_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard(documents(spark, sf_dir))
