"""Helpers that the corpus operators share."""

from __future__ import annotations

import tempfile
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: A word is a run of anything but these characters.
SPACE = r"\x20\x09-\x0D"


def cut(df: DataFrame) -> DataFrame:
    """Write ``df`` to the shared checkpoint folder and cut its lineage.

    The folder is the session's ``spark.checkpoint.dir``. Where there is none a session of one machine (tests) gets a
    temporary one; on a cluster, whose machines do not share such a folder, that is an error.
    """
    sc = df.sparkSession.sparkContext
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        folder = df.sparkSession.conf.get("spark.checkpoint.dir", None)
        if not folder and not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all machines share")
        sc.setCheckpointDir(folder or tempfile.mkdtemp(prefix="worldfold-"))
    return df.checkpoint(eager=True)


def small(df: DataFrame, rows: int = 200_000) -> DataFrame:
    """``df`` (a cut table of narrow rows) with a broadcast hint if it is counted to have ``rows`` at most, else as it is."""
    return F.broadcast(df) if df.count() <= rows else df


@contextmanager
def small_batches(spark: SparkSession, rows: int = 1000) -> Iterator[None]:
    """Jobs run within it hand texts to Python by so many rows at once; the session's setting is put back."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, rows)
    try:
        yield
    finally:
        spark.conf.set(name, before)


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def word_count(text: Column) -> Column:
    """Number of words of a text, null as 0; only one letter a word is kept while counting."""
    one = F.regexp_replace(text, rf"[{SPACE}]*+[^{SPACE}]++", "x")
    return F.coalesce(F.length(F.translate(one, " \t\n\x0b\x0c\r", "")), F.lit(0)).cast("long")


def buckets_for(rows: int, each: int = 50_000) -> int:
    """How many buckets keep about ``each`` rows together."""
    return max(1, -(-rows // each))


def running(df: DataFrame, group: list[str], bucket: str, order: list[Column], value: Column, out: str) -> DataFrame:
    """Adds the exclusive running sum of ``value`` within ``group``, in the order of ``bucket`` and then ``order``.

    Only a bucket is sorted in one task: totals by bucket are summed first, so a group that holds most rows is spread over
    as many tasks as it has buckets. ``df`` is read twice and should be cut. Null group values form a group.
    """
    keys = [*group, bucket]
    base = f"__{out}_base"
    before = Window.partitionBy(*group).orderBy(bucket).rowsBetween(Window.unboundedPreceding, -1)
    sums = df.groupBy(*keys).agg(F.sum(value).alias("__total")).withColumn(base, F.coalesce(F.sum("__total").over(before), F.lit(0)))
    sums = sums.select(*[F.col(c).alias(f"__g{i}") for i, c in enumerate(keys)], base)
    same = [F.col(c).eqNullSafe(F.col(f"__g{i}")) for i, c in enumerate(keys)]
    on = same[0]
    for s in same[1:]:
        on = on & s
    here = Window.partitionBy(*keys).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    joined = df.join(sums, on, "left").drop(*[f"__g{i}" for i in range(len(keys))])
    return joined.withColumn(out, F.coalesce(F.sum(value).over(here), F.lit(0)) + F.col(base)).drop(base)

