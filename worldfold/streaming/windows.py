"""World aggregates over event-time windows, each window released once.

Windows close by watermark and come out in append mode; updating modes would release a window again and again and are
refused. Key, secret world and posterior mode stay for the run, and noise depends on key, window and group alone, so a
replayed batch releases the same values. What a batch has cost and the posterior it leaves are written beside the stream's
checkpoint before its rows are given out, so a restarted run neither charges a replayed batch again nor forgets a batch.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.types import StructType

from worldfold.context import BudgetLedger, QueryContext
from worldfold.functions import aggregates as A
from worldfold.functions.masks import world_mask
from worldfold.functions.release import release, release_sequential


def source(spark: SparkSession, path: str, schema: StructType, files_per_batch: int = 1, pattern: str | None = None) -> DataFrame:
    """Parquet files that arrive in a folder, as a stream."""
    r = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch)
    return (r.option("pathGlobFilter", pattern) if pattern else r).parquet(path)


def windowed(events: DataFrame, unit: str, ctx: QueryContext, time: str = "ts", width: str = "1 day", slide: str | None = None, late: str = "1 hour", group: tuple[str, ...] = (), value: str | None = None) -> DataFrame:
    """start, end, group, count (vector) and, with ``value``, total (vector) of every window.

    Works on a stream and on a table alike; on a table the watermark does nothing.
    """
    if unit in group:
        raise PermissionError("the unit's key can't be a group")
    e = events.withWatermark(time, late).withColumn("__mask", world_mask(unit, ctx=ctx)).where("__mask is not null")
    w = F.window(time, width, slide) if slide else F.window(time, width)
    aggs = [A.world_count("__mask").alias("count")] + ([A.world_sum("__mask", value).alias("total")] if value else [])
    out = e.groupBy(w.alias("w"), *group).agg(*aggs)
    vectors = [A.scaled(F.col(c), ctx).alias(c) for c in ("count", *(("total",) if value else ()))]
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *group, *vectors)


def released(windows: DataFrame, ctx: QueryContext, group: tuple[str, ...] = ()) -> DataFrame:
    vectors = [c for c in ("count", "total") if c in windows.columns]
    return windows.select("start", "end", *group, *[release(v, ctx, v, "start", *group).alias(v) for v in vectors])


class Charges:
    """A stream's record of what its batches have cost and told: one small file a batch in a folder that machines share."""

    def __init__(self, spark: SparkSession, folder: str):
        self.spark, self.folder = spark, folder.rstrip("/")
        self.rows: dict[int, tuple[int, list[float] | None]] = {}
        path = spark._jvm.org.apache.hadoop.fs.Path(self.folder)
        if path.getFileSystem(spark._jsc.hadoopConfiguration()).exists(path):
            for r in spark.read.schema(self.SCHEMA).parquet(f"{self.folder}/*").collect():  # one row a batch
                self.rows[r["batch"]] = (r["cells"], r["posterior"])

    SCHEMA = "batch long, cells long, posterior array<double>"

    def before(self, batch: int) -> list[float] | None:
        """The posterior that the batches before this one have left."""
        told = [i for i, (_, p) in self.rows.items() if i < batch and p is not None]
        return self.rows[max(told)][1] if told else None

    def write(self, batch: int, cells: int, posterior: list[float] | None) -> None:
        self.spark.createDataFrame([(batch, cells, posterior)], self.SCHEMA).coalesce(1).write.mode("overwrite").parquet(f"{self.folder}/batch-{batch}")
        self.rows[batch] = (cells, posterior)


def run(windows: DataFrame, ctx: QueryContext, sink: Callable[[DataFrame, int], None], checkpoint: str, group: tuple[str, ...] = (), ledger: BudgetLedger | None = None, mode: str = "append", once: bool = True) -> StreamingQuery:
    """Starts releasing closed windows to ``sink(batch, id)``; cells are charged with the batch's id before they are given out.

    The charges of an earlier run on the same checkpoint are entered into ``ledger`` first, where it does not have them.
    With a sequential posterior a batch's cells are released one after the other (keys in order), calibrated to what all
    windows before have told; a replayed batch starts from the posterior it started from at first.
    """
    if mode != "append":
        raise PermissionError("a window may be released once only: append mode")
    vectors = [c for c in ("count", "total") if c in windows.columns]
    charges = Charges(windows.sparkSession, f"{checkpoint.rstrip('/')}/charges")
    what = f"{checkpoint}: batch "

    def enter(i: int, cells: int) -> None:
        if ledger is not None and cells and all(e.what != f"{what}{i}" for e in ledger.entries):
            ledger.charge(f"{what}{i}", cells, ctx.mi, adaptive=ctx.adaptive)

    for i, (cells, _) in sorted(charges.rows.items()):
        enter(i, cells)

    def batch(df: DataFrame, i: int) -> None:
        if ctx.adaptive:
            start = charges.before(i)
            rows = release_sequential(df, ["start", "end", *group], vectors, ctx, start=start, carry=True).persist()
            last = rows.where("__posterior IS NOT NULL").orderBy(F.desc("__place")).select("__posterior").first()
            after, out = (list(last[0]) if last else start), rows.drop("__posterior", "__place")
        else:
            rows = released(df, ctx, group).persist()
            after, out = None, rows
        cells = rows.count() * len(vectors)
        enter(i, cells)
        if i not in charges.rows:
            charges.write(i, cells, after)
        sink(out, i)
        rows.unpersist()

    w = windows.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).foreachBatch(batch)
    return (w.trigger(availableNow=True) if once else w).start()
